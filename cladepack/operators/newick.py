"""Newick text and node tables."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..kernels import newick as nw

NODES = "tree_id long, node_id int, parent_id int, first int, last int, card int, is_leaf boolean, label string, length_lex string, length double"
_SCHEMA = pa.schema([("tree_id", pa.int64()), ("node_id", pa.int32()), ("parent_id", pa.int32()), ("first", pa.int32()), ("last", pa.int32()), ("card", pa.int32()), ("is_leaf", pa.bool_()), ("label", pa.string()), ("length_lex", pa.string()), ("length", pa.float64())])


def _pieces(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)


def parse_newick(trees: DataFrame, on_error: str = "fail") -> DataFrame:
    """Node table of trees (tree_id, newick), nodes in postorder, the root last. on_error: fail, or null to leave malformed
    trees out, or quarantine to keep them as one row with a null node_id and the reason as label."""

    def run(batches):
        for batch in _pieces(batches, 64):
            rows: list[list] = [[] for _ in _SCHEMA]
            for tree_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                try:
                    t = nw.parse(text)
                except nw.NewickError as e:
                    if on_error == "fail":
                        raise
                    if on_error == "quarantine":
                        for c, v in zip(rows, (tree_id, None, None, None, None, None, None, str(e), None, None), strict=True):
                            c.append(v)
                    continue
                n = len(t.label)
                new = ([tree_id] * n, range(n), t.parent, t.first, t.last, [b - a + 1 for a, b in zip(t.first, t.last, strict=True)], t.leaf, t.label, t.length, [float(x) if x is not None else None for x in t.length])
                for c, v in zip(rows, new, strict=True):
                    c.extend(v)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(rows, _SCHEMA, strict=True)], schema=_SCHEMA)

    return trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(run, NODES)


def validate_newick(trees: DataFrame) -> DataFrame:
    """(tree_id, error): the class of each tree's first error, null for sound ones."""

    def run(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([nw.error_of(x) for x in batch.column(1).to_pylist()], pa.string())], ["tree_id", "error"])

    return trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(run, "tree_id long, error string")


def write_newick(nodes: DataFrame) -> DataFrame:
    """(tree_id, newick) of node tables. A tree's nodes are gathered in one row; trees are independent."""
    packed = nodes.groupBy("tree_id").agg(F.collect_list(F.struct("node_id", "parent_id", "first", "label", "length_lex")).alias("n"))

    def run(batches):
        for batch in _pieces(batches, 64):
            texts = []
            for rows in batch.column(1).to_pylist():
                at = {r["node_id"]: i for i, r in enumerate(rows)}
                kids: list[list[int]] = [[] for _ in rows]
                root = 0
                for i, r in enumerate(rows):
                    if r["parent_id"] in at:
                        kids[at[r["parent_id"]]].append(i)
                    else:
                        root = i
                for k in kids:
                    k.sort(key=lambda i: rows[i]["first"])
                texts.append(nw.write(root, kids, [r["label"] for r in rows], [r["length_lex"] for r in rows]))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["tree_id", "newick"])

    return packed.mapInArrow(run, "tree_id long, newick string")


def canonical_newick(trees: DataFrame, labels: bool = True, lengths: bool = True) -> DataFrame:
    """(tree_id, canonical): text that is equal for equal trees, whatever the order of children."""

    def run(batches):
        for batch in _pieces(batches, 64):
            out = [nw.canonical(nw.parse(x), labels, lengths) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.string())], ["tree_id", "canonical"])

    return trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(run, "tree_id long, canonical string")


def distinct_topologies(trees: DataFrame) -> DataFrame:
    """(canonical, n_trees): rooted shapes without lengths and inner labels."""
    return canonical_newick(trees, False, False).groupBy("canonical").agg(F.count("*").alias("n_trees"))


def taxon_table(nodes: DataFrame, order: str = "first_tree", given: list[str] | None = None) -> DataFrame:
    """(taxon_idx, label). order: first_tree takes the leaf order of the tree with the least id, so its clusters are single
    runs of bits; lexicographic; or given. The number of taxa is the size of one tree, so one small table is ordered."""
    leaves = nodes.where("is_leaf")
    if order == "given":
        return nodes.sparkSession.createDataFrame(list(enumerate(given or [])), "taxon_idx int, label string")
    if order == "lexicographic":
        return leaves.select("label").distinct().select((F.row_number().over(Window.orderBy("label")) - 1).alias("taxon_idx"), "label")
    lead = leaves.agg(F.min("tree_id").alias("tree_id"))
    return leaves.join(F.broadcast(lead), "tree_id").select(F.col("first").alias("taxon_idx"), "label")


def foreign_taxa(nodes: DataFrame, taxa: DataFrame) -> DataFrame:
    """Leaves whose label is not in the table."""
    return nodes.where("is_leaf").join(F.broadcast(taxa), "label", "left_anti").select("tree_id", "label")


def newick_leaf_counts(trees: DataFrame) -> DataFrame:
    """(tree_id, n_leaves, n_inner, depth) by a tokeniser of Spark functions alone, for plain and quoted labels."""
    tokens = F.regexp_extract_all("newick", F.lit(r"'(?:[^']|'')*'|\[[^\]]*\]|[(),:;]|[^(),:;'\[\]]+"), F.lit(0))
    tok = trees.select("tree_id", F.posexplode(tokens).alias("pos", "tok")).where(~F.col("tok").startswith("[") & (F.trim("tok") != ""))
    w = Window.partitionBy("tree_id").orderBy("pos")
    step = F.when(F.col("tok") == "(", 1).when(F.col("tok") == ")", -1).otherwise(0)
    marked = tok.withColumn("before", F.lag("tok", 1, "(").over(w)).withColumn("depth", F.sum(step).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    is_leaf = F.col("before").isin("(", ",") & ~F.col("tok").isin("(", ")", ",", ":", ";")
    return marked.groupBy("tree_id").agg(F.sum(is_leaf.cast("long")).alias("n_leaves"), F.sum((F.col("tok") == "(").cast("long")).alias("n_inner"), F.max("depth").cast("long").alias("depth"))
