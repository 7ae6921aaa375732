"""Named queries over the tree engine: (spark, sf_dir) -> DataFrame, with SQL that computes the same from the tables."""

from __future__ import annotations

import re
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import sqlapi
from .kernels import codes
from .kernels import deflate as df
from .kernels import newick as nw
from .operators import clusters as cl
from .operators import codec as cd
from .operators import consensus as co
from .operators import hetero, measures
from .operators import newick as on
from .plans import forests as fo
from .plans.forests import DUCK, SPARK, run_sql, table
from .streaming import ingest

#: Taxa (None: every row of the table), trees, depth and noise of the forests over vectors and customers.
EMB = (None, 100, 24, 2)
MD5F = (None, 20, 20, 2)
_PRESET = {"emb": EMB, "md5f": MD5F}
_ROWS = {"nat": "25", "emb": "(SELECT count(*) FROM embeddings)"}
_TEXT = {"nat": fo.nat_sql, "sup": fo.sup_sql, "brand": fo.brand_sql, "evt": fo.evt_sql, "emb": lambda d: fo.emb_sql(d, *EMB), "md5f": lambda d: fo.md5_sql(d, *MD5F)}
_WIDTH = {"nat": 2, "sup": 4, "brand": 2, "evt": 2, "emb": 4, "md5f": 5}


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share. A temporary one only where none is set and one machine runs all."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir is not set")
    return "file://" + tempfile.mkdtemp(prefix="cladepack-")


def stored(made: DataFrame) -> DataFrame:
    """A table written to the shared folder and read back, for those that a query needs more than once."""
    path = f"{shared_dir(made.sparkSession)}/cladepack-tables/{uuid.uuid4().hex}"
    made.write.parquet(path)
    return made.sparkSession.read.schema(made.schema).parquet(path)


def _sql(name: str, tail: str):
    """A query and its oracle from one text over a forest."""
    return lambda spark, d: run_sql(spark, d, f"WITH {_TEXT[name](SPARK)} {tail}"), f"WITH {_TEXT[name](DUCK)} {tail}"


# --- forests as trees ---------------------------------------------------------------------------------------------


def forest(spark: SparkSession, d: str, name: str) -> DataFrame:
    return run_sql(spark, d, f"WITH {_TEXT[name](SPARK)} SELECT * FROM {name}")


def labels_of(spark: SparkSession, d: str, name: str) -> list[str]:
    if name == "nat":
        return [r[0] for r in table(spark, d, "nation").orderBy("n_nationkey").select("n_name").collect()]
    if name == "sup":
        return [f"S{r[0]}" for r in table(spark, d, "supplier").orderBy("s_suppkey").select("s_suppkey").collect()]
    if name == "brand":
        return [r[0] for r in table(spark, d, "part").select("p_brand").distinct().orderBy("p_brand").collect()]
    if name == "evt":
        return [f"B{i}" for i in range(16)]
    n = table(spark, d, "embeddings" if name == "emb" else "customer").count()
    return [f"{'V' if name == 'emb' else 'C'}{i}" for i in range(n)]


def trees_of(spark: SparkSession, d: str, name: str, side: bool = False) -> tuple[DataFrame, list[str]]:
    labels = labels_of(spark, d, name)
    if name in _PRESET and labels and (bits := fo.forest_bits(spark, d, name)) is not None:  # the SQL's trees, made without its shuffles
        return fo.prefix_forest(spark, bits, labels, *_PRESET[name][1:], _WIDTH[name]), labels
    made = forest(spark, d, name)
    if not side:
        return fo.forest_newick(made.select("tree_id", "members"), labels), labels
    leaves = run_sql(spark, d, f"WITH {_TEXT[name](SPARK)} SELECT tree_id, taxon, cents FROM {name}_leaf")
    return fo.forest_newick(made, labels, leaves), labels


def members_text(entries: DataFrame, n: int, width: int) -> DataFrame:
    """entries with the column members, as the forests write it, from bits."""

    def run(batches):
        for batch in batches:
            k = batch.schema.get_field_index("bits")
            out = [",".join(f"{x:0{width}d}" for x in np.flatnonzero(codes.unpack_bits(b, n)).tolist()) for b in batch.column(k).to_pylist()]
            yield batch.append_column("members", pa.array(out, pa.string()))

    return entries.mapInArrow(run, ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in entries.schema) + ", members string")


def key_texts(width: int, n: int):
    """A function of keys to the members of each, as the forests write them, a bounded number at a time."""
    word = [f"{x:0{width}d}" for x in range(n)]

    def texts(keys: list[bytes]) -> list[str]:
        out: list[str] = []
        for lo in range(0, len(keys), 1024):
            some = keys[lo : lo + 1024]
            row, at = codes.members_of(some)
            edges, at = np.searchsorted(row, np.arange(len(some) + 1)).tolist(), at.tolist()
            out += [",".join([word[x] for x in at[a:b]]) for a, b in zip(edges[:-1], edges[1:])]
        return out

    return texts


def restored_clusters(trees: DataFrame, labels: list[str], width: int) -> DataFrame:
    """(tree_id, members, card) of the inner clusters of trees, over the ordinals of labels."""
    entries = cd.cluster_entries(trees, labels, 1 << 30).where("length(key) > 0")
    n = len(labels)

    def run(batches):
        write = key_texts(width, n)
        for batch in batches:
            for lo in range(0, batch.num_rows, 1024):
                keys = batch.column(1).slice(lo, 1024).to_pylist()
                trees = [np.frombuffer(raw, np.int32) for raw in batch.column(2).slice(lo, 1024).to_pylist()]
                times = [len(x) for x in trees]
                texts, cards = pa.array(write(keys), pa.string()), pa.array([codes.card_of_key(x) for x in keys], pa.int32())
                at = pa.array(np.repeat(np.arange(len(keys)), times))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(trees), pa.int64()), texts.take(at), cards.take(at)], ["tree_id", "members", "card"])

    return entries.mapInArrow(run, "tree_id long, members string, card int")


def roundtrip(name: str, codec: str = "packed", block: int | None = None, **pick):
    """Clusters of the restored trees; SQL computes them from the tables, so equality proves that nothing was lost."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        trees, labels = trees_of(spark, d, name)
        size = block or cd.restorable_block(len(labels))
        return restored_clusters(cd.decompress(cd.compress(trees, codec, size), spread=size > 1, **pick), labels, _WIDTH[name])

    return run


def _nodes(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    trees, labels = trees_of(spark, d, "nat")
    nodes = on.parse_newick(trees)
    return nodes, on.taxon_table(nodes, "given", labels)


def hashes(method: str):
    """Hashes of the inner clusters of the monthly trees, by tree and cluster size."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        nodes, taxa = _nodes(spark, d)
        if method == "bottom_up":
            found = cl.hash_bottom_up(nodes, taxa).join(nodes.select("tree_id", "node_id", "card"), ["tree_id", "node_id"])
        else:
            found = cl.clusters(nodes, taxa, method)
        return found.where("card > 1 and card < 25").select("tree_id", "card", "h1", "h2", "h3")

    return run


_HASH_SQL = f"""WITH {_TEXT["nat"](DUCK)},
co AS (SELECT i AS taxon, md5('1:' || i) AS m FROM range(0, 25) t(i)),
cv AS (SELECT taxon, ('0x' || substr(m, 1, 8))::BIGINT % {cl.M1} AS a1, ('0x' || substr(m, 9, 12))::BIGINT % {cl.M2} AS a2, ('0x' || substr(m, 21, 12))::BIGINT % {cl.M3} AS a3 FROM co),
ex AS (SELECT tree_id, members, card, unnest(string_split(members, ','))::INT AS taxon FROM nat)
SELECT tree_id, card, (sum(a1) % {cl.M1})::BIGINT AS h1, (sum(a2) % {cl.M2})::BIGINT AS h2, (sum(a3) % {cl.M3})::BIGINT AS h3 FROM ex JOIN cv USING (taxon) GROUP BY tree_id, members, card"""


def bipartition_support(name: str):
    """Distinct clusters with their supports and choice of side, from the packed container."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        trees, labels = trees_of(spark, d, name)
        entries = cd.container_entries(cd.compress(trees, taxa=labels))
        total = entries.select("members", "card", F.col("n_support").cast("long").alias("n_support"), "sign", F.col("n_listed").cast("long").alias("n_listed")) if "members" in entries.columns else None
        named = members_text(entries.select("bits", "card", "n_support", "sign", "n_listed"), len(labels), _WIDTH[name])
        return total if total is not None else named.select("members", "card", F.col("n_support").cast("long").alias("n_support"), "sign", F.col("n_listed").cast("long").alias("n_listed"))

    return run


def _support_sql(name: str) -> str:
    return f"""WITH {_TEXT[name](DUCK)}, sp AS (SELECT max(tree_id) + 1 AS span FROM {name}),
g AS (SELECT members, card, count(*) AS n_support FROM {name} GROUP BY members, card)
SELECT members, card, n_support, CASE WHEN 2 * n_support > span THEN '-' ELSE '+' END AS sign, CASE WHEN 2 * n_support > span THEN span - n_support ELSE n_support END AS n_listed FROM g, sp"""


def encoded(name: str, bits_code: str = "packed", ids_code: str = "packed", side: str = "both"):
    """Codes of clusters and lists, one row for each cluster, as the codec makes them before a block is put together."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        trees, labels = trees_of(spark, d, name)
        n = len(labels)
        span = (trees.agg(F.max("tree_id")).first()[0] or 0) + 1
        entries = cd.cluster_entries(trees, labels, 1 << 30)
        rows = cd.encode_entries(entries, n, {0: span}, bits_code, ids_code, side).where("card > 0").select("key", "entry", "bits_size", "ids_size", "sign")

        def code(batches):
            write = key_texts(_WIDTH[name], n)
            for batch in batches:
                for lo in range(0, batch.num_rows, 2048):
                    keys, entry, one, two, sign = batch.slice(lo, 2048).columns
                    entry, one, two = entry.to_pylist(), one.to_pylist(), two.to_pylist()
                    ends = [[x[:a] for x, a in zip(entry, one, strict=True)], [x[len(x) - b - (bits_code == "textrun") : len(x) - (bits_code == "textrun")] for x, b in zip(entry, two, strict=True)]]
                    shown = [[x.decode() if kind == "textrun" else x.hex() for x in end] for end, kind in zip(ends, (bits_code, ids_code), strict=True)]
                    yield pa.RecordBatch.from_arrays([pa.array(write(keys.to_pylist()), pa.string()), sign, *(pa.array(x, pa.string()) for x in shown)], ["members", "sign", "bits_code", "ids_code"])

        return rows.mapInArrow(code, "members string, sign string, bits_code string, ids_code string")

    return run


_SIDE = """, sp AS (SELECT max(tree_id) + 1 AS span FROM {0}),
gr AS (SELECT members, count(*) AS n_support, list_sort(list(tree_id)) AS inset FROM {0} GROUP BY members),
ch AS (SELECT members, CASE WHEN 2 * n_support > span THEN '-' ELSE '+' END AS sign,
  CASE WHEN 2 * n_support > span THEN list_filter(range(0, span), lambda x: NOT list_contains(inset, x)) ELSE inset END AS ids FROM gr, sp),
dl AS (SELECT members, sign, list_transform(range(1, len(ids) + 1), lambda i: CASE WHEN i = 1 THEN ids[1] ELSE ids[i] - ids[i - 1] END) AS gaps FROM ch),
ms AS (SELECT *, list_transform(string_split(members, ','), lambda x: x::INT) AS m FROM dl),
bt AS (SELECT * EXCLUDE (m), array_to_string(list_transform(range(1, len(m) + 1), lambda i: repeat('0', CASE WHEN i = 1 THEN m[1] ELSE m[i] - m[i - 1] - 1 END) || '1'), '') || repeat('0', ({1} - 1 - m[len(m)])::INT) AS bits FROM ms)"""


def _textrun_sql(name: str) -> str:
    return f"""WITH {_TEXT[name](DUCK)}{_SIDE.format(name, _ROWS[name])},
rn AS (SELECT *, regexp_extract_all(bits, '0+|1+') AS runs FROM bt)
SELECT members, sign,
  array_to_string(list_transform(runs, lambda r: CASE WHEN len(r) = 1 THEN CASE WHEN r = '1' THEN 'B' ELSE 'A' END ELSE (CASE WHEN r[1] = '1' THEN 'K' ELSE 'L' END) || len(r)::VARCHAR END), '') AS bits_code,
  array_to_string(list_transform(gaps, lambda g: substr('ABCDEFGHIJ', substr(g::VARCHAR, 1, 1)::INT + 1, 1) || substr(g::VARCHAR, 2)), '') AS ids_code FROM rn"""


def _packed_ids_sql(name: str) -> str:
    """Packed list codes; the bits' code is compared in unit tests and round trips."""
    return f"""WITH {_TEXT[name](DUCK)}{_SIDE.format(name, _ROWS[name])}
SELECT members, sign, lower(array_to_string(list_transform(range(1, len(gaps) + 1), lambda i: CASE WHEN i = 1 THEN printf('%04x', gaps[i]) WHEN gaps[i] <= 255 THEN printf('%02x', gaps[i]) ELSE '00' || printf('%04x', gaps[i]) END), '')) AS ids_code FROM bt"""


def _fixed_ids_sql(name: str) -> str:
    return f"""WITH {_TEXT[name](DUCK)}{_SIDE.format(name, _ROWS[name])}
SELECT members, sign, array_to_string(list_transform(gaps, lambda g: printf('%04x', g)), '') AS ids_code FROM bt"""


def textrun_file_lines(spark: SparkSession, d: str) -> DataFrame:
    from .sources.container import textrun_lines

    trees, labels = trees_of(spark, d, "nat")
    return textrun_lines(cd.compress(trees, "textrun", taxa=labels)).where("line_no >= 1").select("line")


def _textrun_lines_sql() -> str:
    return f"""SELECT line FROM (WITH x AS ({_textrun_sql("nat").replace("AS ids_code FROM rn", "AS ids_code, len(gaps) AS k FROM rn")})
SELECT bits_code || ' ' || sign || ':' || k || ':' || ids_code AS line FROM x UNION ALL SELECT 'NTREES ' || (SELECT count(DISTINCT tree_id) FROM (WITH {_TEXT["nat"](DUCK)} SELECT * FROM nat)) UNION ALL SELECT 'NBIPARTITIONS ' || count(*) FROM x)"""


def roundtrip_nat_side(spark: SparkSession, d: str) -> DataFrame:
    """Inner nodes of the restored monthly trees with label and length in cents."""
    trees, labels = trees_of(spark, d, "nat", True)
    back = cd.decompress(cd.compress(trees, lengths="exact", labels=True, taxa=labels))
    inner = on.parse_newick(back).where("card > 1 and card < 25")
    return inner.select("tree_id", "card", "label", F.round(F.col("length") * 100).cast("long").alias("cents"))


def textrun_loss(spark: SparkSession, d: str) -> DataFrame:
    """What the text baseline keeps of the same nodes: no labels; six decimals still hold whole cents."""
    trees, labels = trees_of(spark, d, "nat", True)
    back = cd.decompress(cd.compress(trees, "textrun", lengths="exact", labels=True, taxa=labels))
    inner = on.parse_newick(back).where("card > 1 and card < 25")
    return inner.select("tree_id", "card", F.col("label").isNull().alias("label_lost"), F.round(F.col("length") * 100).cast("long").alias("cents"))


def _seventh_digit(spark: SparkSession, d: str) -> DataFrame:
    """Star trees of the nations whose leaf lengths have seven decimals: the month's cents, in ten-millionths and odd."""
    leaves = run_sql(spark, d, f"WITH {fo.nat_sql(SPARK)} SELECT tree_id, taxon, cents FROM nat_leaf")
    lex = F.format_string("N%02d:%d.%07d", "taxon", F.expr("(2 * cents + 1) div 10000000"), (2 * F.col("cents") + 1) % 10000000)
    return leaves.groupBy("tree_id").agg(F.array_sort(F.collect_list(lex)).alias("x")).select("tree_id", F.concat(F.lit("("), F.array_join("x", ","), F.lit(");")).alias("newick"))


def six_digit_lengths(spark: SparkSession, d: str) -> DataFrame:
    """Leaf lengths of seven decimals after the text baseline, in millionths: its own rounding, to six."""
    back = cd.decompress(cd.compress(_seventh_digit(spark, d), "textrun", lengths="exact"))
    leaves = on.parse_newick(back).where("is_leaf")
    return leaves.select("tree_id", F.substring("label", 2, 2).cast("int").alias("taxon"), F.round(F.col("length") * 1000000).cast("long").alias("micro"))


def length_errors_by_codec(spark: SparkSession, d: str) -> DataFrame:
    """Largest error of leaf lengths of seven decimals, in ten-millionths: none for the packed codec, up to five for the
    text baseline."""
    trees = _seventh_digit(spark, d)
    rows = [measures.length_error(trees, cd.decompress(cd.compress(trees, codec, lengths="exact"))).select(F.lit(codec).alias("codec"), F.round(F.col("max_error") * 1e7).cast("long").alias("error")) for codec in ("packed", "textrun")]
    return rows[0].unionByName(rows[1])


def small_primes(spark: SparkSession, d: str) -> DataFrame:
    """Collisions of the monthly clusters' hashes under moduli so small that they must meet: 5 and 7."""
    nodes, taxa = _nodes(spark, d)
    return cl.collisions(cl.clusters(nodes, taxa), 5, 7)


_SMALL_PRIMES_SQL = "WITH x AS ({}), k AS (SELECT h1 % 5 AS h1, h2 % 7 AS h2, h3, card FROM x) SELECT h1, h2 FROM k GROUP BY 1, 2 HAVING min(h3) <> max(h3) OR min(card) <> max(card)"


def crossing_clusters(spark: SparkSession, d: str) -> DataFrame:
    """Trees that are none: the clusters of a month and of the next taken together, where two of them cross."""
    made = forest(spark, d, "nat").select(F.expr("tree_id div 2").alias("tree_id"), F.col("members").alias("cluster"), "card").distinct()
    found = co.check_laminar(made.select("tree_id", "cluster", "card", F.explode(F.split("cluster", ",")).alias("taxon")))
    return found.select("tree_id").distinct()


_CROSSING_SQL = f"""WITH {_TEXT["nat"](DUCK)}, c AS (SELECT DISTINCT tree_id // 2 AS tree_id, members, string_split(members, ',') AS m FROM nat)
SELECT DISTINCT a.tree_id FROM c a JOIN c b ON a.tree_id = b.tree_id AND a.members < b.members AND len(list_intersect(a.m, b.m)) > 0
AND len(list_intersect(a.m, b.m)) < least(len(a.m), len(b.m))"""


def damaged_accuracy(spark: SparkSession, d: str) -> DataFrame:
    """Share of trees restored exactly when the container is of other trees in every fourth month: those of the month
    before. A tree is right only where the two months agree."""
    trees, labels = trees_of(spark, d, "nat")
    shift = F.when(F.col("tree_id") % 4 == 1, F.col("tree_id") - 1).otherwise(F.col("tree_id"))
    source = trees.select(F.col("tree_id").alias("from"), "newick")
    other = trees.select("tree_id", shift.alias("from")).join(source, "from").select("tree_id", "newick")
    found = cd.verify_roundtrip(trees, cd.compress(other, taxa=labels))
    return found.agg(F.count("*").alias("n_trees"), F.sum(F.col("ok").cast("long")).alias("n_ok"))


_DAMAGED_SQL = f"""WITH {_TEXT["nat"](DUCK)}, s AS (SELECT tree_id, string_agg(members, ';' ORDER BY members) AS shape FROM nat GROUP BY tree_id)
SELECT count(*) AS n_trees, sum(CASE WHEN a.tree_id % 4 = 1 AND a.shape <> b.shape THEN 0 ELSE 1 END)::BIGINT AS n_ok FROM s a LEFT JOIN s b ON b.tree_id = a.tree_id - 1"""


def raw_sizes(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of the text baseline's lines for the monthly trees, as measured on its container's payload."""
    trees, labels = trees_of(spark, d, "nat")
    return cd.compress(trees, "textrun", taxa=labels).agg(F.sum(F.octet_length("payload")).cast("long").alias("payload_bytes"), F.sum("n_bip").cast("long").alias("n_entries"))


def canonical_nat(spark: SparkSession, d: str) -> DataFrame:
    """Trees whose canonical text survives packing, by kind of check."""
    trees, labels = trees_of(spark, d, "nat", True)
    packed = cd.compress(trees, lengths="exact", labels=True, taxa=labels)
    return cd.verify_roundtrip(trees, packed, True, True)


def rebuild_parents(method: str):
    """Parent of each cluster of the monthly trees."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        made = forest(spark, d, "nat").select("tree_id", F.col("members").alias("cluster"), "card", F.transform(F.split("members", ","), lambda x: x.cast("int")).alias("members"))
        if method == "window":
            return co.parents_by_window(made.select("tree_id", "cluster", "card", F.explode("members").alias("taxon")))
        if method == "pairwise":
            return co.parents_by_pairs(made)
        return co.parents_by_kernel(made, 25, method)

    return run


_PARENT_SQL = f"""WITH {_TEXT["nat"](DUCK)}, p AS (SELECT a.tree_id, a.members AS cluster, arg_min(b.members, b.card) AS parent FROM nat a LEFT JOIN nat b
  ON a.tree_id = b.tree_id AND a.card < b.card AND list_has_all(string_split(b.members, ','), string_split(a.members, ',')) GROUP BY 1, 2) SELECT tree_id, cluster, parent FROM p"""


def laminar_violations(spark: SparkSession, d: str) -> DataFrame:
    return co.check_laminar_sets(forest(spark, d, "sup")).agg(F.count("*").alias("n_violations"))


def consensus(kind: str, name: str = "nat"):
    def run(spark: SparkSession, d: str) -> DataFrame:
        trees, labels = trees_of(spark, d, name)
        packed = cd.compress(trees, taxa=labels)
        found = co.consensus_clusters(co.cluster_supports(packed), co.n_trees(packed), kind)
        return members_text(found.select("bits", "card", "n_support"), len(labels), _WIDTH[name]).select("members", F.col("n_support").cast("long").alias("n_support"))

    return run


def _consensus_sql(name: str, test: str) -> str:
    return f"WITH {_TEXT[name](DUCK)}, t AS (SELECT count(DISTINCT tree_id) AS n FROM {name}), g AS (SELECT members, count(*) AS n_support FROM {name} GROUP BY members) SELECT members, n_support FROM g, t WHERE {test}"


def consensus_subset(spark: SparkSession, d: str) -> DataFrame:
    """Majority consensus on the even nations, without restoring a tree."""
    trees, labels = trees_of(spark, d, "nat")
    packed, subset = cd.compress(trees, taxa=labels), labels[::2]
    found = co.consensus_clusters(co.subset_supports(packed, labels, subset), co.n_trees(packed), "majority")
    return members_text(found.select("bits", "n_support"), len(subset), 2).select("members", F.col("n_support").cast("long").alias("n_support"))


_SUBSET_SQL = f"""WITH {_TEXT["nat"](DUCK)}, t AS (SELECT count(DISTINCT tree_id) AS n FROM nat),
c AS (SELECT tree_id, list_transform(list_filter(list_transform(string_split(members, ','), lambda x: x::INT), lambda x: x % 2 = 0), lambda x: lpad((x // 2)::VARCHAR, 2, '0')) AS m FROM nat),
k AS (SELECT DISTINCT tree_id, array_to_string(m, ',') AS members FROM c WHERE len(m) > 1 AND len(m) < 13), g AS (SELECT members, count(*) AS n_support FROM k GROUP BY members)
SELECT members, n_support FROM g, t WHERE n_support > n * 0.5"""


def rf_matrix_nat(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "nat")
    packed = stored(cd.compress(trees, taxa=labels))
    return co.rf_matrix(co.container_entries(packed), co.n_trees(packed)).select("t1", "t2", F.col("rf").cast("long").alias("rf"), F.round("norm", 9).alias("norm"))


_RF_SQL = f"""WITH {_TEXT["nat"](DUCK)}, m AS (SELECT tree_id, count(*) AS m FROM nat GROUP BY 1),
c AS (SELECT a.tree_id AS t1, b.tree_id AS t2, count(*) AS c FROM nat a JOIN nat b ON a.members = b.members AND a.tree_id < b.tree_id GROUP BY 1, 2)
SELECT x.tree_id AS t1, y.tree_id AS t2, x.m + y.m - 2 * coalesce(c, 0) AS rf, round((x.m + y.m - 2 * coalesce(c, 0)) / (x.m + y.m), 9) AS norm FROM m x JOIN m y ON x.tree_id < y.tree_id LEFT JOIN c ON t1 = x.tree_id AND t2 = y.tree_id"""


def frequent_clusters(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "emb")
    packed = cd.compress(trees, taxa=labels)
    found = co.frequent_clusters(co.cluster_supports(packed), co.n_trees(packed), 0.25)
    return members_text(found.select("bits", "n_support"), len(labels), 4).select("members", F.col("n_support").cast("long").alias("n_support"))


def frequent_restrictions(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "nat")
    entries = co.container_entries(cd.compress(trees, taxa=labels)).where("card <= 5")
    return co.frequent_restrictions(entries, labels, 2, 40).select(F.expr("array_join(transform(split(taxa, ','), x -> lpad(cast(cast(x as int) as string), 2, '0')), ',')").alias("taxa"), "n_support")


_RESTRICT_SQL = f"""WITH {_TEXT["nat"](DUCK)}, e AS (SELECT tree_id, members, unnest(string_split(members, ',')) AS x FROM nat WHERE card <= 5),
p AS (SELECT DISTINCT a.tree_id, a.x || ',' || b.x AS taxa FROM e a JOIN e b ON a.tree_id = b.tree_id AND a.members = b.members AND a.x < b.x) SELECT taxa, count(*) AS n_support FROM p GROUP BY taxa HAVING count(*) >= 40"""


def trees_with_cluster(spark: SparkSession, d: str) -> DataFrame:
    """Trees that have the most frequent proper pair of each region's nations: lookups by bits in the packed table."""
    trees, labels = trees_of(spark, d, "nat")
    entries = members_text(co.container_entries(cd.compress(trees, taxa=labels)).where("card = 2").select("bits", "first_tree", "support"), 25, 2)
    return entries.select("members", "first_tree", F.explode("support").alias("s")).select("members", (F.col("first_tree") + F.col("s")).alias("tree_id"))


def taxon_instability(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "nat")
    packed = cd.compress(trees, taxa=labels)
    return co.taxon_instability(co.cluster_supports(packed), labels, co.n_trees(packed)).select("taxon", "n_clusters", "n_weak", F.round("share", 9).alias("share"))


_INSTABLE_SQL = f"""WITH {_TEXT["nat"](DUCK)}, t AS (SELECT count(DISTINCT tree_id) AS n FROM nat), g AS (SELECT members, count(*) AS s FROM nat GROUP BY members),
e AS (SELECT unnest(string_split(members, ','))::INT AS x, s < 0.5 * n AS weak FROM g, t)
SELECT n_name AS taxon, count(*) AS n_clusters, sum(weak::INT)::BIGINT AS n_weak, round(sum(weak::INT) / count(*), 9) AS share FROM e JOIN nation ON n_nationkey = x GROUP BY n_name"""


def merge_blocks(spark: SparkSession, d: str) -> DataFrame:
    """Two containers written apart, merged and restored."""
    trees, labels = trees_of(spark, d, "nat")
    one, two = (cd.compress(trees.where(c), block=40, taxa=labels) for c in ("tree_id < 40", "tree_id >= 40"))
    return restored_clusters(cd.decompress(cd.merge(one, two)), labels, 2)


def hetero_pages(spark: SparkSession, d: str) -> DataFrame:
    """Element trees of pages, packed over the union of their leaves and restored: whether the canonical text is
    the same, null for a page without a tree."""
    pages = table(spark, d, "pages")
    trees = hetero.page_trees(pages)
    taxa = hetero.union_taxa(trees)
    back = on.canonical_newick(hetero.decompress_hetero(hetero.compress_hetero(trees, taxa), taxa)).select("tree_id", F.col("canonical").alias("y"))
    judged = on.canonical_newick(trees).join(back, "tree_id", "left").select("tree_id", F.coalesce(F.col("canonical") == F.col("y"), F.lit(False)).alias("ok"))
    return pages.select(F.col("page_id").alias("tree_id")).join(judged, "tree_id", "left").select("tree_id", "ok")


# --- model --------------------------------------------------------------------------------------------------------


def taxa_order(spark: SparkSession, d: str) -> DataFrame:
    nodes, _ = _nodes(spark, d)
    return on.taxon_table(nodes, "lexicographic")


def leaf_counts(spark: SparkSession, d: str) -> DataFrame:
    trees, _ = trees_of(spark, d, "nat", True)
    return on.newick_leaf_counts(trees).select("tree_id", "n_leaves", "n_inner")


def cluster_kinds(spark: SparkSession, d: str) -> DataFrame:
    nodes, taxa = _nodes(spark, d)
    return cl.clusters(nodes, taxa).groupBy("kind").agg(F.count("*").alias("n"))


def cluster_cardinality(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "sup")
    return cd.container_entries(cd.compress(trees, taxa=labels)).groupBy("card").agg(F.sum("n_support").cast("long").alias("n"))


def invalid_documents(spark: SparkSession, d: str) -> DataFrame:
    """Documents with brackets, taken as Newick: none of them is a tree."""
    docs = table(spark, d, "documents").where(F.col("text").contains("(")).select(F.col("doc_id").alias("tree_id"), F.col("text").alias("newick"))
    return on.validate_newick(docs).select("tree_id", F.col("error").isNotNull().alias("invalid"))


def collision_count(spark: SparkSession, d: str) -> DataFrame:
    nodes, taxa = _nodes(spark, d)
    return cl.collisions(cl.clusters(nodes, taxa)).agg(F.count("*").alias("n_collisions"))


def bipartition_counts(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "emb")
    return measures.count_bipartitions(cd.compress(trees, taxa=labels), len(labels))


def inout_choice(spark: SparkSession, d: str) -> DataFrame:
    """Native form: hashes, one aggregate, array functions."""
    nodes, taxa = _nodes(spark, d)
    chosen = cl.choose_side(cl.bipartition_table(cl.clusters(nodes, taxa)), F.lit(80))
    return chosen.groupBy("sign").agg(F.count("*").alias("n"), F.sum(F.size("ids")).alias("n_ids"))


def code_gain(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of the packed and the text codes of the daily trees' clusters and lists."""
    size = lambda hex_col: F.sum(F.length(hex_col) / 2).cast("long")
    packed, text = encoded("sup")(spark, d), encoded("sup", "textrun", "textrun")(spark, d)
    one = packed.agg(size("bits_code").alias("packed_bits"), size("ids_code").alias("packed_ids"))
    return one.join(text.agg(F.sum(F.length("bits_code")).alias("text_bits"), F.sum(F.length("ids_code")).alias("text_ids")), F.lit(True))


def subtree_dict_counts(spark: SparkSession, d: str) -> DataFrame:
    """Inner nodes and distinct subtrees of the older baseline on the monthly trees."""
    return cd.subtree_dictionary_size(trees_of(spark, d, "nat")[0]).select("n_subtrees", "comp_bytes", "n_distinct")


# --- sizes --------------------------------------------------------------------------------------------------------


def _sizes(spark: SparkSession, d: str, names=("nat", "brand", "emb")) -> list[tuple[str, str, int, int]]:
    out = []
    for name in names:
        trees, _ = trees_of(spark, d, name)
        trees = trees.persist()
        raw = measures.raw_size(trees).first()["raw_bytes"]
        for codec in ("textrun", "packed", "packed_raw"):
            out.append((name, codec, raw, measures.container_size(cd.compress(trees, codec)).first()["comp_bytes"]))
        out.append((name, "subtree_dict", raw, cd.subtree_dictionary_size(trees).first()["comp_bytes"]))
        out += [(name, codec, raw, cd.general_codec(trees, codec).agg(F.sum(F.octet_length("payload"))).first()[0]) for codec in ("text_deflate", "text_bz2", "text_lzma")]
        trees.unpersist()
    return out


def sizes_by_codec(spark: SparkSession, d: str) -> DataFrame:
    return measures.size_report(spark, _sizes(spark, d))


def ratio_saving(spark: SparkSession, d: str) -> DataFrame:
    return measures.macro_average(measures.size_report(spark, _sizes(spark, d, ("nat", "emb"))))


def size_cube(spark: SparkSession, d: str) -> DataFrame:
    return measures.size_cube(measures.size_report(spark, _sizes(spark, d, ("nat",))))


def dataset_properties(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "emb")
    return measures.dataset_properties(trees, cd.compress(trees, taxa=labels), "emb").select("n_taxa", "n_trees", "n_all", "n_unique")


def accuracy(spark: SparkSession, d: str) -> DataFrame:
    trees, labels = trees_of(spark, d, "nat", True)
    return measures.accuracy_report(trees, cd.compress(trees, lengths="exact", labels=True, taxa=labels))


def length_errors(spark: SparkSession, d: str) -> DataFrame:
    """Largest length error after packing: none."""
    trees, labels = trees_of(spark, d, "nat", True)
    return measures.length_error(trees, cd.decompress(cd.compress(trees, lengths="exact", taxa=labels)))


ABLATION = [(b, i, s) for b in ("packed", "textrun", "raw") for i in ("packed", "textrun", "fixed") for s in ("both", "in")]


def ablation_grid(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of every choice of bit code, list code and side, with and without Deflate, on one forest. Clusters are encoded in
    parallel; each choice is one stream, in the order of the bits, in a task of its own."""
    trees, labels = trees_of(spark, d, "emb")
    packed = stored(cd.compress(trees, taxa=labels))
    n, span = len(labels), packed.agg(F.max(F.col("first_tree") + F.col("span"))).first()[0]
    entries = stored(cd.container_entries(packed).select("bits", "support")).orderBy("bits")

    def code(batches):
        import pyspark

        part, at = pyspark.TaskContext.get().partitionId(), 0
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                out = []
                for bits, support in zip(*(c.to_pylist() for c in batch.slice(lo, 512).columns[:2]), strict=True):
                    ids = np.array(support, np.int64)
                    ones = {b: cd.encode_one(bits, n, ids[:0], span, b, "packed", "in")[0] for b in dict.fromkeys(k[0] for k in ABLATION)}
                    twos = {k: cd.encode_one(b"", 0, ids, span, "raw", *k)[1:] for k in dict.fromkeys(k[1:] for k in ABLATION)}
                    for k, (b, *rest) in enumerate(ABLATION):
                        two, sign, listed = twos[tuple(rest)]
                        out.append((k, part, at, ones[b] + codes.varint(2 * len(listed) + (sign == "-")) + two))
                    at += 1
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.binary()), strict=True)], ["k", "part", "at", "entry"])

    def deflate(batches):
        import zlib

        packs: dict[int, list] = {}
        for batch in batches:
            for k, entry in zip(batch.column(0).to_pylist(), batch.column(3).to_pylist(), strict=True):
                got = packs.setdefault(k, [zlib.compressobj(6, zlib.DEFLATED, -15), 0, 0])
                got[1] += len(entry)
                got[2] += len(got[0].compress(entry))
        if packs:
            rows = [(*ABLATION[k], raw, size + len(pack.flush())) for k, (pack, raw, size) in packs.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows, strict=True)], ["bits_code", "ids_code", "side", "raw_bytes", "deflated_bytes"])

    coded = entries.mapInArrow(code, "k int, part int, at long, entry binary").repartitionById(len(ABLATION), "k").sortWithinPartitions("k", "part", "at")
    return coded.mapInArrow(deflate, "bits_code string, ids_code string, side string, raw_bytes long, deflated_bytes long")


# --- deflate ------------------------------------------------------------------------------------------------------


def _texts(spark: SparkSession, d: str, name: str, key: str, column: str) -> DataFrame:
    """Whole texts for the pure-Python stages."""
    return table(spark, d, name).select(F.col(key).alias("id"), F.col(column).cast("binary").alias("data"))


def deflate_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    """Digest of every document's text after Deflate and back."""
    docs = table(spark, d, "documents").select("doc_id", F.col("text").cast("binary").alias("data"))
    return docs.select("doc_id", F.md5(sqlapi.inflate(sqlapi.deflate("data"))).alias("digest"))


def own_deflate(spark: SparkSession, d: str) -> DataFrame:
    """The own encoder's stream, read by the standard inflater and the other way round."""
    data = _texts(spark, d, "benchmark", "item_id", "text")
    one = F.md5(sqlapi.inflate(sqlapi.own_deflate("data"))) == F.md5("data")
    two = F.md5(sqlapi.own_inflate(sqlapi.deflate("data"))) == F.md5("data")
    return data.select(F.col("id").alias("item_id"), one.alias("own_then_standard"), two.alias("standard_then_own"))


def lz77_pages(spark: SparkSession, d: str) -> DataFrame:
    """Bytes of every whole page after matching and expanding, and whether nothing changed."""

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                x = batch.column(1)[i].as_py() or b""
                back = df.lz77_expand(df.lz77_tokens(x))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(i, 1), pa.array([len(back)], pa.int64()), pa.array([back == x])], ["page_id", "n_bytes", "same"])

    return _texts(spark, d, "pages", "page_id", "html").mapInArrow(run, "page_id long, n_bytes long, same boolean")


def huffman_kraft(spark: SparkSession, d: str) -> DataFrame:
    """Kraft sum of the optimal code of each conversation's bytes: 1 for a complete code."""

    def run(batches):
        from collections import Counter

        for batch in batches:
            sums = []
            for x in batch.column(1).to_pylist():
                lengths = df.huffman_lengths(Counter(x or b""))
                sums.append(sum(2.0**-n for n in lengths.values()) if len(lengths) > 1 else 1.0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sums)], ["id", "kraft"])

    return _texts(spark, d, "conversations", "conv_id", "text").mapInArrow(run, "id long, kraft double").groupBy("kraft").agg(F.count("*").alias("n"))


def block_modes(spark: SparkSession, d: str) -> DataFrame:
    """Blocks, bits and bytes by mode of the own encoder, for text, pages and packed bytes."""

    def run(batches):
        for batch in batches:
            rows = [s for x in batch.column(1).to_pylist() for mode in ("auto", "stored", "fixed", "dynamic") for s in [(mode, *s) for s in df.deflate_blocks(df.lz77_tokens(x or b""), mode, 1024)[1]]]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (zip(*rows, strict=True) if rows else ([], [], [], []))], ["asked", "mode", "bits", "bytes"]) if rows else pa.RecordBatch.from_arrays([pa.array([], pa.string()), pa.array([], pa.string()), pa.array([], pa.int64()), pa.array([], pa.int64())], ["asked", "mode", "bits", "bytes"])

    data = _texts(spark, d, "benchmark", "item_id", "text")
    return data.mapInArrow(run, "asked string, mode string, bits long, bytes long").groupBy("asked", "mode").agg(F.count("*").alias("n_blocks"), F.sum("bits").alias("bits"), F.sum("bytes").alias("bytes"))


# --- streams ------------------------------------------------------------------------------------------------------


def _stream(spark: SparkSession, d: str) -> DataFrame:
    path = f"{d}/events.parquet"
    schema = spark.read.parquet(path).schema
    # a file stream takes folders or globs
    return ingest.utc(spark.readStream.schema(schema).parquet(path[:-1] + "*"))


def _drained(spark: SparkSession, stream: DataFrame) -> DataFrame:
    name = f"clade_{uuid.uuid4().hex[:12]}"
    return ingest.drain(stream, name, f"{shared_dir(spark)}/cladepack-stream/{name}", "complete")


def stream_evt_clusters(spark: SparkSession, d: str) -> DataFrame:
    """Hourly trees from the event stream, over all that is there."""
    counts = _drained(spark, ingest.bucket_counts(_stream(spark, d)))
    return ingest.hourly_clusters(counts)


def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    counts = _drained(spark, ingest.bucket_counts(_stream(spark, d), "6 hours", "1 hour"))
    return counts.select(F.unix_timestamp("start").alias("start_s"), "bucket", "n")


_SLIDING_SQL = """SELECT CAST(epoch(date_trunc('hour', ts)) - 3600 * k AS BIGINT) AS start_s, CAST(user_id % 16 AS INT) AS bucket, count(*) AS n FROM events, range(0, 6) t(k) GROUP BY 1, 2"""


def stream_session(spark: SparkSession, d: str) -> DataFrame:
    found = _drained(spark, ingest.session_counts(_stream(spark, d)))
    return found.groupBy("user_id").agg(F.count("*").alias("n_sessions"), F.sum("n").alias("n_events"))


_SESSION_SQL = """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events)
SELECT user_id, sum(new)::BIGINT AS n_sessions, count(*) AS n_events FROM g GROUP BY user_id"""


# --- bench workloads ----------------------------------------------------------------------------------------------

#: name: (taxa, noise, source at sf0.1, trees of the bench)
WORKLOADS = {
    "w01": (125, 0, "emb", 10000), "w02": (150, 2, "emb", 10000), "w03": (218, 2, "emb", 5000), "w04": (354, 5, "emb", 2000), "w05": (404, 3, "emb", 2000), "w06": (500, 2, "emb", 2000),
    "w07": (628, 2, "emb", 1000), "w08": (714, 2, "emb", 1000), "w09": (994, 2, "emb", 1000), "w10": (1288, 2, "emb", 500), "w11": (1481, 5, "emb", 500), "w12": (1512, 2, "emb", 500),
    "w13": (1604, 2, "emb", 500), "w14": (1908, 2, "emb", 500), "w15": (2000, 5, "emb", 500), "w16": (2308, 2, "md5", 300), "w17": (2554, 2, "md5", 300),
}


def preset_depth(n: int) -> int:
    return next((depth for most, depth in ((218, 20), (500, 24), (1000, 28), (2000, 32)) if n <= most), 36)


def workload_taxa(spark: SparkSession, d: str, name: str) -> tuple[np.ndarray, list[str]]:
    """Bits and labels of a workload's taxa. Where the vectors are too few, digests stand in; where those are too few as
    well, there are fewer taxa."""
    n, _, source, _ = WORKLOADS[name]
    if source == "emb" and table(spark, d, "embeddings").count() < n:
        source = "md5"
    return fo.embedding_bits(spark, d, n) if source == "emb" else fo.digest_bits(spark, d, n)


def workload_trees(spark: SparkSession, d: str, name: str, trees: int | None = None) -> DataFrame:
    """Replicate trees of a workload."""
    n, noise, _, most = WORKLOADS[name]
    bits, labels = workload_taxa(spark, d, name)
    return fo.prefix_trees(spark, bits, labels, trees or most, preset_depth(n), noise)


def whole_trees(spark: SparkSession, d: str, source: str, trees: int | None = None) -> tuple[DataFrame, list[str]]:
    """Replicate trees over all rows of embeddings or customer, with the noise and number of trees of the least workload
    that has as many taxa, or of the largest."""
    bits, labels = (fo.embedding_bits if source == "emb" else fo.digest_bits)(spark, d, (1 << 63) - 1)
    n = len(labels)
    _, noise, _, most = next((w for w in WORKLOADS.values() if w[0] >= n), WORKLOADS["w17"])
    return fo.prefix_trees(spark, bits, labels, trees or most, preset_depth(n), noise), labels


def whole_clusters(source: str, packed: bool, trees: int | None = None):
    """Clusters of the whole trees, as they are made or after packing and restoring."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        made, labels = whole_trees(spark, d, source, trees)
        block = cd.restorable_block(len(labels))
        return restored_clusters(cd.decompress(cd.compress(made, block=block, taxa=cd.taxa_of(made)), spread=block > 1) if packed else made, labels, 4 if source == "emb" else 5)

    return run


def workload_query(name: str, trees: int | None = None):
    """Sizes, counts and round trip of a workload, at its own number of trees unless another is given; n_taxa is the
    number of taxa that the tables really gave."""

    def run(spark: SparkSession, d: str) -> DataFrame:
        n_taxa = len(workload_taxa(spark, d, name)[1])
        made = workload_trees(spark, d, name, trees).persist()
        raw = measures.raw_size(made).first()
        rows = []
        for codec in ("textrun", "packed", "packed_raw"):
            packed = cd.compress(made, codec).persist()
            size = measures.container_size(packed).first()
            ok = cd.verify_roundtrip(made, packed).agg(F.avg(F.col("ok").cast("double"))).first()[0]
            rows.append((name, codec, n_taxa, raw["n_trees"], raw["raw_bytes"], size["comp_bytes"], size["n_entries"], ok))
            packed.unpersist()
        made.unpersist()
        return spark.createDataFrame(rows, "dataset string, codec string, n_taxa int, n_trees long, raw_bytes long, comp_bytes long, n_unique long, ok_share double")

    return run


def retrieval(spark: SparkSession, d: str) -> DataFrame:
    """On-the-fly retrieval: three ids out of blocks of 32 trees, blocks without them left unread."""
    trees, labels = trees_of(spark, d, "emb")
    return restored_clusters(cd.decompress(cd.compress(trees, block=32, taxa=labels), tree_ids=[3, 40, 77]), labels, 4)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Monthly trees with labels and lengths: packed, restored and compared tree by tree."""
    trees, labels = trees_of(spark, d, "nat", True)
    packed = cd.compress(trees, lengths="exact", labels=True, taxa=labels)
    sizes = measures.container_size(packed).join(measures.raw_size(trees), F.lit(True))
    return cd.verify_roundtrip(trees, packed, True, True).join(F.broadcast(sizes), F.lit(True)).select("tree_id", "ok", "raw_bytes", F.col("comp_bytes").alias("packed_bytes"))


def _registry() -> dict[str, tuple]:
    q = {f"forest_{n.removesuffix('f') if n == 'md5f' else n}_clusters": _sql(n, f"SELECT tree_id, members, card FROM {n}") for n in _TEXT}
    rt = lambda n, where="": f"WITH {_TEXT[n](DUCK)} SELECT tree_id, members, card FROM {n} {where}"
    q |= {
        "taxa_order": (taxa_order, "SELECT CAST(row_number() OVER (ORDER BY n_name) - 1 AS INT) AS taxon_idx, n_name AS label FROM nation"),
        "newick_leaf_counts": (leaf_counts, f"WITH {_TEXT['nat'](DUCK)} SELECT tree_id, 25::BIGINT AS n_leaves, count(*) + 1 AS n_inner FROM nat GROUP BY tree_id"),
        "cluster_cardinality": (cluster_cardinality, f"WITH {_TEXT['sup'](DUCK)} SELECT card, count(*) AS n FROM sup GROUP BY card"),
        "cluster_kind_counts": (cluster_kinds, f"WITH {_TEXT['nat'](DUCK)}, t AS (SELECT count(DISTINCT tree_id) AS n FROM nat) SELECT 'trivial' AS kind, 25 * n AS n FROM t UNION ALL SELECT 'root', n FROM t UNION ALL SELECT 'inner', count(*) FROM nat"),
        "newick_invalid_documents": (invalid_documents, "SELECT doc_id AS tree_id, true AS invalid FROM documents WHERE contains(text, '(')"),
        "hash_prefix": (hashes("prefix"), _HASH_SQL),
        "hash_bottom_up": (hashes("bottom_up"), _HASH_SQL),
        "hash_naive": (hashes("naive"), _HASH_SQL),
        "collisions": (collision_count, "SELECT 0::BIGINT AS n_collisions"),
        "bipartition_support": (bipartition_support("nat"), _support_sql("nat")),
        "bipartition_support_emb": (bipartition_support("emb"), _support_sql("emb")),
        "bipartition_counts_all_unique": (bipartition_counts, f"WITH {_TEXT['emb'](DUCK)} SELECT count(*) + count(DISTINCT tree_id) + (SELECT count(*) FROM embeddings) AS n_all, count(DISTINCT members) AS n_unique FROM emb"),
        "inout_choice": (inout_choice, f"SELECT sign, count(*) AS n, sum(n_listed)::BIGINT AS n_ids FROM ({_support_sql('nat')}) GROUP BY sign"),
        "textrun_codes": (encoded("nat", "textrun", "textrun"), _textrun_sql("nat")),
        "textrun_codes_emb": (encoded("emb", "textrun", "textrun"), _textrun_sql("emb")),
        "textrun_file_lines": (textrun_file_lines, _textrun_lines_sql()),
        "packed_ids_hex": (lambda s, d: encoded("nat")(s, d).drop("bits_code"), _packed_ids_sql("nat")),
        "packed_ids_hex_emb": (lambda s, d: encoded("emb")(s, d).drop("bits_code"), _packed_ids_sql("emb")),
        "fixed_ids_hex": (lambda s, d: encoded("nat", "packed", "fixed")(s, d).drop("bits_code"), _fixed_ids_sql("nat")),
        "packed_bits_hex": (lambda s, d: encoded("emb")(s, d).select("members", "bits_code"), None),
        "code_gain": (code_gain, None),
        "six_digit_lengths": (six_digit_lengths, f"WITH {_TEXT['nat'](DUCK)} SELECT tree_id, taxon, CAST(printf('%.6f', (2 * cents + 1) / 10000000.0::DOUBLE)::DOUBLE * 1000000 AS BIGINT) AS micro FROM nat_leaf"),
        "length_error_by_codec": (length_errors_by_codec, f"WITH {_TEXT['nat'](DUCK)} SELECT 'packed' AS codec, 0::BIGINT AS error UNION ALL SELECT 'textrun', max(abs(2 * cents + 1 - 10 * CAST(printf('%.6f', (2 * cents + 1) / 10000000.0::DOUBLE)::DOUBLE * 1000000 AS BIGINT)))::BIGINT FROM nat_leaf"),
        "collisions_small_primes": (small_primes, _SMALL_PRIMES_SQL.format(_HASH_SQL)),
        "crossing_clusters": (crossing_clusters, _CROSSING_SQL),
        "accuracy_damaged": (damaged_accuracy, _DAMAGED_SQL),
        "textrun_payload_bytes": (raw_sizes, f"SELECT (sum(octet_length(encode(line)) + 1) + octet_length(encode('TAXA ' || (SELECT string_agg(n_name, ':' ORDER BY n_nationkey) FROM nation))) + 1)::BIGINT AS payload_bytes, sum(CASE WHEN line LIKE 'N%' THEN 0 ELSE 1 END)::BIGINT AS n_entries FROM ({_textrun_lines_sql()})"),
        "subtree_dict_counts": (lambda s, d: subtree_dict_counts(s, d).select("n_subtrees"), f"WITH {_TEXT['nat'](DUCK)} SELECT count(*) + count(DISTINCT tree_id) AS n_subtrees FROM nat"),
        "deflate_roundtrip_documents": (deflate_roundtrip, "SELECT doc_id, md5(text) AS digest FROM documents"),
        "deflate_own_vs_zlib": (own_deflate, "SELECT item_id, true AS own_then_standard, true AS standard_then_own FROM benchmark"),
        "lz77_roundtrip_pages": (lz77_pages, "SELECT page_id, coalesce(octet_length(encode(html)), 0)::BIGINT AS n_bytes, true AS same FROM pages"),
        "huffman_kraft": (huffman_kraft, "SELECT 1.0::DOUBLE AS kraft, count(*) AS n FROM conversations"),
        "deflate_block_modes": (block_modes, None),
        "rebuild_leaf_path": (rebuild_parents("leaf_path"), _PARENT_SQL),
        "rebuild_leaf_path_full": (rebuild_parents("leaf_path_full"), _PARENT_SQL),
        "rebuild_window": (rebuild_parents("window"), _PARENT_SQL),
        "rebuild_pairwise": (rebuild_parents("pairwise"), _PARENT_SQL),
        "rebuild_refine": (rebuild_parents("refine"), _PARENT_SQL),
        "laminar_violations": (laminar_violations, "SELECT 0::BIGINT AS n_violations"),
        "roundtrip_nat": (roundtrip_nat_side, f"WITH {_TEXT['nat'](DUCK)} SELECT tree_id, card, label, cents FROM nat"),
        "roundtrip_sup": (roundtrip("sup"), rt("sup")),
        "roundtrip_emb": (roundtrip("emb"), rt("emb")),
        "roundtrip_md5": (roundtrip("md5f", "packed_raw"), rt("md5f")),
        "roundtrip_brand_blocks": (roundtrip("brand", "packed", 16), rt("brand")),
        "roundtrip_textrun": (roundtrip("emb", "textrun"), rt("emb")),
        "roundtrip_textrun_loss": (textrun_loss, f"WITH {_TEXT['nat'](DUCK)} SELECT tree_id, card, true AS label_lost, cents FROM nat"),
        "decompress_subset": (roundtrip("sup", block=500, first=400, last=900), rt("sup", "WHERE tree_id BETWEEN 400 AND 900")),
        "retrieval": (retrieval, rt("emb", "WHERE tree_id IN (3, 40, 77)")),
        "canonical_nat": (canonical_nat, f"WITH {_TEXT['nat'](DUCK)} SELECT DISTINCT tree_id, true AS ok FROM nat"),
        "sizes_by_codec": (sizes_by_codec, None),
        "ratio_saving": (ratio_saving, None),
        "size_cube": (size_cube, None),
        "ablation_grid": (ablation_grid, None),
        "dataset_properties": (dataset_properties, f"WITH {_TEXT['emb'](DUCK)} SELECT (SELECT count(*) FROM embeddings)::INT AS n_taxa, count(DISTINCT tree_id) AS n_trees, count(*) + count(DISTINCT tree_id) + (SELECT count(*) FROM embeddings) AS n_all, count(DISTINCT members) AS n_unique FROM emb"),
        "accuracy_report": (accuracy, "SELECT 1.0::DOUBLE AS share, unnest(['shape', 'labels', 'lengths']) AS what"),
        "length_error": (length_errors, "SELECT 0.0::DOUBLE AS max_error"),
        "majority_consensus_nat": (consensus("majority"), _consensus_sql("nat", "n_support > n * 0.5")),
        "majority_consensus_emb": (consensus("majority", "emb"), _consensus_sql("emb", "n_support > n * 0.5")),
        "strict_consensus_nat": (consensus("strict"), _consensus_sql("nat", "n_support = n")),
        "greedy_consensus_nat": (consensus("greedy"), None),
        "consensus_subset": (consensus_subset, _SUBSET_SQL),
        "rf_matrix_nat": (rf_matrix_nat, _RF_SQL),
        "frequent_clusters": (frequent_clusters, _consensus_sql("emb", "n_support >= n * 0.25")),
        "frequent_restrictions": (frequent_restrictions, _RESTRICT_SQL),
        "trees_with_cluster": (trees_with_cluster, f"WITH {_TEXT['nat'](DUCK)} SELECT members, tree_id FROM nat WHERE card = 2"),
        "taxon_instability": (taxon_instability, _INSTABLE_SQL),
        "merge_blocks": (merge_blocks, rt("nat")),
        "hetero_pages": (hetero_pages, None),
        "stream_evt_clusters": (stream_evt_clusters, rt("evt")),
        "stream_sliding": (stream_sliding, _SLIDING_SQL),
        "stream_session": (stream_session, _SESSION_SQL),
    }
    q |= {f"forest_{source}_all_clusters": (whole_clusters(source, False), None) for source in ("emb", "md5")}
    q |= {f"roundtrip_{source}_all": (whole_clusters(source, True), None) for source in ("emb", "md5")}
    q |= {f"{name}_codecs": (workload_query(name), None) for name in WORKLOADS}
    return q


def queries() -> dict:
    return {name: run for name, (run, _) in _registry().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in _registry().items() if sql}
