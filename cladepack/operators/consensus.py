"""Questions that the packed data answers without restoring trees: consensus, distances, lookups, stability."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..kernels import codes
from ..kernels import newick as nw
from ..kernels import trees as tk
from .codec import container_entries


def cluster_supports(container: DataFrame) -> DataFrame:
    """(bits, card, n_support) over all blocks: list lengths are added, lists are not expanded."""
    return container_entries(container).select("bits", "card", "n_support").groupBy("bits", "card").agg(F.sum("n_support").alias("n_support"))


def n_trees(container: DataFrame) -> int:
    return container.agg(F.coalesce(F.sum("n_trees"), F.lit(0))).first()[0]


def mask_bits(table: DataFrame, taxa: list[str], subset: list[str]) -> DataFrame:
    """Clusters cut down to a subset of the taxa, in its order; trivial ones and the whole subset are dropped. A tree has a
    cut cluster once, however many of its clusters fall on it, so supports are told apart by tree."""
    at, n = np.array([taxa.index(x) for x in subset]), len(taxa)

    def run(batches):
        for batch in batches:
            keep, out = [], []
            for bits in batch.column(batch.schema.get_field_index("bits")).to_pylist():
                row = codes.unpack_bits(bits, n)[at]
                keep.append(1 < row.sum() < len(at))
                out.append(np.packbits(row).tobytes())
            k = batch.schema.get_field_index("bits")
            yield batch.set_column(k, "bits", pa.array(out, pa.binary())).filter(pa.array(keep, pa.bool_()))

    return table.mapInArrow(run, table.schema)


def subset_supports(container: DataFrame, taxa: list[str], subset: list[str]) -> DataFrame:
    """(bits, card, n_support) of clusters cut down to a subset."""
    cut = mask_bits(container_entries(container).select("first_tree", "bits", "support"), taxa, subset)
    per_tree = cut.select("bits", "first_tree", F.explode("support").alias("s")).select("bits", (F.col("first_tree") + F.col("s")).alias("tree_id")).distinct()
    card = F.expr("cast(aggregate(sequence(1, length(hex(bits))), 0L, (n, i) -> n + bit_count(cast(conv(substr(hex(bits), i, 1), 16, 10) as long))) as int)")
    return per_tree.groupBy("bits").agg(F.count("*").alias("n_support")).withColumn("card", card)


def consensus_clusters(supports: DataFrame, total: int, kind: str = "majority", threshold: float = 0.5) -> DataFrame:
    """Clusters of the majority (in more than the threshold's share of the trees), strict (in all) or greedy consensus (by
    support, each that fits with those taken before)."""
    if kind == "strict":
        return supports.where(F.col("n_support") == total)
    if kind == "majority":
        return supports.where(F.col("n_support") > F.lit(total) * threshold)
    # an ordered scan over the frequent clusters: those in more than half the trees always fit; the others are ranked
    ranked = supports.repartition(1).sortWithinPartitions(F.desc("n_support"), F.col("bits"))

    def run(batches):
        taken: list[np.ndarray] = []
        for batch in batches:
            keep = []
            for bits in batch.column(0).to_pylist():
                row = np.frombuffer(bits, np.uint8)
                fits = all(not (row & t).any() or ((row & t) == row).all() or ((row & t) == t).all() for t in taken)
                keep.append(fits)
                if fits:
                    taken.append(row)
            yield batch.filter(pa.array(keep, pa.bool_()))

    return ranked.mapInArrow(run, supports.schema)


def consensus_tree(found: DataFrame, taxa: list[str]) -> str:
    """Newick text of a consensus: at most as many clusters as taxa, rebuilt once."""
    rows = [codes.unpack_bits(bytes(r["bits"]), len(taxa)) for r in found.select("bits").collect()]
    made = tk.sort_clusters(np.array(rows, bool).reshape(-1, len(taxa)))
    kids = tk.children_lists(*tk.leaf_path(made))
    return nw.write(len(kids) - 1, kids, [*taxa, *[None] * len(made)], [None] * len(kids))


#: Clusters whose memberships are multiplied at once.
_CLUSTERS = 8192


def rf_matrix(entries: DataFrame, total: int, block: int = 512) -> DataFrame:
    """(t1, t2, rf, norm) of all pairs t1 < t2: clusters of either less twice those of both.

    The table of memberships is made once. Trees are dealt into blocks of `block` by their id; a pair of blocks is one group,
    which gets a row for each cluster of its trees with the ids that have it, and counts common clusters as a matrix product.
    So a cluster in many trees gives a row for each block, not one for each pair of its trees. The result itself has a row
    for each pair of trees.
    """
    ids = F.explode(F.transform("support", lambda x: x + F.col("first_tree"))).alias("t")
    rows = entries.select("bits", ids).select("bits", "t", F.floor(F.col("t") / block).alias("b"))
    lists = rows.groupBy("b", "bits").agg(F.collect_list("t").alias("ids"))
    blocks = entries.select(F.explode(F.sequence(F.floor(F.col("first_tree") / block), F.floor((F.col("first_tree") + F.array_max("support")) / block))).alias("o")).distinct()
    dealt = lists.join(F.broadcast(blocks), F.lit(True)).select(F.least("b", "o").alias("i"), F.greatest("b", "o").alias("j"), "b", "bits", "ids")

    def count(key, whole):
        i, j = key[0].as_py(), key[1].as_py()
        code = whole.column("bits").combine_chunks().dictionary_encode().indices.to_numpy()
        side, lists = whole.column("b").to_numpy(), whole.column("ids").to_pylist()
        trees = {b: np.unique(np.concatenate([lists[k] for k in at])) if len(at := np.flatnonzero(side == b)) else np.zeros(0, np.int64) for b in {i, j}}
        size = {b: np.zeros(len(t), np.int64) for b, t in trees.items()}
        common = np.zeros((len(trees[i]), len(trees[j])), np.int64)
        for first in range(0, int(code.max()) + 1, _CLUSTERS):  # clusters of a product
            has = {b: np.zeros((len(t), _CLUSTERS), np.float32) for b, t in trees.items()}
            for k in np.flatnonzero((code >= first) & (code < first + _CLUSTERS)).tolist():
                has[side[k]][np.searchsorted(trees[side[k]], lists[k]), code[k] - first] = 1
            common += np.rint(has[i] @ has[j].T).astype(np.int64)
            for b, m in has.items():
                size[b] += m.sum(1, dtype=np.int64)
        t1, t2, both = trees[i], trees[j], size[i][:, None] + size[j][None, :]
        rf = both - 2 * common
        at, to = np.nonzero(t1[:, None] < t2[None, :])
        return pa.Table.from_arrays([pa.array(t1[at]), pa.array(t2[to]), pa.array(rf[at, to]), pa.array(rf[at, to] / both[at, to])], ["t1", "t2", "rf", "norm"])

    return dealt.groupBy("i", "j").applyInArrow(count, "t1 long, t2 long, rf long, norm double")


def bits_of(taxa: list[str], members: list[str]) -> bytes:
    return codes.pack_bits(np.array([taxa.index(x) for x in members]), len(taxa))


def trees_with(entries: DataFrame, bits: bytes) -> DataFrame:
    """Ids of the trees that have a cluster."""
    return entries.where(F.col("bits") == F.lit(bits)).select("first_tree", F.explode("support").alias("s")).select((F.col("first_tree") + F.col("s")).alias("tree_id"))


def clusters_of(entries: DataFrame, tree_id: int) -> DataFrame:
    """(bits, card) of a tree's clusters."""
    local = F.lit(tree_id) - F.col("first_tree")
    return entries.where((local >= 0) & F.array_contains("support", local.cast("int"))).select("bits", "card")


def frequent_clusters(supports: DataFrame, total: int, least: float) -> DataFrame:
    return supports.where(F.col("n_support") >= F.lit(total) * least)


def frequent_restrictions(entries: DataFrame, taxa: list[str], k: int, least: int) -> DataFrame:
    """(taxa, n_support): k-leaf subsets that are a cluster of the trees cut down to them and one more taxon outside, in at
    least so many trees: subsets of small clusters, by their trees. k is small."""
    n = len(taxa)

    def run(batches):
        from itertools import combinations

        for batch in batches:
            names, ids = [], []
            for first, bits, support in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                members = np.flatnonzero(codes.unpack_bits(bits, n)).tolist()
                for combo in combinations(members, k):
                    name = ",".join(f"{x:04d}" for x in combo)
                    names += [name] * len(support)
                    ids += [first + s for s in support]
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(ids, pa.int64())], ["taxa", "tree_id"])

    small = entries.select("first_tree", "bits", "support")
    return small.mapInArrow(run, "taxa string, tree_id long").distinct().groupBy("taxa").agg(F.count("*").alias("n_support")).where(F.col("n_support") >= least)


def taxon_instability(supports: DataFrame, taxa: list[str], total: int, level: float = 0.5) -> DataFrame:
    """(taxon, n_clusters, n_weak, share): how many of the distinct clusters with a taxon have less support than the level
    of all trees. The measure that sequence data would give is not possible here."""
    n = len(taxa)

    def run(batches):
        for batch in batches:
            names, weak = [], []
            for bits, support in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for x in np.flatnonzero(codes.unpack_bits(bits, n)).tolist():
                    names.append(taxa[x])
                    weak.append(support < level * total)
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(weak, pa.bool_())], ["taxon", "weak"])

    each = supports.select("bits", "n_support").mapInArrow(run, "taxon string, weak boolean")
    return each.groupBy("taxon").agg(F.count("*").alias("n_clusters"), F.sum(F.col("weak").cast("long")).alias("n_weak")).withColumn("share", F.col("n_weak") / F.col("n_clusters"))


def parents_by_window(members: DataFrame) -> DataFrame:
    """(tree_id, cluster, parent) of exploded clusters (tree_id, cluster, card, taxon): along a leaf, clusters by size are
    its path to the root, so the next one is the parent. One window, no loop."""
    w = Window.partitionBy("tree_id", "taxon").orderBy("card", "cluster")
    return members.withColumn("parent", F.lead("cluster").over(w)).select("tree_id", "cluster", "parent").distinct()


def check_laminar(members: DataFrame) -> DataFrame:
    """Clusters with more than one parent: none if the clusters of every tree are nested or disjoint."""
    return parents_by_window(members).groupBy("tree_id", "cluster").agg(F.countDistinct(F.coalesce("parent", F.lit("root"))).alias("n")).where("n > 1")


def check_laminar_sets(forest: DataFrame) -> DataFrame:
    """The same of (tree_id, members, card), members being joined ordinals: a tree's clusters are one row, members are not
    shuffled one by one."""
    packed = forest.groupBy("tree_id").agg(F.collect_list(F.struct("card", "members")).alias("c"))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pylist()[0]
                made = sorted((c["card"], c["members"]) for c in row["c"])
                sets = [np.array(m.split(","), np.int64) for _, m in made]
                leaf, cluster = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
                order = np.argsort(leaf, kind="stable")
                leaf, cluster = leaf[order], cluster[order]
                above = np.where(np.append(leaf[1:] == leaf[:-1], False), np.append(cluster[1:], 0), len(sets))
                pairs = np.unique(cluster * (len(sets) + 1) + above) // (len(sets) + 1)
                found, n = np.unique(pairs, return_counts=True)
                found, n = found[n > 1], n[n > 1]
                yield pa.RecordBatch.from_arrays([pa.array([row["tree_id"]] * len(n), pa.int64()), pa.array([made[k][1] for k in found.tolist()], pa.string()), pa.array(n, pa.int64())], ["tree_id", "cluster", "n"])

    return packed.mapInArrow(run, "tree_id long, cluster string, n long")


def parents_by_pairs(clusters: DataFrame) -> DataFrame:
    """(tree_id, cluster, parent) by comparing the clusters of a tree in pairs: the least strict superset. members: arrays."""
    a, b = clusters.alias("a"), clusters.alias("b")
    inside = (F.col("a.card") < F.col("b.card")) & (F.size(F.array_except("a.members", "b.members")) == 0)
    pairs = a.join(b, F.col("a.tree_id") == F.col("b.tree_id")).where(inside)
    best = pairs.groupBy(F.col("a.tree_id").alias("tree_id"), F.col("a.cluster").alias("cluster")).agg(F.min_by(F.col("b.cluster"), F.col("b.card")).alias("parent"))
    return clusters.select("tree_id", "cluster").join(best, ["tree_id", "cluster"], "left")


def parents_by_kernel(clusters: DataFrame, n: int, method: str) -> DataFrame:
    """(tree_id, cluster, parent) by a rebuild kernel; clusters: (tree_id, cluster, card, members)."""
    packed = clusters.groupBy("tree_id").agg(F.array_sort(F.collect_list(F.struct("card", "cluster", "members"))).alias("c"))

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pylist()[0]
                rows = np.zeros((len(row["c"]) + 1, n), bool)
                for k, c in enumerate(row["c"]):
                    rows[k, c["members"]] = True
                rows[-1] = True
                _, parent = tk.METHODS[method](rows)
                names = [c["cluster"] for c in row["c"]]
                up = [names[p] if 0 <= p < len(names) else None for p in parent[:-1].tolist()]
                yield pa.RecordBatch.from_arrays([pa.array([row["tree_id"]] * len(names), pa.int64()), pa.array(names, pa.string()), pa.array(up, pa.string())], ["tree_id", "cluster", "parent"])

    return packed.mapInArrow(run, "tree_id long, cluster string, parent string")
