"""Bipartitions of trees as spans of leaves, their universal hashes, and the table of distinct ones."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Primes of the two hashes, and of a third that only tells collisions of the pair.
M1, M2, M3 = 1_000_003, 10**12 + 39, 10**12 + 61
#: Sums of coefficients stay within a long for so many taxa.
MOST_TAXA = 9_000_000


def coefficients(n: int, seed: int = 1) -> list[tuple[int, int, int]]:
    """Pseudo-random coefficients of n taxa, below M1, M2 and M3: digits of a digest of seed and ordinal, which SQL can
    follow. (A linear recurrence would not do: sums of its terms meet for different sets.)"""
    if n > MOST_TAXA:
        raise ValueError("too many taxa")
    digests = [hashlib.md5(f"{seed}:{i}".encode()).hexdigest() for i in range(n)]
    return [(int(d[:8], 16) % M1, int(d[8:20], 16) % M2, int(d[20:], 16) % M3) for d in digests]


def coefficient_columns(i: Column, seed: int = 1) -> list[Column]:
    """The same as column expressions of the ordinal."""
    digest = F.md5(F.concat(F.lit(f"{seed}:"), i.cast("string")))
    part = lambda at, n: F.conv(F.substring(digest, at, n), 16, 10).cast("long")
    return [(part(1, 8) % M1).alias("a1"), (part(9, 12) % M2).alias("a2"), (part(21, 12) % M3).alias("a3")]


def leaf_order(nodes: DataFrame, taxa: DataFrame) -> DataFrame:
    """(tree_id, pos, taxon_idx): the leaves of each tree in text order."""
    return nodes.where("is_leaf").join(F.broadcast(taxa), "label").select("tree_id", F.col("first").alias("pos"), "taxon_idx")


def kind(card: Column, n: Column) -> Column:
    return F.when(card == 1, "trivial").when(card == n, "root").otherwise("inner")


def clusters(nodes: DataFrame, taxa: DataFrame, method: str = "prefix", rooted: bool = True, seed: int = 1) -> DataFrame:
    """(tree_id, node_id, card, kind, first, last, h1, h2, h3) of all nodes. Every hash is the sum of the coefficients of
    the leaves below, modulo a prime.

    method: prefix, differences of running sums along the leaf order, without recursion; naive, a sum over the leaves of
    each node by a range join; bottom_up is in hash_bottom_up. rooted=False takes of every bipartition the side without
    taxon 0, whose hash is the total less the node's, and drops the root.
    """
    sizes = nodes.where("is_leaf").groupBy("tree_id").agg(F.count("*").cast("int").alias("n"))
    leaves = leaf_order(nodes, taxa).select("tree_id", "pos", "taxon_idx", *coefficient_columns(F.col("taxon_idx"), seed))
    base = nodes.select("tree_id", "node_id", "card", "first", "last").join(sizes, "tree_id").withColumn("kind", kind(F.col("card"), F.col("n")))
    primes = {"1": M1, "2": M2, "3": M3}
    if method == "prefix":
        run = Window.partitionBy("tree_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
        sums = leaves.select("tree_id", "pos", *[F.sum(f"a{k}").over(run).alias(f"p{k}") for k in primes])
        hi = sums.select("tree_id", F.col("pos").alias("last"), *[F.col(f"p{k}").alias(f"q{k}") for k in primes])
        lo = sums.select("tree_id", (F.col("pos") + 1).alias("first"), *[F.col(f"p{k}").alias(f"r{k}") for k in primes])
        joined = base.join(hi, ["tree_id", "last"]).join(lo, ["tree_id", "first"], "left")
        hashed = joined.select(*base.columns, *[((F.col(f"q{k}") - F.coalesce(f"r{k}", F.lit(0))) % m).alias(f"h{k}") for k, m in primes.items()])
    else:
        within = leaves.join(base.select("tree_id", "node_id", "first", "last"), "tree_id").where("first <= pos and pos <= last")
        sums = within.groupBy("tree_id", "node_id").agg(*[(F.sum(f"a{k}") % m).alias(f"h{k}") for k, m in primes.items()])
        hashed = base.join(sums, ["tree_id", "node_id"]).select(*base.columns, "h1", "h2", "h3")
    if not rooted:
        zero = leaves.where("taxon_idx = 0").select("tree_id", F.col("pos").alias("zero"))
        total = leaves.groupBy("tree_id").agg(*[F.sum(f"a{k}").alias(f"s{k}") for k in primes])
        flip = F.col("zero").between(F.col("first"), F.col("last"))
        wide = hashed.where("kind <> 'root'").join(zero, "tree_id").join(total, "tree_id")
        hashed = wide.select("tree_id", "node_id", F.when(flip, F.col("n") - F.col("card")).otherwise(F.col("card")).alias("card"), "first", "last", "n", "kind", *[F.when(flip, F.pmod(F.col(f"s{k}") - F.col(f"h{k}"), F.lit(m))).otherwise(F.col(f"h{k}")).alias(f"h{k}") for k, m in primes.items()])
    return hashed.select("tree_id", "node_id", "card", "kind", "first", "last", "h1", "h2", "h3")


def hash_bottom_up(nodes: DataFrame, taxa: DataFrame, seed: int = 1) -> DataFrame:
    """(tree_id, node_id, h1, h2, h3) by adding children into parents in postorder, a tree at a time."""
    leaves = leaf_order(nodes, taxa).select("tree_id", F.col("pos").alias("first"), *coefficient_columns(F.col("taxon_idx"), seed))
    full = nodes.join(leaves, ["tree_id", "first"]).groupBy("tree_id").agg(F.array_sort(F.collect_list(F.struct("node_id", "parent_id", "is_leaf", "a1", "a2", "a3"))).alias("n"))
    primes = (M1, M2, M3)

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            ids, node_ids, hashes = [], [], ([], [], [])
            for tree_id, rows in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                acc = {r["node_id"]: ([r["a1"], r["a2"], r["a3"]] if r["is_leaf"] else [0, 0, 0]) for r in rows}
                for r in rows:
                    mine = acc[r["node_id"]]
                    if r["parent_id"] in acc:
                        above = acc[r["parent_id"]]
                        for k in range(3):
                            above[k] = (above[k] + mine[k]) % primes[k]
                    ids.append(tree_id)
                    node_ids.append(r["node_id"])
                    for k in range(3):
                        hashes[k].append(mine[k] % primes[k])
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(node_ids, pa.int32()), *[pa.array(h, pa.int64()) for h in hashes]], ["tree_id", "node_id", "h1", "h2", "h3"])

    return full.mapInArrow(run, "tree_id long, node_id int, h1 long, h2 long, h3 long")


def bipartition_table(found: DataFrame, block: int = 65536) -> DataFrame:
    """(block, h1, h2, card, n_support, support) of inner clusters: ids relative to the block's first tree, ascending. A
    block bounds the list, and with it the skew of a cluster that every tree has."""
    inner = found.where("kind = 'inner'").select(F.floor(F.col("tree_id") / block).cast("int").alias("block"), (F.col("tree_id") % block).cast("int").alias("id"), "h1", "h2", "card")
    return inner.groupBy("block", "h1", "h2", "card").agg(F.count("*").alias("n_support"), F.array_sort(F.collect_list("id")).alias("support"))


def support_counts(found: DataFrame) -> DataFrame:
    """(h1, h2, card, n_support) over all trees: longs only, so a hash aggregate that combines before the shuffle."""
    return found.where("kind = 'inner'").groupBy("h1", "h2", "card").agg(F.count("*").alias("n_support"))


def collisions(found: DataFrame, m1: int = M1, m2: int = M2) -> DataFrame:
    """Keys (h1 mod m1, h2 mod m2) under which two different clusters meet, told by the third hash or the cardinality.
    The smaller moduli are there to force collisions in tests."""
    key = found.where("kind = 'inner'").select((F.col("h1") % m1).alias("h1"), (F.col("h2") % m2).alias("h2"), "h3", "card")
    spread = key.groupBy("h1", "h2").agg(F.min("h3").alias("lo"), F.max("h3").alias("hi"), F.min("card").alias("c"), F.max("card").alias("d"))
    return spread.where("lo <> hi or c <> d").select("h1", "h2")


def collision_bound(n_unique: int, m1: int = M1, m2: int = M2) -> dict[str, float]:
    """Chance that a given pair collides, and an upper bound for any pair among n_unique bipartitions."""
    return {"pair": 1 / (m1 * m2), "any": min(1.0, n_unique * n_unique / (2 * m1 * m2))}


def choose_side(table: DataFrame, n_trees: Column) -> DataFrame:
    """sign and ids of the smaller of in-set (+) and out-set (-), the in-set on a tie, from column support."""
    out = F.array_except(F.sequence(F.lit(0), (n_trees - 1).cast("int")), F.col("support"))
    small = F.size("support") * 2 <= n_trees
    return table.withColumn("sign", F.when(small, "+").otherwise("-")).withColumn("ids", F.when(small, F.col("support")).otherwise(out))
