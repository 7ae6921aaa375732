"""N-gram Jaccard join: documents whose word-shingle sets have a Jaccard similarity of num / den or more.

Size-banded tiles. A document's distinct shingle hashes, in order, are cut into K segments of the hash space; K follows
from the band of set sizes it lies in. Two sets of similarity num / den differ in at most D elements, so of the segments
that one of them fills, all but D are the same in the other. K is half as many again as the band's D; then linked
documents of a band share a tile (band, segment, content of the segment), and no link is lost. A document that could
also have a partner in the band below stands in that band's tiles as well. The few documents that fill no more than D
segments also stand in one tile for each of their elements. A tile is much rarer than a shingle: a passage or a frequent
shingle that documents share does not put them into one tile, only a whole segment in common does.

Linked documents share not one tile but all that one of them fills less D, its need. A tile of one document is in no link,
and a document with fewer other tiles than its need has none at all. Of the s tiles of a document that are left, in an
order common to all (rare ones first), the first s - need + 1 hold one that any linked document has among its first, too:
only these go on.

Within tiles pairs are settled as components.resolve_tiles says. A pair is checked by its sizes and hashed bitmaps first:
a bit set in one and not in the other is an element the other lacks, which bounds the overlap from above. Pairs that the
bound leaves are intersected as sorted arrays, exactly.

Equal sets are one member (its 64-bit set hash), whatever the number of copies.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import HOT_GROUPS, Scratch, batch_of, lookup, map_arrow, maybe_broadcast, mix64, numbered, shingle_sets, signed, without, word_hashes
from .components import bitmap, linked, resolve_tiles

_BAND0, _GROWTH = 8, 1.5
#: Bits of a tile's key: two keys that meet by chance only make a pair to verify. The unused bytes stand last in a row, beside
#: the next row's head, where the shuffle's codec takes them.
_TILE = np.uint64((1 << 48) - 1)
_A, _B, _C = np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F), np.uint64(0xE7037ED1A0B428DB)


def most_apart(n: int, num: int, den: int) -> int:
    """The largest symmetric difference that a set of n elements can have with a set linked to it."""
    return (n + n * den // num) * (den - num) // (den + num)


def band_limits(n: int) -> list[int]:
    """Upper sizes of the bands up to the one of n."""
    tops = [_BAND0]
    while tops[-1] < n:
        tops.append(int(tops[-1] * _GROWTH))
    return tops


def tile_keys(s: np.ndarray, num: int, den: int) -> tuple[np.ndarray, list[int]]:
    """The tiles of a set, given as sorted hashes, and how many of them a linked set shares at least: the tiles of an even
    band are even and count for the first need, those of an odd band for the second. None if only an equal set can be
    linked with it."""
    n, need = len(s), [0, 0]
    apart = most_apart(n, num, den)
    if apart == 0:
        return np.zeros(0, np.uint64), need
    tops = band_limits(n)
    own = len(tops) - 1
    bands = [own] if own == 0 or n > tops[own - 1] * den // num else [own, own - 1]
    high, out = s >> np.uint64(32), []
    spread = mix64(s ^ _A)
    for band in bands:
        top = most_apart(tops[band], num, den)
        k = top + top // 2 + 3
        part = (high * np.uint64(k)) >> np.uint64(32)
        starts = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1])))
        sums = np.add.reduceat(spread, starts)
        keys = mix64(sums ^ mix64(part[starts] * _B + np.uint64(band + 1)))
        if len(starts) <= apart:
            keys = np.concatenate([keys, mix64(s * _C + np.uint64(band + 1))])
        keys = keys & _TILE & ~np.uint64(1) | np.uint64(band % 2)
        need[band % 2] = max(1, len(np.unique(keys[: len(starts)])) - apart)
        out.append(keys)
    return np.concatenate(out), need


def set_hash(s: np.ndarray) -> np.uint64:
    with np.errstate(over="ignore"):
        return mix64((mix64(s).sum(dtype=np.uint64, keepdims=True)) + np.uint64(len(s)))[0]


def shingle_profile(docs: DataFrame, n: int, num: int, den: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, text_hash, n_shingles, set_hash, needs); a text without words has 0 shingles and no set_hash."""

    def fn(batch: pa.RecordBatch):
        sets = shingle_sets(*word_hashes(batch.column(1)), n)
        hashes = pa.array([int(set_hash(s).view(np.int64)) if len(s) else None for s in sets], pa.int64())
        needs = pa.array([tile_keys(s, num, den)[1] if len(s) else None for s in sets], pa.list_(pa.int32()))
        yield batch_of({"doc_id": batch.column(0), "text_hash": batch.column(2), "n_shingles": pa.array([len(s) for s in sets], pa.int64()), "set_hash": hashes, "needs": needs})

    text = F.col(text_col).cast("string")
    return map_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("text_hash")), fn, "doc_id long, text_hash long, n_shingles long, set_hash long, needs array<int>")


def shared_tiles(scratch: Scratch, rows: DataFrame, needs: DataFrame) -> DataFrame:
    """The tiles (tile, m) in which a link can show, without repeated rows. rows: (tile, m) of all sets; needs: (m, needs)."""
    w = Window.partitionBy("tile")
    common = rows.withColumn("lo", F.min("m").over(w)).withColumn("hi", F.max("m").over(w)).withColumn("c", F.count("*").over(w))
    common = scratch.save(common.where("lo <> hi").select("tile", "m", "c").distinct())
    # rows of one set and parity: as many as it has segments at most
    mine = Window.partitionBy("m", "odd")
    ranked = common.join(needs, "m").select("tile", "m", "c", F.expr("cast(pmod(tile, 2) as int)").alias("odd"), F.expr("get(needs, cast(pmod(tile, 2) as int))").alias("need"))
    ranked = ranked.withColumn("s", F.count("*").over(mine)).withColumn("at", F.row_number().over(mine.orderBy("c", "tile"))).where("at <= s - need + 1")
    out = scratch.save(ranked.select("tile", "m"))
    scratch.drop(common)
    return out


def ngram_jaccard_components(docs: DataFrame, n: int = 5, num: int = 4, den: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, n_copies, linked) for every row of docs.

    component_id is the smallest doc_id reachable over links of similarity num / den or more, the row's own included;
    n_copies counts the rows with an equal set; linked says whether the row's set is linked with a different one.
    Null, empty and white-space texts have no shingles and stand alone. Repeated doc_ids are rows of their own that
    share the smallest id; a null doc_id counts as larger than all others. Texts of any length are read whole, their
    words piece by piece. An empty table gives an empty result; other columns are ignored.

    A set is known by a 64-bit hash of its shingles' hashes, and two different sets are taken for one with a probability of
    2 to the -64.
    """
    spark = docs.sparkSession
    scratch = Scratch(spark, "ngram-jaccard")
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    profile = scratch.save(shingle_profile(text, n, num, den))
    n_rows = profile.count()
    sets = profile.where("set_hash is not null").groupBy("set_hash").agg(F.min("doc_id").alias("rep"), F.count("*").alias("n_copies"), F.first("needs").alias("needs"), F.min(F.struct("doc_id", "text_hash")).alias("found_in"))
    sets = scratch.save(sets)

    # of a hot group of equal sets only its representative enters the tiles; there are fewer than HOT_GROUPS of those
    hot = sets.where((F.col("n_copies") > max(1000, n_rows // HOT_GROUPS)) & F.col("rep").isNotNull()).select("set_hash", "rep")
    sent = spark.sparkContext.broadcast({r["set_hash"]: r["rep"] for r in hot.collect()})

    def tiles_of(batch: pa.RecordBatch):
        keys, member, seen = [], [], set()
        for doc_id, s in zip(batch.column(0).to_pylist(), shingle_sets(*word_hashes(batch.column(1)), n), strict=True):
            m = set_hash(s) if len(s) else np.uint64(0)
            if int(m) not in seen and sent.value.get(int(m.view(np.int64)), doc_id) == doc_id:
                seen.add(int(m))
                keys.append(t := tile_keys(s, num, den)[0])
                member.append(np.full(len(t), m, np.uint64))
        if sum(map(len, keys)):
            yield batch_of({"m": signed(np.concatenate(member)), "tile": signed(np.concatenate(keys))})

    tiles = shared_tiles(scratch, map_arrow(text, tiles_of, "m long, tile long"), sets.select(F.col("set_hash").alias("m"), "needs"))
    arrays = None

    def load(wanted: DataFrame) -> None:
        """The arrays of the sets that are left, from their texts; the bitmaps are a column of them."""
        nonlocal arrays
        named = scratch.save(wanted.select(F.col("m").alias("set_hash")).join(sets, "set_hash").select("set_hash", F.col("found_in.doc_id").alias("in_doc"), F.col("found_in.text_hash").alias("text_hash")))

        def arrays_of(batch: pa.RecordBatch):
            found = shingle_sets(*word_hashes(batch.column(1)), n)
            mine = pa.array([len(s) > 0 and int(set_hash(s).view(np.int64)) == m for s, m in zip(found, batch.column(0).to_pylist(), strict=True)], pa.bool_())
            yield batch_of({"m": batch.column(0), "n": pa.array([len(s) for s in found], pa.int64()), "s": pa.array([s.tobytes() for s in found], pa.binary()), "bits": pa.array([bitmap(s) for s in found], pa.binary())}).filter(mine)

        rows = text.withColumn("text_hash", F.xxhash64("text")).join(maybe_broadcast(named), "text_hash").where(F.col("doc_id").eqNullSafe(F.col("in_doc")))
        rows = scratch.save(map_arrow(rows.select("set_hash", "text"), arrays_of, "m long, n long, s binary, bits binary"), codec="none")
        if rows.count() > named.count():  # a row stands in the table more than once
            rows = scratch.save(rows.dropDuplicates(["m"]), codec="none")
        arrays = rows

    def verify(pairs: DataFrame) -> DataFrame:
        def fn(batch: pa.RecordBatch):
            keep = []
            for a, b in zip(batch.column(2), batch.column(3), strict=True):
                keep.append(linked(np.frombuffer(a.as_buffer(), np.uint64), np.frombuffer(b.as_buffer(), np.uint64), num, den))
            yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))

        # few sets are left in pairs: only their arrays are shuffled
        ends = scratch.save(pairs.select(F.col("a").alias("m")).union(pairs.select(F.col("b").alias("m"))).distinct())
        held = arrays.select("m", "s").join(maybe_broadcast(ends), "m", "left_semi")
        one, two = (held.select(F.col("m").alias(x), F.col("s").alias("s" + x)) for x in "ab")
        return map_arrow(pairs.join(one, "a").join(two, "b").select("a", "b", "sa", "sb"), fn, "a long, b long")

    parts, links = resolve_tiles(scratch, tiles, load, lambda wanted: arrays.select("m", "n", "bits"), verify, num, den)
    ends = links.select(F.col("a").alias("set_hash")).union(links.select(F.col("b").alias("set_hash"))).distinct().withColumn("linked", F.lit(True))
    joined = sets.join(parts.select(F.col("node").alias("set_hash"), "component"), "set_hash", "left").withColumn("component", F.coalesce("component", "set_hash"))
    least = joined.groupBy("component").agg(F.min("rep").alias("component_id"))
    named = joined.join(least, "component").join(ends, "set_hash", "left").select("set_hash", "n_copies", "component_id", F.coalesce("linked", F.lit(False)).alias("linked"))
    out = lookup(profile, scratch.save(named), ["set_hash"], "n_copies", n_rows)
    return out.select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"), F.coalesce("n_copies", F.lit(1)).cast("long").alias("n_copies"), F.coalesce("linked", F.lit(False)).alias("linked"))


def keep_one_of_each(docs: DataFrame, n: int = 5, num: int = 4, den: int = 5) -> DataFrame:
    """The rows of docs without near copies, columns unchanged: of each component the row with the smallest doc_id stays,
    null ids last, and of rows with equal ids the first. Texts without words stand alone and stay."""
    scratch = Scratch(docs.sparkSession, "near")
    rows, row = numbered(scratch, docs)
    found = ngram_jaccard_components(rows, n, num, den, id_col=row).where("n_copies > 1 or linked").select(F.col("doc_id").alias("row"), "component_id")
    order = F.struct(F.col("doc_id").isNull().alias("no_id"), F.col("doc_id").alias("id"), F.col(row).alias("row"))
    named = scratch.save(found.join(rows.select(F.col(row).alias("row"), order.alias("order")), "row"))
    keep = named.groupBy("component_id").agg(F.min("order").alias("keep")).select(F.col("keep.row").alias("row"))
    return without(rows, row, named.join(keep, "row", "left_anti").select("row"))
