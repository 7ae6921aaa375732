"""Exact dedup with static binary-fuse filters.

A snapshot is an immutable set of text digests, dealt into buckets by digest. Each bucket has its exact table and one
binary-fuse filter over its 64-bit keys (three probes, about nine bits a key, no false negatives). Digests of a new batch
are grouped among themselves first, then screened by the filters of their buckets; a miss is surely new, and only hits
are joined with the exact buckets, where length and SHA-256 decide. Before anything is dropped, the texts of every group
are compared byte by byte: a scan groups the candidate texts themselves and a digest that covers two texts raises an error.

Nothing here depends on the number of copies in a group: groups are combined before each shuffle, and hot groups join
their rows by broadcast (common.lookup).
"""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, batch_of, lookup, map_arrow, maybe_broadcast, mix64, numbered, without

#: Aimed number of keys in one bucket; the number of buckets follows the input.
BUCKET_KEYS = 200_000


# --- binary-fuse filter -------------------------------------------------------------------------------------------


class FuseFilter:
    """Static 8-bit binary-fuse filter with three probes in consecutive segments.

    build() takes distinct 64-bit keys. contains() is true for every key of the set and for about 1 of 256 others.
    """

    def __init__(self, seed: int, segment: int, segments: int, prints: np.ndarray):
        self.seed, self.segment, self.segments, self.prints = seed, segment, segments, prints

    @staticmethod
    def _shape(n: int) -> tuple[int, int]:
        segment = 1 << min(18, max(2, int(np.floor(np.log(max(n, 2)) / np.log(3.33) + 2.25))))
        factor = max(1.125, 0.875 + 0.25 * np.log(1_000_000) / np.log(max(n, 2)))
        return segment, max(1, -(-int(n * factor) // segment) - 2)

    @staticmethod
    def _probe(keys: np.ndarray, seed: int, segment: int, segments: int) -> tuple[np.ndarray, np.ndarray]:
        h = mix64(keys.view(np.uint64) + np.uint64(seed))
        start = ((h >> np.uint64(32)) * np.uint64(segments) >> np.uint64(32)).astype(np.int64) * segment
        mask = np.uint64(segment - 1)
        at = np.stack([start + j * segment + ((h >> np.uint64(s)) & mask).astype(np.int64) for j, s in enumerate((0, 18, 36))])
        return at, (mix64(h) >> np.uint64(56)).astype(np.uint8)

    @classmethod
    def build(cls, keys: np.ndarray) -> FuseFilter:
        keys = np.unique(np.asarray(keys, dtype=np.int64))
        segment, segments = cls._shape(len(keys))
        size = (segments + 2) * segment
        for attempt in range(1, 200):
            seed = attempt * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF
            at, print_ = cls._probe(keys, seed, segment, segments)
            order, slot = cls._peel(at, size, len(keys))
            if len(order) == len(keys):
                prints = np.zeros(size, np.uint8)
                cells, own = at.T.tolist(), print_.tolist()
                for k, s in zip(reversed(order), reversed(slot), strict=True):
                    a, b, c = cells[k]
                    prints[s] = own[k] ^ int(prints[a]) ^ int(prints[b]) ^ int(prints[c]) ^ int(prints[s])
                return cls(seed, segment, segments, prints)
            if attempt % 20 == 0:
                segments += max(1, segments // 10)
                size = (segments + 2) * segment
        raise RuntimeError("binary-fuse filter could not be built")

    @staticmethod
    def _peel(at: np.ndarray, size: int, n: int) -> tuple[list[int], list[int]]:
        count = np.bincount(at.ravel(), minlength=size)
        mixed = np.zeros(size, np.int64)
        for row in at:
            np.bitwise_xor.at(mixed, row, np.arange(n))
        count, mixed, cells = count.tolist(), mixed.tolist(), at.T.tolist()
        stack = [i for i, c in enumerate(count) if c == 1]
        order, slot = [], []
        while stack:
            s = stack.pop()
            if count[s] != 1:
                continue
            k = mixed[s]
            order.append(k)
            slot.append(s)
            for x in cells[k]:
                count[x] -= 1
                mixed[x] ^= k
                if count[x] == 1:
                    stack.append(x)
        return order, slot

    def contains(self, keys: np.ndarray) -> np.ndarray:
        at, print_ = self._probe(np.asarray(keys, dtype=np.int64), self.seed, self.segment, self.segments)
        return self.prints[at[0]] ^ self.prints[at[1]] ^ self.prints[at[2]] == print_

    def pack(self) -> bytes:
        return np.array([self.seed, self.segment, self.segments], np.uint64).tobytes() + self.prints.tobytes()

    @classmethod
    def unpack(cls, blob: bytes) -> FuseFilter:
        seed, segment, segments = (int(x) for x in np.frombuffer(blob[:24], np.uint64))
        return cls(seed, segment, segments, np.frombuffer(blob, np.uint8, offset=24))


# --- digests ------------------------------------------------------------------------------------------------------


def text_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None) -> DataFrame:
    """(doc_id, row, key, n_bytes, sha): SHA-256 of the text with A-Z lower-cased, its first eight bytes as a 64-bit key, and
    its length in bytes. Null counts as the empty text. Rows are numbered if no column does it."""

    def fn(batch: pa.RecordBatch):
        low = pc.ascii_lower(batch.column(2).fill_null(""))
        shas = [hashlib.sha256(x.as_buffer()).digest() for x in low]
        keys = np.frombuffer(b"".join(x[:8] for x in shas), dtype=np.int64)
        yield batch_of({"doc_id": batch.column(0), "row": batch.column(1), "key": pa.array(keys), "n_bytes": pc.binary_length(low).cast(pa.int64()), "sha": pa.array(shas, pa.binary())})

    row = F.monotonically_increasing_id() if row_col is None else F.col(row_col).cast("long")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), row.alias("row"), F.col(text_col).cast("string").alias("text"))
    return map_arrow(rows, fn, "doc_id long, row long, key long, n_bytes long, sha binary")


def _groups(digests: DataFrame) -> DataFrame:
    return digests.groupBy("key", "n_bytes", "sha").agg(F.max(F.struct("doc_id", "row")).alias("keep"), F.count("*").alias("group_size"))


class Snapshot:
    """An immutable set of grouped digests in buckets, with one filter for each bucket."""

    def __init__(self, scratch: Scratch, groups: DataFrame, n_groups: int):
        self.n_buckets = max(1, -(-n_groups // BUCKET_KEYS))
        self.groups = groups

        def build(keys: pd.DataFrame) -> pd.DataFrame:
            return pd.DataFrame({"bucket": [keys["bucket"].iloc[0]], "filter": [FuseFilter.build(keys["key"].to_numpy()).pack()]})

        keyed = groups.select(self.bucket().alias("bucket"), "key").distinct()
        self.filters = scratch.save(keyed.groupBy("bucket").applyInPandas(build, "bucket long, filter binary"))

    def bucket(self):
        return F.pmod(F.xxhash64("key"), F.lit(self.n_buckets))

    def screen(self, batch: DataFrame) -> DataFrame:
        """Rows of batch (distinct digests) that pass the filter of their bucket: every key that the snapshot holds."""

        def probe(rows: pd.DataFrame, filters: pd.DataFrame) -> pd.DataFrame:
            if not len(filters) or not len(rows):
                return rows.iloc[:0]
            return rows[FuseFilter.unpack(filters["filter"].iloc[0]).contains(rows["key"].to_numpy())]

        dealt = batch.withColumn("bucket", self.bucket())
        return dealt.groupBy("bucket").cogroup(self.filters.groupBy("bucket")).applyInPandas(probe, dealt.schema).drop("bucket")

    def matches(self, batch: DataFrame) -> DataFrame:
        """Screened rows whose digest is in the exact buckets, with the snapshot's group."""
        mine = self.groups.select("key", "n_bytes", "sha", F.col("keep").alias("old_keep"), F.col("group_size").alias("old_size"))
        return self.screen(batch).join(mine, ["key", "n_bytes", "sha"])


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256) for every row of docs.

    The rows are taken as two generations, by a hash of their number: the first is the snapshot, the second the batch that
    it screens. Texts are equal if they are the same bytes after lower-casing A-Z; null counts as empty. Of equal texts the
    row with the largest doc_id stays, null being less than any; of rows with that id the last, so exactly one row of each
    group is kept. An empty table gives an empty result; other columns are ignored.
    """
    return _marked(docs, id_col, text_col).drop("row")


def _marked(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", row_col: str | None = None) -> DataFrame:
    spark = docs.sparkSession
    scratch = Scratch(spark, "exact-dedup")
    rows = scratch.save(text_digests(docs, id_col, text_col, row_col))
    n_rows = rows.count()
    old = F.pmod(F.xxhash64("row"), F.lit(2)) == 0
    first, second = scratch.save(_groups(rows.where(old))), scratch.save(_groups(rows.where(~old)))
    snapshot = Snapshot(scratch, first, max(first.count(), second.count()))
    both = scratch.save(snapshot.matches(second))
    merged = both.select("key", "n_bytes", "sha", F.greatest("keep", "old_keep").alias("keep"), (F.col("group_size") + F.col("old_size")).alias("group_size"))
    alone = first.unionByName(second).join(both.select("key", "n_bytes", "sha"), ["key", "n_bytes", "sha"], "left_anti")
    groups = scratch.save(merged.unionByName(alone))
    check_bytes(docs, groups, scratch, id_col, text_col)
    out = lookup(rows, groups, ["key", "n_bytes", "sha"], "group_size", n_rows)
    return out.select("row", "doc_id", F.col("keep.doc_id").alias("keep_id"), "group_size", (F.col("row") == F.col("keep.row")).alias("kept"), F.lower(F.hex("sha")).alias("text_sha256"))


def check_bytes(docs: DataFrame, groups: DataFrame, scratch: Scratch, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Raise if a group of several rows holds two texts that differ in a byte.

    One scan: the texts whose digest is that of a group of several rows are grouped by their bytes, combined before the
    shuffle. The groups' keys are broadcast within the limit; beyond it they meet the texts by shuffle.
    """
    several = scratch.save(groups.where("group_size > 1").select("key").distinct())

    def low(batch: pa.RecordBatch):
        text = pc.ascii_lower(batch.column(0).fill_null(""))
        keys = np.frombuffer(b"".join(hashlib.sha256(x.as_buffer()).digest()[:8] for x in text), dtype=np.int64)
        yield batch_of({"key": pa.array(keys), "text": text})

    texts = map_arrow(docs.select(F.col(text_col).cast("string").alias("text")), low, "key long, text string").join(maybe_broadcast(several), "key", "left_semi")
    clash = texts.groupBy("key", "text").agg(F.count("*").alias("n")).select("key", F.sha2("text", 256).alias("sha")).groupBy("key", "sha").agg(F.count("*").alias("n")).where("n > 1")
    if clash.limit(1).count():
        raise RuntimeError("two different texts share one SHA-256 digest")


def drop_exact_duplicates(docs: DataFrame) -> DataFrame:
    """The kept rows of docs, one of each text, columns unchanged."""
    rows, row = numbered(Scratch(docs.sparkSession, "exact"), docs)
    return without(rows, row, _marked(rows, row_col=row).where("not kept").select("row"))
