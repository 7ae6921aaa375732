"""Shared parts of the text operators: the scratch folder, Arrow helpers, hash kernels, skew-safe lookups."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows above which a side is joined by shuffle rather than broadcast; 16-byte rows, so some 16 MB at most.
BROADCAST_ROWS = 500_000
#: At most so many groups count as hot, whatever the input; they are broadcast.
HOT_GROUPS = 10_000

_own_dir: str | None = None


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir). A temporary one only where none is set and one
    machine runs all."""
    global _own_dir
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir is not set")
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="cladepack-")
        atexit.register(shutil.rmtree, _own_dir, True)
    return "file://" + _own_dir


class Scratch:
    """Tables written to the shared folder, so that a lost executor costs no more than the tasks it ran."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root = spark, f"{shared_dir(spark)}/cladepack/{name}-{uuid.uuid4().hex}"
        self.n = 0

    def save(self, df: DataFrame, codec: str = "zstd") -> DataFrame:
        self.n += 1
        path = f"{self.root}/{self.n}"
        df.write.option("compression", codec).parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, df: DataFrame) -> None:
        """Delete a table that no later plan reads."""
        path = getattr(df, "_scratch_path", None)
        if path:
            jvm = self.spark.sparkContext._jvm
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def maybe_broadcast(df: DataFrame, rows: int | None = None, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Broadcast hint only when the counted rows are within the limit; else Spark shuffles."""
    return F.broadcast(df) if (df.count() if rows is None else rows) <= limit else df


def map_arrow(df: DataFrame, fn: Callable[[pa.RecordBatch], Iterable[pa.RecordBatch]], schema: str, rows_per_piece: int = 512) -> DataFrame:
    """mapInArrow over small pieces of each batch, so that a task's arrays stay small whatever the batch size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, rows_per_piece):
                yield from fn(batch.slice(at, rows_per_piece))

    return df.mapInArrow(run, schema)


# --- vectorised hashing -------------------------------------------------------------------------------------------

_M1, _M2, _P = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53), np.uint64(0x9E3779B97F4A7C15)
_PINV = np.uint64(pow(int(_P), -1, 1 << 64))
_S33 = np.uint64(33)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_CHUNK = 1 << 19


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64 bits."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> _S33
    x *= _M1
    x ^= x >> _S33
    x *= _M2
    x ^= x >> _S33
    return x


def powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n, base, dtype=np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and the offsets of its rows; nulls are empty."""
    column = column.cast(pa.large_string()) if not pa.types.is_large_string(column.type) else column
    if column.null_count:
        column = column.fill_null("")
    off = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    raw = np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]] if data is not None and len(off) else np.zeros(0, np.uint8)
    return raw, off - off[0]


def word_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hash of each word (a run of bytes other than ASCII white space, A-Z lower-cased) and the word offsets of
    the rows. Works through the buffer in pieces that end between words, so memory follows the piece, not the text."""
    raw, off = text_buffer(column)
    n = len(raw)
    hashes, starts_at = [], []
    bound = np.zeros(n + 1, dtype=bool)
    bound[off] = True
    at = 0
    pw = piw = np.zeros(0, np.uint64)
    while at < n:
        end = min(n, at + _CHUNK)
        if end < n:
            cut = np.flatnonzero(_SPACE[raw[at:end]])
            step = _CHUNK
            while not len(cut) and end < n:  # one word longer than the piece
                step *= 2
                end = min(n, at + step)
                cut = np.flatnonzero(_SPACE[raw[at:end]])
            if end < n:
                end = at + int(cut[-1]) + 1
        part = raw[at:end]
        if len(pw) < len(part):
            pw, piw = powers(_P, len(part)), powers(_PINV, len(part))
        ink = ~_SPACE[part]
        first = bound[at:end].copy()
        first[0] = True
        first[1:] |= ~ink[:-1]
        s = np.flatnonzero(ink & first)
        last = np.ones(len(part), dtype=bool)
        last[:-1] = ~ink[1:] | bound[at + 1 : end]
        e = np.flatnonzero(ink & last)
        total = np.cumsum((_LOWER[part].astype(np.uint64) + np.uint64(1)) * pw[: len(part)], dtype=np.uint64)
        before = np.where(s > 0, total[s - 1], np.uint64(0))
        hashes.append(mix64((total[e] - before) * piw[s]))
        starts_at.append(s + at)
        at = end
    if not hashes:
        return np.zeros(0, np.uint64), np.zeros(len(off), np.int64)
    return np.concatenate(hashes), np.searchsorted(np.concatenate(starts_at), off)


def distinct(x: np.ndarray) -> np.ndarray:
    """The distinct values in order; for short arrays faster than numpy's unique, which hashes first."""
    x = np.sort(x)
    return x[np.concatenate(([True], x[1:] != x[:-1]))] if len(x) > 1 else x


def shingle_sets(words: np.ndarray, off: np.ndarray, n: int) -> list[np.ndarray]:
    """For each row the sorted distinct hashes of its n-word shingles; a shorter row is one shingle of all its words."""
    m = powers(_P, n)
    count = len(words) - n + 1
    if count > 0:
        every = words[:count] * m[0]
        for j in range(1, n):
            every = every + words[j : j + count] * m[j]
        every = mix64(every + np.uint64(n))
    out = []
    for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True):
        if b - a >= n:
            out.append(distinct(every[a : b - n + 1]))
        elif b > a:
            with np.errstate(over="ignore"):
                out.append(mix64((words[a:b] * m[: b - a]).sum(dtype=np.uint64, keepdims=True) + np.uint64(b - a)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def signed(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def batch_of(schema: dict[str, pa.Array]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(list(schema.values()), names=list(schema))


# --- skew-safe joins ----------------------------------------------------------------------------------------------


def lookup(rows: DataFrame, groups: DataFrame, keys: list[str], weight: str, n_rows: int) -> DataFrame:
    """Left join of rows with one row per group. A group of more than n_rows / HOT_GROUPS rows is hot; there are fewer
    than HOT_GROUPS of those, so they are broadcast and their rows stay where they are. The others are shuffled."""
    hot = F.col(weight) > max(1000, n_rows // HOT_GROUPS)
    value = [c for c in groups.columns if c not in keys]
    few = groups.where(hot).select(*keys, F.struct(*value).alias("_hot"))
    flagged = rows.join(F.broadcast(few), keys, "left")
    inner = flagged.where("_hot is not null").select(*rows.columns, *[F.col(f"_hot.{c}").alias(c) for c in value])
    rest = flagged.where("_hot is null").select(*rows.columns).join(groups.where(~hot), keys, "left")
    return inner.unionByName(rest.select(*rows.columns, *value))


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df does not have, in any case."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name += "_"
    return name


def numbered(scratch: Scratch, docs: DataFrame) -> tuple[DataFrame, str]:
    """docs, written once, with a number for each row, and the name of that column. Ids may be null or repeat; a row is
    known by its number."""
    row = fresh(docs, "row_number")
    return scratch.save(docs.withColumn(row, F.monotonically_increasing_id())), row


def without(rows: DataFrame, row: str, gone: DataFrame) -> DataFrame:
    """Numbered rows less those whose number is in gone(row), without the number. The numbers are written and counted:
    within the limit they are broadcast, so no text moves; beyond it both sides are shuffled."""
    gone = Scratch(rows.sparkSession, "gone").save(gone.select(F.col("row").alias(row)))
    return rows.join(maybe_broadcast(gone), row, "left_anti").drop(row)


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
