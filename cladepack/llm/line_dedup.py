"""Fuzzy line dedup by MinHash.

A line's signature is the one-permutation MinHash of its character shingles: each shingle's hash falls into one of
BANDS * ROWS bins, which keep their least value; an empty bin takes over the value of another that is picked by a hash of
its number, so equal sets still agree. Lines that agree in a whole band share a tile. With 10 bands of 4 values a pair of
similarity 0.8 meets in some band with a probability of 0.995, and a more similar one more surely.

Pairs within tiles are verified by the exact Jaccard similarity of their shingle sets; verified links go to the
distributed union-find, and of each component the line that comes first (least doc_id, then line number) stays.

Equal lines are one member, whatever their number. Lines shorter than a shingle only match equal lines.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, HOT_GROUPS, Scratch, batch_of, distinct, fresh, lookup, map_arrow, maybe_broadcast, mix64, numbered, signed
from .components import linked, resolve_tiles

SHINGLE, BANDS, ROWS = 6, 10, 4
_BINS = BANDS * ROWS
_NONE = np.uint64(0xFFFFFFFFFFFFFFFF)
_P = np.uint64(0x9E3779B97F4A7C15)
_PIECE = 1 << 18
#: Shingles hashed at once: what stays in a core's cache.
_STRETCH = 1 << 14
#: For each bin the others in the order in which an empty one tries them; fixed by a rule, not by data.
_DONORS = np.stack([np.random.default_rng(1000 + b).permutation(_BINS) for b in range(_BINS)])


def shingle_hashes(code: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(line, hash) of all shingles of lines given as ascending ranges of code points, in order, a bounded number at a time.
    All places of a stretch are hashed, which reads it straight on; the few across two lines are left out."""
    counts = np.maximum(0, ends - starts - SHINGLE + 1)
    line = np.repeat(np.arange(len(starts)), counts)
    at = np.arange(len(line)) + np.repeat(starts - (np.cumsum(counts) - counts), counts)
    for a in range(0, len(at), _STRETCH):
        i = at[a : a + _STRETCH]
        first, n = int(i[0]), int(i[-1] - i[0]) + 1
        c = code[first : first + n + SHINGLE - 1].astype(np.uint64)
        h = c[:n]
        for j in range(1, SHINGLE):
            h = h * _P
            h += c[j : j + n]
        yield line[a : a + _STRETCH], mix64(h if n == len(i) else h[i - first])


def code_points(lines: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Lower-cased lines in one array of code points, with their starts and ends."""
    low = [x.lower() for x in lines]
    ends = np.cumsum([len(x) for x in low])
    return np.frombuffer("".join(low).encode("utf-32-le", "surrogatepass"), np.uint32), np.concatenate(([0], ends[:-1])), ends


def signatures(code: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """MinHash bins (lines x bins) of lines given as ranges of code points; all-ones rows for lines without shingles."""
    sig = np.full(len(starts) * _BINS, _NONE, np.uint64)
    for own, h in shingle_hashes(code, starts, ends):
        np.minimum.at(sig, own * _BINS + ((h >> np.uint64(32)) * np.uint64(_BINS) >> np.uint64(32)).astype(np.int64), h)
    sig = sig.reshape(-1, _BINS)
    empty = sig == _NONE
    some = ~empty.all(1) & empty.any(1)
    if some.any():
        part, gap = sig[some], empty[some]
        full = part.copy()
        row, own = np.nonzero(gap)
        for t in range(_BINS):
            donor = _DONORS[own, t]
            use = ~gap[row, donor]
            full[row[use], own[use]] = part[row[use], donor[use]] + np.uint64(t + 1)
            row, own = row[~use], own[~use]
            if not len(row):
                break
        sig[some] = full
    return sig


def band_keys(sig: np.ndarray) -> np.ndarray:
    """One 64-bit key for each line and band."""
    s = sig.reshape(len(sig), BANDS, ROWS)
    out = np.repeat(np.arange(1, BANDS + 1, dtype=np.uint64)[None, :], len(sig), 0) * _P
    for r in range(ROWS):
        out = mix64(out ^ s[:, :, r])
    return out


def shingles(line: str) -> set[str]:
    low = line.lower()
    return {low[i : i + SHINGLE] for i in range(len(low) - SHINGLE + 1)}


def _line_tiles(batch: pa.RecordBatch, hot: dict[int, int]):
    lines: dict[str, list[int]] = {}
    for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
        if text:
            for line in text.split("\n"):
                if len(line) >= SHINGLE and line.strip(" \t\r\n\x0b\x0c"):
                    lines.setdefault(line, []).append(doc)
    hashes = {x: xxhash.xxh64_intdigest(x.encode("utf-8", "surrogatepass"), 42) for x in lines}
    # a hot line comes from the document that has it first
    items = [x for x, docs in lines.items() if (lead := hot.get(hashes[x], docs[0])) in docs or lead is None]
    at = 0
    while at < len(items):
        size, end = 0, at
        while end < len(items) and (end == at or size + len(items[end]) <= _PIECE):
            size += len(items[end])
            end += 1
        keys = band_keys(signatures(*code_points(items[at:end])))
        m = np.array([hashes[x] for x in items[at:end]], np.uint64)
        yield batch_of({"tile": signed(keys.ravel()), "m": signed(np.repeat(m, BANDS))})
        at = end


def shingle_sets(lines: list[str]) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each line."""
    found = list(shingle_hashes(*code_points(lines)))
    line, h = (np.concatenate(x) for x in zip(*found, strict=True)) if found else (np.zeros(0, np.int64), np.zeros(0, np.uint64))
    edges = np.searchsorted(line, np.arange(len(lines) + 1))
    return [distinct(h[x:y]) for x, y in zip(edges[:-1], edges[1:], strict=True)]


def _line_pairs(batch: pa.RecordBatch, num: int, den: int):
    if batch.num_rows > 1 and batch.column(2).nbytes + batch.column(3).nbytes > 1 << 22:  # long lines
        half = batch.num_rows // 2
        yield from _line_pairs(batch.slice(0, half), num, den)
        yield from _line_pairs(batch.slice(half), num, den)
        return
    one, two = batch.column(2).dictionary_encode(), batch.column(3).dictionary_encode()
    x, y = shingle_sets(one.dictionary.to_pylist()), shingle_sets(two.dictionary.to_pylist())
    keep = [linked(x[i], y[j], num, den) for i, j in zip(one.indices.to_pylist(), two.indices.to_pylist(), strict=True)]
    yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))


def line_components(docs: DataFrame, num: int = 4, den: int = 5, row_col: str | None = None) -> tuple[DataFrame, DataFrame, int]:
    """Occurrences (row, doc_id, line_no, m) of the lines of docs, where m is a hash of the line and null for blank ones and
    for texts without lines; the groups (m, n, keep_row, keep_line) of lines that occur or match more than once; the number
    of occurrences. Rows are numbered if no column does it."""
    scratch = Scratch(docs.sparkSession, "line-dedup")
    row = F.monotonically_increasing_id() if row_col is None else F.col(row_col)
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), row.alias("row"))
    lines = text.select("row", "doc_id", F.posexplode_outer(F.split("text", "\n")).alias("line_no", "line"))
    seen = scratch.save(lines.select("row", "doc_id", "line_no", F.when(F.col("line").rlike(r"[^\x20\x09-\x0D]"), F.xxhash64("line")).alias("m")))
    n_rows = seen.count()
    first = F.struct("doc_id", "line_no", "row")
    uniq = scratch.save(seen.where("m is not null").groupBy("m").agg(F.count("*").alias("n"), F.min(first).alias("first")))

    hot = uniq.where(F.col("n") > max(1000, n_rows // HOT_GROUPS)).select("m", F.col("first.doc_id").alias("rep")).collect()  # fewer than HOT_GROUPS
    sent = docs.sparkSession.sparkContext.broadcast({r["m"] & 0xFFFFFFFFFFFFFFFF: r["rep"] for r in hot})
    rows = map_arrow(text.select("doc_id", "text"), lambda b: _line_tiles(b, sent.value), "tile long, m long", 256)
    w = Window.partitionBy("tile")
    tiles = scratch.save(rows.withColumn("lo", F.min("m").over(w)).withColumn("hi", F.max("m").over(w)).where("lo <> hi").select("tile", "m").distinct())

    bodies = None

    def load(wanted: DataFrame) -> None:
        """The lines that are left, each from where it stands first."""
        nonlocal bodies
        places = scratch.save(uniq.join(maybe_broadcast(wanted), "m", "left_semi").select("m", F.col("first.doc_id").alias("in_doc"), F.col("first.line_no").alias("line_no")))
        rows = lines.withColumn("m", F.xxhash64("line")).join(maybe_broadcast(places), ["m", "line_no"]).where(F.col("doc_id").eqNullSafe(F.col("in_doc")))
        bodies = scratch.save(rows.select("m", "line"))
        if bodies.count() > places.count():  # rows with one id hold the line at one place
            bodies = scratch.save(bodies.dropDuplicates(["m"]))

    def verify(pairs: DataFrame) -> DataFrame:
        ends = scratch.save(pairs.select(F.col("a").alias("m")).union(pairs.select(F.col("b").alias("m"))).distinct())
        held = bodies.join(maybe_broadcast(ends), "m", "left_semi")
        one, two = held.select(F.col("m").alias("a"), F.col("line").alias("x")), held.select(F.col("m").alias("b"), F.col("line").alias("y"))
        return map_arrow(pairs.join(one, "a").join(two, "b").select("a", "b", "x", "y"), lambda b: _line_pairs(b, num, den), "a long, b long", 4096)

    def sketch(wanted: DataFrame) -> DataFrame:
        return bodies.join(maybe_broadcast(wanted), "m", "left_semi").select("m", F.length("line").cast("long").alias("n"), F.encode("line", "utf-8").alias("bits"))

    def expand(bits: list[bytes]) -> list[np.ndarray]:
        return shingle_sets([x.decode() for x in bits])

    parts, _ = resolve_tiles(scratch, tiles, load, sketch, verify, num, den, bound=False, small=4, expand=expand)
    parts = parts.select(F.col("node").alias("m"), "component")
    named = uniq.join(maybe_broadcast(parts), "m", "left").where("component is not null or n > 1")
    named = scratch.save(named.select("m", "n", "first", F.coalesce("component", "m").alias("component")))
    keep = named.groupBy("component").agg(F.min("first").alias("keep"))
    groups = scratch.save(named.join(keep, "component").select("m", "n", F.col("keep.row").alias("keep_row"), F.col("keep.line_no").alias("keep_line")))
    return seen, groups, n_rows


def duplicate_lines(docs: DataFrame, num: int = 4, den: int = 5) -> DataFrame:
    """(doc_id, n_lines, n_dropped, dropped) for every row of docs; dropped has the numbers (from 0) of the lines that are
    equal or similar (Jaccard num / den or more, or linked over others) to an earlier line, by doc_id, line number and place
    of the row; a null id comes before all others.

    Blank lines are kept and count; null texts have no lines. Rows with equal or null ids stay rows of their own. Lines of
    any length are taken whole. An empty table gives an empty result; other columns are ignored.
    """
    return _dropped(docs, num, den).drop("row")


def _dropped(docs: DataFrame, num: int, den: int, row_col: str | None = None) -> DataFrame:
    seen, groups, n_rows = line_components(docs, num, den, row_col)
    n_groups = groups.count()
    named = seen.join(F.broadcast(groups), "m", "left") if n_groups <= BROADCAST_ROWS // 2 else lookup(seen, groups, ["m"], "n", n_rows)
    gone = F.col("keep_row").isNotNull() & ~((F.col("keep_row") == F.col("row")) & (F.col("keep_line") == F.col("line_no")))
    out = named.groupBy("row").agg(F.first("doc_id").alias("doc_id"), F.count("line_no").alias("n_lines"), F.array_sort(F.collect_list(F.when(gone, F.col("line_no")))).alias("dropped"))
    return out.select("row", "doc_id", "n_lines", F.size("dropped").cast("long").alias("n_dropped"), "dropped")


def drop_duplicate_lines(docs: DataFrame, num: int = 4, den: int = 5) -> DataFrame:
    """docs with the duplicate lines taken out of their texts, columns unchanged."""
    rows, row = numbered(Scratch(docs.sparkSession, "lines"), docs)
    cut = fresh(rows, "cut")
    gone = _dropped(rows, num, den, row).where("n_dropped > 0").select(F.col("row").alias(row), F.col("dropped").alias(cut))
    lines = F.split(F.col("text"), "\n")
    left = F.array_join(F.filter(F.transform(lines, lambda x, i: F.when(~F.array_contains(F.col(cut), i), x)), lambda x: x.isNotNull()), "\n")
    return rows.join(gone, row, "left").withColumn("text", F.when(F.col(cut).isNull(), F.col("text")).otherwise(left)).select(*docs.columns)
