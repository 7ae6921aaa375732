"""Compressing tree collections into independent blocks, and restoring them.

A block holds the trees of a range of ids. Trees are parsed and their clusters gathered where they are read: every input
piece sends on one row for each of its distinct clusters, with the ids of its trees, so clusters that most trees share
are combined before any shuffle. Rows of one cluster meet by its bits, exactly; they are encoded there, and the codes of a
block are put together in the order of their bits. On the way a cluster's bits are a key in the space of its members
(`codes.gap_keys`), since of many taxa most clusters have few. A block of one tree is made where the tree is read. Restoring needs one block only. It is inflated and decoded once, where
it is read, and turned into pieces, one for a range of its trees, with the clusters of those alone. Trees are rebuilt from
pieces: in the same task where blocks are many, else in tasks of their own, to which the pieces are shuffled.
"""

from __future__ import annotations

import bz2
import hashlib
import json
import lzma
import zlib
from collections.abc import Callable, Iterator
from itertools import islice

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernels import codes
from ..kernels import newick as nw
from ..kernels import trees as tk
from .clusters import M1, M2, M3, coefficients

#: Trees of a block at most: ids within a block fit into two bytes.
BLOCK_TREES = 65_536
#: Lengths of a block at most.
BLOCK_LENGTHS = 16_000_000
#: Bytes of the clusters' bits of a block to be restored at most, were every tree fully resolved and no cluster shared.
BLOCK_BITS = 1 << 27
#: Bits that stand unpacked at once.
UNPACKED = 8_000_000
#: Members of clusters that stand listed at once.
MEMBERS = 500_000
CONTAINER = "block_id int, first_tree long, n_trees int, span int, n_taxa int, taxa array<string>, codec string, flags int, n_bip int, raw_bytes long, payload binary, trees binary, lengths binary, labels binary, crc long"
_ENTRY = "block int, key binary, ids binary, lens array<string>, labels array<string>"
_ENCODED = "block int, key binary, card int, entry binary, ids binary, lens array<string>, labels array<string>, bits_size int, ids_size int, n_ids int, sign string"


def restorable_block(n: int) -> int:
    """Trees of a block that one task can hold decoded, of n taxa."""
    return max(1, min(BLOCK_TREES, BLOCK_BITS // max(1, n * n // 8)))


def taxa_of(trees: DataFrame, order: str = "first_tree") -> list[str]:
    """Labels of the taxa in their order, from the tree with the least id; as many as one tree has."""
    row = trees.select("tree_id", "newick").orderBy("tree_id").limit(1).collect()
    if not row:
        return []
    labels = nw.parse(row[0]["newick"]).leaves()
    return sorted(labels) if order == "lexicographic" else labels


# --- clusters of a piece of input ---------------------------------------------------------------------------------


class Extractor:
    """Distinct clusters of a batch of trees. Plain texts go through the batch parser; others, and side data, through the
    full one."""

    def __init__(self, taxa: list[str], block: int, side: bool, rooted: bool = True):
        self.taxa, self.n, self.block, self.side, self.rooted = taxa, len(taxa), block, side, rooted
        self.ordinal = {t: i for i, t in enumerate(taxa)}
        hashes = np.array([nw.hash_label(t.encode()) for t in taxa], np.uint64)
        self.taxa_at = np.argsort(hashes)
        self.taxa_hash = hashes[self.taxa_at]
        self.coef = np.array(coefficients(self.n), np.int64).reshape(-1, 3)

    def __call__(self, ids: np.ndarray, texts: list[str]) -> Iterator[tuple]:
        """(block, key, local ids, lens, labels) of distinct clusters, and (block, b"", local ids) for the trees there."""
        found = None
        if not self.side and self.rooted and self.n and len(np.unique(self.taxa_hash)) == self.n:
            raw = "".join(texts).encode()
            if b"'" not in raw and b"[" not in raw and b" " not in raw and b"\n" not in raw:
                off = np.concatenate(([0], np.cumsum([len(t.encode()) if not t.isascii() else len(t) for t in texts])))
                found = nw.batch_topology(np.frombuffer(raw, np.uint8), off, self.taxa_hash, self.taxa_at)
                if found is not None:
                    taxon, leaf_off, *_ = found
                    sizes = np.diff(leaf_off)
                    marks = np.bincount(np.repeat(np.arange(len(ids)), sizes) * self.n + taxon, minlength=len(ids) * self.n)
                    if (sizes != self.n).any() or marks.max() > 1:
                        found = None
        blocks = ids // self.block
        for b in np.unique(blocks):
            yield int(b), b"", np.sort(ids[blocks == b] % self.block), None, None
        yield from self._fast(ids, found) if found is not None else self._full(ids, texts)

    def _fast(self, ids: np.ndarray, found) -> Iterator[tuple]:
        taxon, _, tree, first, last = found
        inner = last - first + 1 < self.n
        tree, first, last = tree[inner], first[inner], last[inner]
        if not len(tree):
            return
        run = np.concatenate((np.zeros((1, 3), np.int64), np.cumsum(self.coef[taxon], axis=0)))
        h1, h2, h3 = ((run[last + 1, k] - run[first, k]) % m for k, m in enumerate((M1, M2, M3)))
        block, card = ids[tree] // self.block, last - first + 1
        key = h2.astype(np.uint64) * np.uint64(M1) + h1.astype(np.uint64)
        order = np.lexsort((ids[tree], key, block))
        k, b = key[order], block[order]
        new = np.concatenate(([True], (k[1:] != k[:-1]) | (b[1:] != b[:-1])))
        same = ~new[1:]
        if (h3[order][1:][same] != h3[order][:-1][same]).any() or (card[order][1:][same] != card[order][:-1][same]).any():
            raise ValueError("two different bipartitions share both hashes")
        starts = np.flatnonzero(new)
        ends = np.concatenate((starts[1:], [len(order)]))
        rep = order[starts]
        local, upto, lo = (ids[tree] % self.block)[order], np.cumsum(card[rep]), 0
        while lo < len(rep):
            hi = max(lo + 1, int(np.searchsorted(upto, (upto[lo - 1] if lo else 0) + MEMBERS, "right")))
            part = rep[lo:hi]
            sizes = card[part]
            flat = np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes) + np.repeat(first[part], sizes)
            row, member = np.divmod(np.sort(np.repeat(np.arange(len(part)) * self.n, sizes) + taxon[flat]), self.n)
            for key, s, e in zip(codes.cut(*codes.keys_of_members(row, member, len(part))), starts[lo:hi].tolist(), ends[lo:hi].tolist(), strict=True):
                yield int(b[s]), key, local[s:e], None, None
            lo = hi

    def _full(self, ids: np.ndarray, texts: list[str]) -> Iterator[tuple]:
        table: dict[tuple[int, bytes], list] = {}
        for tree_id, text in zip(ids.tolist(), texts, strict=True):
            t = nw.parse(text)
            try:
                at = np.array([self.ordinal[x] for x in t.leaves()])
            except KeyError as e:
                raise ValueError(f"tree {tree_id} has a taxon that others lack: {e}") from None
            if len(at) != self.n:
                raise ValueError(f"tree {tree_id} has {len(at)} taxa of {self.n}")
            for node in range(len(t.label)):
                card = t.last[node] - t.first[node] + 1
                if not self.side and (card == 1 or card == self.n):
                    continue
                members = at[t.first[node] : t.last[node] + 1]
                if not self.rooted and 0 in members:
                    members = np.setdiff1d(np.arange(self.n), members)
                    if len(members) in (0, 1):
                        continue
                got = table.setdefault((tree_id // self.block, codes.pack_bits(members, self.n)), [[], [], []])
                if got[0] and got[0][-1] == tree_id % self.block:
                    continue
                got[0].append(tree_id % self.block)
                got[1].append(t.length[node])
                got[2].append(None if t.leaf[node] else t.label[node])
        for (b, bits), (local, lens, labels) in table.items():
            yield b, codes.keys_of_bits([bits])[0], np.array(local), lens if self.side else None, labels if self.side else None


def cluster_entries(trees: DataFrame, taxa: list[str], block: int = BLOCK_TREES, side: bool = False, rooted: bool = True) -> DataFrame:
    """Rows (block, key, ids, lens, labels): per piece of input the distinct clusters and the trees that have them, ids as
    32-bit integers relative to the block. A row with an empty key lists the trees themselves. With side data, trivial
    clusters and the root come along, and lens and labels stand beside the ids."""
    sent = trees.sparkSession.sparkContext.broadcast(taxa)
    rows = max(1, min(4096, 100_000 // max(1, len(taxa))))  # the parser holds some hundred bytes for each leaf

    def run(batches):
        take = Extractor(sent.value, block, side, rooted)
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                piece = batch.slice(at, rows)
                got = take(np.asarray(piece.column(0)), piece.column(1).to_pylist())
                while some := list(islice(got, 4096)):
                    b, keys, ids, lens, labels = zip(*some, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(b, pa.int32()), pa.array(keys, pa.binary()), pa.array([i.astype(np.int32).tobytes() for i in ids], pa.binary()), pa.array(lens, pa.list_(pa.string())), pa.array(labels, pa.list_(pa.string()))], ["block", "key", "ids", "lens", "labels"])

    return trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(run, _ENTRY)


# --- codes --------------------------------------------------------------------------------------------------------


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[list[dict]]:
    """Rows that stand together with the same block and key."""
    held: list[dict] = []
    for batch in batches:
        for at in range(0, batch.num_rows, 2048):
            for row in batch.slice(at, 2048).to_pylist():
                if held and (held[0]["block"] != row["block"] or held[0]["key"] != row["key"]):
                    yield held
                    held = []
                held.append(row)
    if held:
        yield held


def encode_one(bits: bytes, n: int, ids: np.ndarray, span: int, bits_code: str, ids_code: str, side: str) -> tuple[bytes, bytes, str, np.ndarray]:
    """Code of the bits, code of the list, sign and the ids that are listed."""
    sign, listed = "+", ids
    if side == "both" and 2 * len(ids) > span:
        absent = np.ones(span, bool)
        absent[ids] = False
        sign, listed = "-", np.flatnonzero(absent)
    one = codes.packed_bits_encode(bits) if bits_code == "packed" else bits if bits_code == "raw" else codes.textrun_bits_encode(codes.bit_text(bits, n)).encode()
    if ids_code == "packed":
        two = codes.packed_ids_encode(listed, span > 65_536)
    else:
        two = codes.fixed_ids_encode(listed) if ids_code == "fixed" else codes.textrun_ids_encode(listed).encode()
    return one, two, sign, listed


def _encode(groups: Iterator[list[dict]], n: int, span_of: Callable[[int], int], bits_code: str, ids_code: str, side: str) -> Iterator[tuple]:
    """Encoded rows of groups of entries, one for each block and cluster."""
    for rows in groups:
        block, key = rows[0]["block"], rows[0]["key"]
        ids = np.concatenate([np.frombuffer(r["ids"], np.int32) for r in rows])
        order = np.argsort(ids, kind="stable")
        ids = ids[order].astype(np.int64)
        lens = labels = None
        if rows[0]["lens"] is not None:
            lens, labels = ([x for r in rows for x in r[c]] for c in ("lens", "labels"))
            lens, labels = [lens[i] for i in order], [labels[i] for i in order]
        if not key:
            yield block, key, 0, codes.runs_encode(ids), ids.astype(np.int32).tobytes(), None, None, 0, 0, len(ids), "+"
            continue
        packed = bits_code == "packed"
        one, two, sign, listed = encode_one(b"" if packed else codes.bits_of_key(key, n), n, ids, span_of(block), bits_code, ids_code, side)
        one = codes.packed_bits_of_key(key, n) if packed else one
        if bits_code == "textrun":
            entry = one + f" {sign}:{len(listed)}:".encode() + two + b"\n"
        else:
            entry = one + codes.varint(2 * len(listed) + (sign == "-")) + two
        keep = ids.astype(np.int32).tobytes() if lens is not None else None
        yield block, key, codes.card_of_key(key), entry, keep, lens, labels, len(one), len(two), len(listed), sign


def encode_entries(entries: DataFrame, n: int, spans: dict[int, int], bits_code: str = "packed", ids_code: str = "packed", side: str = "both") -> DataFrame:
    """Encoded rows, one for each block and cluster. bits_code: packed, textrun, raw; ids_code: packed, textrun, fixed;
    side: both, or in for in-sets only. Rows with an empty key list the trees of a block. spans: trees of each block, of which
    there is one for 65,536 trees."""
    spark = entries.sparkSession
    sent = spark.sparkContext.broadcast(spans)

    def run(batches):
        made = _encode(_groups(batches), n, lambda b: sent.value[b], bits_code, ids_code, side)
        while out := list(islice(made, 2048)):
            yield _encoded(out)

    p = int(spark.conf.get("spark.sql.shuffle.partitions"))
    return entries.repartition(p, "block", "key").sortWithinPartitions("block", "key").mapInArrow(run, _ENCODED)


def _encoded(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.binary(), pa.int32(), pa.binary(), pa.binary(), pa.list_(pa.string()), pa.list_(pa.string()), pa.int32(), pa.int32(), pa.int32(), pa.string()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], [x.split()[0] for x in _ENCODED.replace("array<string>", "x").split(", ")])


def _pack_lengths(values: list[str | None]) -> bytes:
    """0: none; 1: doubles, where each text is the shortest of its double; 2: texts, a line each, empty for none."""
    if all(v is None for v in values):
        return b"\x00"
    try:
        if all(v is not None and repr(float(v)) == v for v in values):
            return b"\x01" + zlib.compress(np.array([float(v) for v in values], ">f8").tobytes(), 6)
    except ValueError:
        pass
    return b"\x02" + zlib.compress("\n".join(v or "" for v in values).encode(), 6)


def _unpack_lengths(data: bytes, n: int) -> list[str | None]:
    if data[:1] == b"\x00":
        return [None] * n
    if data[:1] == b"\x01":
        return [repr(v) for v in np.frombuffer(zlib.decompress(data[1:]), ">f8").tolist()]
    return [v or None for v in zlib.decompress(data[1:]).decode().split("\n")]


def _round_six(value: str | None) -> str | None:
    return None if value is None else f"{float(value):.6f}"


def compress(trees: DataFrame, codec: str = "packed", block: int = BLOCK_TREES, lengths: str = "none", labels: bool = False, taxa: list[str] | None = None, order: str = "first_tree", rooted: bool = True, level: int = 6) -> DataFrame:
    """Container rows, one for each block, of trees (tree_id, newick) on one set of taxa.

    codec: packed, packed_raw (without Deflate) or textrun (the text baseline, which drops inner labels and rounds lengths
    to six decimals). lengths: none or exact, which keeps every digit as it was written; labels: keep inner labels.
    Tree ids are not negative and distinct; a taxon that the first tree lacks raises an error.
    """
    spark = trees.sparkSession
    taxa = taxa_of(trees, order) if taxa is None else taxa
    n, side = len(taxa), lengths != "none" or labels
    if lengths != "none":  # a block's lengths are texts in one task
        block = min(block, max(256, BLOCK_LENGTHS // max(1, 2 * n)))
    flags = (lengths != "none") + 2 * (labels and codec != "textrun") + 4 * rooted
    how = {"n": n, "bits_code": "textrun" if codec == "textrun" else "packed", "ids_code": "textrun" if codec == "textrun" else "packed", "side": "both"}
    if block == 1:  # nothing is shared, so each is made where its tree is read
        sent = spark.sparkContext.broadcast(taxa)

        def alone(batches):
            take = Extractor(sent.value, 1, side, rooted)
            for batch in batches:
                for tree, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    got = sorted(take(np.array([tree]), [text]), key=lambda r: r[1])
                    rows = ({"block": b, "key": key, "ids": ids.astype(np.int32).tobytes(), "lens": lens, "labels": names} for b, key, ids, lens, names in got)
                    now = _BlockWriter(tree, 1, 1, sent.value, codec, flags, level)
                    for x in _encode(([r] for r in rows), span_of=lambda b: 1, **how):
                        now.add(*x[1:7], x[9])
                    yield now.finish()

        return trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(alone, CONTAINER)

    spans = {r["b"]: r["s"] + 1 for r in trees.groupBy(F.floor(F.col("tree_id") / block).cast("int").alias("b")).agg(F.max((F.col("tree_id") % block).cast("int")).alias("s")).collect()}
    coded = encode_entries(cluster_entries(trees, taxa, block, side, rooted), spans=spans, **how)
    sent = spark.sparkContext.broadcast((spans, taxa))

    def run(batches):
        now = None
        for batch in batches:
            for row in (r for at in range(0, batch.num_rows, 2048) for r in batch.slice(at, 2048).to_pylist()):
                if now is None or row["block"] != now.block_id:
                    if now is not None:
                        yield now.finish()
                    now = _BlockWriter(row["block"], block, sent.value[0][row["block"]], sent.value[1], codec, flags, level)
                now.add(*(row[c] for c in ("key", "card", "entry", "ids", "lens", "labels", "n_ids")))
        if now is not None:
            yield now.finish()

    p = max(1, min(len(spans), int(spark.conf.get("spark.sql.shuffle.partitions"))))
    slim = coded if side else coded.select("block", "key", "card", "entry", F.lit(None).cast("binary").alias("ids"), F.lit(None).cast("array<string>").alias("lens"), F.lit(None).cast("array<string>").alias("labels"), "n_ids")
    return slim.repartition(p, "block").sortWithinPartitions("block", "key").mapInArrow(run, CONTAINER)


class _BlockWriter:
    """One container row, from encoded rows in the order of their keys. What is deflated is so as it comes."""

    def __init__(self, block_id: int, block: int, span: int, taxa: list[str], codec: str, flags: int, level: int):
        self.block_id, self.first, self.span, self.taxa, self.codec, self.flags = block_id, block_id * block, span, taxa, codec, flags
        self.lengths, self.labels = bool(flags & 1), bool(flags & 2)
        self.pack = zlib.compressobj(level, zlib.DEFLATED, -15) if codec == "packed" else None
        self.there, self.n_trees, self.parts, self.raw, self.n_bip, self.side = b"", 0, [], 0, 0, []

    def add(self, key: bytes, card: int, entry: bytes, ids: bytes | None, lens: list | None, labels: list | None, n_ids: int) -> None:
        n = len(self.taxa)
        if not key:
            self.there, self.n_trees = entry, n_ids
            return
        if lens is not None or labels is not None:
            self.side.append((1 if card == 1 else 2 if card == n else 0, key if card > 1 else bytes(255 - b for b in key), lens, labels))
        if 1 < card < n:
            self.parts.append(entry if self.pack is None else self.pack.compress(entry))
            self.raw += len(entry)
            self.n_bip += 1

    def finish(self) -> pa.RecordBatch:
        if self.codec == "textrun":
            head = f"TAXA {':'.join(self.taxa)}\nNTREES {self.n_trees}\nNBIPARTITIONS {self.n_bip}\n".encode()
            self.parts.insert(0, head)
            self.raw += len(head)
        if self.pack is not None:
            self.parts.append(self.pack.flush())
        payload, lens, names = b"".join(self.parts), None, None
        # inner clusters in the order of the payload, then leaves, then the root
        self.side.sort(key=lambda r: r[:2])
        if self.lengths:
            lens = _pack_lengths([_round_six(x) if self.codec == "textrun" else x for r in self.side for x in r[2]])
        if self.labels:
            told = [None if not any(r[3]) else r[3][0] if len(set(r[3])) == 1 else r[3] for r in self.side if r[0] != 1]
            names = zlib.compress(json.dumps(told).encode(), 6)
        row = (self.block_id, self.first, self.n_trees, self.span, len(self.taxa), self.taxa, self.codec, self.flags, self.n_bip, self.raw, payload, self.there, lens, names, zlib.crc32(payload))
        kinds = [pa.int32(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.string()), pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.binary(), pa.int64()]
        return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, kinds, strict=True)], [x.split()[0] for x in CONTAINER.replace("array<string>", "x").split(", ")])


# --- restoring ----------------------------------------------------------------------------------------------------


def open_payload(row: dict) -> bytes:
    if zlib.crc32(row["payload"]) != row["crc"]:
        raise ValueError(f"block {row['block_id']} is damaged")
    return zlib.decompress(row["payload"], -15) if row["codec"] == "packed" else row["payload"]


def decode_payload(data: bytes, n: int, span: int, codec: str) -> Iterator[tuple[bytes, str, np.ndarray]]:
    """(bits, sign, listed ids) of the entries of a payload."""
    if codec == "textrun":
        for line in data.decode().split("\n")[3:]:
            if line:
                code, rest = line.split(" ", 1)
                sign, _, ids = rest.split(":", 2)
                text = codes.textrun_bits_decode(code)
                width = (len(text) + 7) // 8
                yield int(text.ljust(8 * width, "0"), 2).to_bytes(width, "big"), sign, np.array(codes.textrun_ids_decode(ids), np.int64)
        return
    at = 0
    while at < len(data):
        bits, at = codes.packed_bits_decode(data, n, at)
        head, at = codes.read_varint(data, at)
        ids, at = codes.packed_ids_decode(data, head >> 1, at, span > 65_536)
        yield bits, "+-"[head & 1], ids


def in_set(sign: str, ids: np.ndarray, there: np.ndarray, span: int) -> np.ndarray:
    if sign == "+":
        return ids
    keep = np.zeros(span, bool)
    keep[there] = True
    keep[ids] = False
    return np.flatnonzero(keep)


def _trees_of(row: dict) -> np.ndarray:
    return codes.runs_decode(row["trees"] or b"")


#: A range of trees with its clusters: their bits or, where those are longer, their keys and the sizes of these; memberships by tree and ascending size, entries counted from 0 within the piece; lens
#: and names hold, tree after tree, those of its clusters, then of the leaves (lens only) and of the root.
_PIECE = "block_id int, lo int, first_tree long, n int, taxa array<string>, there binary, bits binary, sizes binary, tree binary, entry binary, lens array<string>, names array<string>"


class Block:
    """A decoded block: keys of its clusters and, for every tree, which of them it has."""

    def __init__(self, row: dict):
        n, span = row["n_taxa"], row["span"]
        self.n, self.first, self.id, self.taxa, self.there = n, row["first_tree"], row["block_id"], row["taxa"], _trees_of(row)
        keys, sets = [], []
        found = decode_payload(open_payload(row), n, span, row["codec"])
        while some := list(islice(found, max(1, UNPACKED // (n + 7)))):
            keys += codes.keys_of_bits([b for b, _, _ in some])
            sets += [in_set(sign, ids, self.there, span) for _, sign, ids in some]
        self.keys, card = keys, np.array([codes.card_of_key(x) for x in keys], np.int64)
        count = np.array([len(x) for x in sets], np.int64)
        entry = np.repeat(np.arange(len(sets)), count)
        tree = np.concatenate(sets) if sets else np.zeros(0, np.int64)
        order = np.lexsort((card[entry], tree))
        self.tree, self.entry = tree[order], entry[order]
        self.lens = self.names = None
        if row["lengths"] is not None or row["labels"] is not None:
            self.spot = order  # place of a membership among all, in the order of the payload
            self.starts = np.concatenate(([0], np.cumsum(count)))
        if row["lengths"] is not None:
            total = int(self.starts[-1]) + len(self.there) * (n + (n > 1))
            self.lens = np.array(_unpack_lengths(row["lengths"], total), object)
        if row["labels"] is not None:
            self.names = json.loads(zlib.decompress(row["labels"]))

    def _side(self, a: int, b: int, x: int, y: int) -> tuple[list | None, list | None]:
        """Lengths and labels of the memberships a to b and of the trees at x to y."""
        lens = names = None
        tree, entry = self.tree[a:b], self.entry[a:b]
        k, m = len(self.keys), len(self.there)
        edges = np.searchsorted(tree, self.there[x : y + 1] if y < m else np.append(self.there[x:], 1 << 40)).tolist()
        if self.lens is not None:
            inner, base, lens = self.lens[self.spot[a:b]], int(self.starts[-1]), []
            rest = self.lens[base:].reshape(-1, m)[:, x:y]
            for i in range(y - x):
                lens += [*inner[edges[i] : edges[i + 1]].tolist(), *rest[:, i].tolist()]
        if self.names is not None:
            at, names = self.spot[a:b] - self.starts[entry], []
            told = [t[j] if isinstance(t := self.names[e], list) else t for e, j in zip(entry.tolist(), at.tolist(), strict=True)]
            root = self.names[k] if self.n > 1 else None
            for i in range(y - x):
                names += [*told[edges[i] : edges[i + 1]], root[x + i] if isinstance(root, list) else root]
        return lens, names

    def pieces(self, split: int, first: int | None, last: int | None) -> Iterator[dict]:
        """Rows of the trees from first to last, `split` of the block's numbers each."""
        lo = 0 if first is None else max(0, first - self.first)
        hi = 1 << 40 if last is None else last - self.first + 1
        x, stop = (int(i) for i in np.searchsorted(self.there, [lo, hi]))
        while x < stop:
            at = int(self.there[x]) // split * split
            y = min(stop, int(np.searchsorted(self.there, at + split)))
            a, b = (int(i) for i in np.searchsorted(self.tree, [self.there[x], self.there[y - 1] + 1]))
            used, entry = np.unique(self.entry[a:b], return_inverse=True)
            lens, names = self._side(a, b, x, y)
            there, keys, width = self.there[x:y], [self.keys[e] for e in used.tolist()], (self.n + 7) // 8
            sizes = [len(k) for k in keys]
            dense = sum(sizes) >= width * len(keys)
            bits = b"".join(codes.bits_of_key(k, self.n) for k in keys) if dense else b"".join(keys)
            yield {"block_id": self.id, "lo": at, "first_tree": self.first, "n": self.n, "taxa": self.taxa, "there": there.astype(np.int32).tobytes(), "bits": bits, "sizes": None if dense else np.array(sizes, np.int32).tobytes(), "tree": np.searchsorted(there, self.tree[a:b]).astype(np.int32).tobytes(), "entry": entry.astype(np.int32).tobytes(), "lens": lens, "names": names}
            x = y


def rebuild_piece(piece: dict, method: str = "leaf_path") -> Iterator[tuple[int, str]]:
    """(tree_id, newick) of the trees of a piece."""
    n, taxa = piece["n"], list(piece["taxa"])
    there, tree, entry = (np.frombuffer(piece[c], np.int32) for c in ("there", "tree", "entry"))
    if piece["sizes"] is None:
        bits = np.frombuffer(piece["bits"], np.uint8).reshape(-1, max(1, (n + 7) // 8))
    else:
        keys = codes.cut(np.frombuffer(piece["bits"], np.uint8), np.concatenate(([0], np.cumsum(np.frombuffer(piece["sizes"], np.int32)))))
    lens, names = piece["lens"], piece["names"]
    edges = np.searchsorted(tree, np.arange(len(there) + 1)).tolist()
    at_len = at_name = 0
    for i, local in enumerate(there.tolist()):
        mine = entry[edges[i] : edges[i + 1]]
        k = len(mine)
        own = told = None
        if lens is not None:
            own = lens[at_len : at_len + k + n + (n > 1)]
            at_len += k + n + (n > 1)
        if names is not None:
            told = names[at_name : at_name + k + 1]
            at_name += k + 1
        if n == 1:
            yield piece["first_tree"] + local, nw.write(0, [[]], taxa, [own[0] if own else None])
            continue
        own_keys = None if piece["sizes"] is None else [keys[e] for e in mine.tolist()]
        if method == "leaf_path":
            held = tk.memberships(bits[mine], n) if own_keys is None else tk.by_leaf(*codes.members_of(own_keys), n, k)
            kids = tk.children_lists(*tk.walk_paths(*held, n, k + 1))
        else:
            raw = bits[mine] if own_keys is None else np.frombuffer(b"".join(codes.bits_of_key(x, n) for x in own_keys), np.uint8).reshape(k, -1)
            rows = np.unpackbits(raw, axis=1)[:, :n].astype(bool)
            kids = tk.children_lists(*tk.METHODS[method](np.vstack([rows, np.ones((1, n), bool)])))
        label = [*taxa, *(told if told is not None else [None] * (k + 1))]
        length = [*own[k : k + n], *own[:k], own[k + n]] if own is not None else [None] * len(label)
        yield piece["first_tree"] + local, nw.write(len(kids) - 1, kids, label, length)


def _piece_batch(rows: list[dict]) -> pa.RecordBatch:
    kinds = {"block_id": pa.int32(), "lo": pa.int32(), "first_tree": pa.int64(), "n": pa.int32(), "taxa": pa.list_(pa.string()), "lens": pa.list_(pa.string()), "names": pa.list_(pa.string())}
    names = [x.split()[0] for x in _PIECE.replace("array<string>", "x").split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r[c] for r in rows], kinds.get(c, pa.binary())) for c in names], names)


def _tree_batches(pieces: Iterator[dict], pick: frozenset | None, method: str) -> Iterator[pa.RecordBatch]:
    for piece in pieces:
        got = [x for x in rebuild_piece(piece, method) if pick is None or x[0] in pick]
        yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in got], pa.int64()), pa.array([t for _, t in got], pa.string())], ["tree_id", "newick"])


def decompress(container: DataFrame, tree_ids: list[int] | None = None, first: int | None = None, last: int | None = None, method: str = "leaf_path", split: int = 256, spread: bool = True) -> DataFrame:
    """(tree_id, newick) of all trees, of those in tree_ids, or of the ids from first to last. Blocks without wanted trees
    are not read; each is decoded once. With spread, pieces of `split` trees are shuffled, so that a few blocks keep all
    tasks busy; without, trees are rebuilt where their block is read and nothing is shuffled, which suits containers of many
    blocks (`restore_plan` tells). A damaged block raises an error."""
    rows = container
    if tree_ids is not None:
        wanted = sorted(set(tree_ids))
        first, last = (wanted[0], wanted[-1]) if wanted else (0, -1)
    if first is not None:
        rows = rows.where(F.col("first_tree") + F.col("span") > first)
    if last is not None:
        rows = rows.where(F.col("first_tree") <= last)
    pick = None if tree_ids is None else frozenset(wanted)
    spark = rows.sparkSession
    def read(batches) -> Iterator[dict]:
        for batch in batches:
            for i in range(batch.num_rows):
                yield from Block(batch.slice(i, 1).to_pylist()[0]).pieces(split, first, last)

    if not spread:
        return rows.mapInArrow(lambda batches: _tree_batches(read(batches), pick, method), "tree_id long, newick string")
    pieces = rows.mapInArrow(lambda batches: (_piece_batch([p]) for p in read(batches)), _PIECE)

    def rebuild(batches):
        yield from _tree_batches((batch.slice(i, 1).to_pylist()[0] for batch in batches for i in range(batch.num_rows)), pick, method)

    slots = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)
    return pieces.repartition(slots, "block_id", "lo").mapInArrow(rebuild, "tree_id long, newick string")


def restore_plan(container: DataFrame) -> dict:
    """spread and split for a written container: blocks that are as many as the tasks that can run are restored in place;
    else some four pieces come on each task, of 64 to 4,096 trees."""
    n, trees = container.agg(F.count("*"), F.coalesce(F.sum("span"), F.lit(0))).first()
    slots = container.sparkSession.sparkContext.defaultParallelism
    return {"spread": n < slots, "split": max(64, min(4096, trees // (4 * slots)))}


def container_entries(container: DataFrame) -> DataFrame:
    """(block_id, first_tree, n_trees, bits, card, sign, n_listed, n_support, support) of all clusters of a container,
    without rebuilding a tree."""

    def run(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1).to_pylist()[0]
                there, found = _trees_of(row), decode_payload(open_payload(row), row["n_taxa"], row["span"], row["codec"])
                while some := list(islice(found, max(64, min(4096, 8 * UNPACKED // max(1, row["n_taxa"]))))):
                    out = []
                    for bits, sign, ids in some:
                        support = in_set(sign, ids, there, row["span"])
                        out.append((row["block_id"], row["first_tree"], row["n_trees"], bits, int.from_bytes(bits, "big").bit_count(), sign, len(ids), len(support), support.astype(np.int32)))
                    kinds = [pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.int32(), pa.string(), pa.int32(), pa.int32(), pa.list_(pa.int32())]
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], ["block_id", "first_tree", "n_trees", "bits", "card", "sign", "n_listed", "n_support", "support"])

    return container.mapInArrow(run, "block_id int, first_tree long, n_trees int, bits binary, card int, sign string, n_listed int, n_support int, support array<int>")


def merge(*containers: DataFrame) -> DataFrame:
    """Containers of disjoint blocks in one; blocks are not encoded anew."""
    out = containers[0]
    for c in containers[1:]:
        out = out.unionByName(c)
    return out


def verify_roundtrip(trees: DataFrame, container: DataFrame, labels: bool = False, lengths: bool = False) -> DataFrame:
    """(tree_id, ok): whether the canonical texts of input and restored tree agree; ok is false for a tree that only one
    side has. Digests are joined, not texts."""
    from .newick import canonical_newick

    one = canonical_newick(trees, labels, lengths).select("tree_id", F.md5("canonical").alias("x"))
    two = canonical_newick(decompress(container), labels, lengths).select("tree_id", F.md5("canonical").alias("y"))
    return one.join(two, "tree_id", "full_outer").select("tree_id", F.coalesce(F.col("x") == F.col("y"), F.lit(False)).alias("ok"))


# --- other baselines ----------------------------------------------------------------------------------------------


def general_codec(trees: DataFrame, codec: str, block: int = BLOCK_TREES) -> DataFrame:
    """(block, raw_bytes, payload): a byte compressor on the Newick lines of a block, in order. codec: text_deflate,
    text_bz2, text_lzma. The compressor is fed a line at a time; one block's output is held."""
    ordered = trees.select(F.floor(F.col("tree_id") / block).cast("int").alias("block"), "tree_id", "newick")

    def make():
        if codec == "text_deflate":
            return zlib.compressobj(6, zlib.DEFLATED, -15)
        return bz2.BZ2Compressor(9) if codec == "text_bz2" else lzma.LZMACompressor(preset=6)

    def run(batches):
        now, pack, out, raw = None, None, [], 0

        def close():
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([raw], pa.int64()), pa.array([b"".join([*out, pack.flush()])], pa.binary())], ["block", "raw_bytes", "payload"])

        for batch in batches:
            for b, text in zip(batch.column(0).to_pylist(), batch.column(2).to_pylist(), strict=True):
                if b != now:
                    if now is not None:
                        yield close()
                    now, pack, out, raw = b, make(), [], 0
                line = (text + "\n").encode()
                raw += len(line)
                out.append(pack.compress(line))
        if now is not None:
            yield close()

    p = int(trees.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return ordered.repartition(p, "block").sortWithinPartitions("block", "tree_id").mapInArrow(run, "block int, raw_bytes long, payload binary")


def subtree_dictionary(trees: DataFrame) -> DataFrame:
    """(subtree, n_copies, first_tree, ref): the canonical texts of inner nodes, each stored at its first copy; later ones
    are references. ref numbers those with more than one copy, in the order of their text's hash."""

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                ids, subs = [], []
                for tree_id, text in zip(batch.column(0).to_pylist()[at : at + 64], batch.column(1).to_pylist()[at : at + 64], strict=True):
                    t = nw.parse(text)
                    kids, least, word = nw.children_of(t), list(t.label), [nw.quote(x) for x in t.label]
                    for node in range(len(t.label)):
                        if kids[node]:
                            kids[node].sort(key=lambda c: least[c])
                            least[node] = least[kids[node][0]]
                            word[node] = "(" + ",".join(word[c] for c in kids[node]) + ")"
                            ids.append(tree_id)
                            subs.append(word[node])
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(subs, pa.string())], ["tree_id", "subtree"])

    found = trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(run, "tree_id long, subtree string")
    return found.groupBy("subtree").agg(F.count("*").alias("n_copies"), F.min("tree_id").alias("first_tree")).withColumn("ref", F.when(F.col("n_copies") > 1, F.xxhash64("subtree")))


def subtree_dictionary_size(trees: DataFrame, ref_bytes: int = 4) -> DataFrame:
    """(n_subtrees, n_distinct, comp_bytes) of the older baseline: an inner node's own text where it stands first - its
    brackets, commas and leaf labels - and a reference for every later copy whose parent is not itself a copy."""
    taxa = taxa_of(trees)

    def key(text: str | None) -> bytes | None:
        return None if text is None else hashlib.blake2b(text.encode(), digest_size=16).digest()

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                rows = []
                for tree_id, text in zip(batch.column(0).to_pylist()[at : at + 64], batch.column(1).to_pylist()[at : at + 64], strict=True):
                    t = nw.parse(text)
                    kids, least, word = nw.children_of(t), list(t.label), [nw.quote(x) for x in t.label]
                    own = [len(w) for w in word]
                    for node in range(len(t.label)):
                        if kids[node]:
                            kids[node].sort(key=lambda c: least[c])
                            least[node] = least[kids[node][0]]
                            word[node] = "(" + ",".join(word[c] for c in kids[node]) + ")"
                            own[node] = 1 + len(kids[node]) + sum(own[c] for c in kids[node] if not kids[c])
                    names = [key(w) if kids[x] else None for x, w in enumerate(word)]
                    rows += [(tree_id, names[x], names[t.parent[x]] if t.parent[x] >= 0 else None, own[x]) for x in range(len(t.label)) if kids[x]]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.binary(), pa.binary(), pa.int64()), strict=True)], ["tree_id", "s", "a", "own"])

    # texts of large trees are long: only their digests are shuffled
    nodes = trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(run, "tree_id long, s binary, a binary, own long")
    keyed = nodes.withColumn("top", F.col("a").isNull())
    firsts = nodes.groupBy("s").agg(F.min("tree_id").alias("f"))
    above = firsts.select(F.col("s").alias("a"), F.col("f").alias("fa"))
    joined = keyed.join(firsts, "s").join(above, "a", "left")
    is_first, above_first = F.col("tree_id") == F.col("f"), F.col("top") | (F.col("tree_id") == F.col("fa"))
    size = F.sum(F.when(is_first, F.col("own")).when(above_first, ref_bytes).otherwise(0))
    return joined.agg(F.count("*").alias("n_subtrees"), F.countDistinct("s").alias("n_distinct"), (size + sum(len(x) + 1 for x in taxa)).alias("comp_bytes"))
