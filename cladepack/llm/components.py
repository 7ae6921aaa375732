"""Distributed union-find over links, and the exact resolution of candidate tiles."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, map_arrow

_SPREAD = np.uint64(0xA0761D6478BD642F)


#: Links that one task unites.
TASK_LINKS = 500_000


def _unite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Union-find over the links of one partition: (node, least node of its tree) for every node but the roots."""
    found = [(np.asarray(b.column(0)), np.asarray(b.column(1))) for b in batches if b.num_rows]
    if not found:
        return
    a, b = (np.concatenate(x) for x in zip(*found, strict=True))
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    root = list(range(len(nodes)))
    for x, y in zip(at[: len(a)].tolist(), at[len(a) :].tolist(), strict=True):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        while root[y] != y:
            root[y] = root[root[y]]
            y = root[y]
        if x != y:  # nodes are in order, so the smaller index is the smaller node
            root[max(x, y)] = min(x, y)
    for x in range(len(root)):
        root[x] = root[root[x]]
    top = nodes[np.array(root)]
    keep = top != nodes
    yield pa.RecordBatch.from_arrays([pa.array(nodes[keep]), pa.array(top[keep])], ["u", "v"])


def connected_components(scratch: Scratch, links: DataFrame, most_rounds: int = 60, task_links: int = TASK_LINKS) -> DataFrame:
    """(node, component) for every node of links(a, b); component is the smallest node reachable.

    A distributed union-find. Every task unites some task_links of the links, dealt by both ends so that the links of a hub
    are spread, and hands on its trees, one edge a node. If
    there was more than one task, the trees are joined by alternating star rewiring: each round hangs the neighbours of a
    node on the least of them, once upwards and once downwards, until the edges stand still. A round is two aggregates with
    a join each, both keyed by node and combined before the shuffle; its edges are written to the shared folder. Null or
    equal ends are ignored; links may repeat.
    """
    edges = scratch.save(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v"))
    tasks = -(-edges.count() // task_links)
    whole = edges
    while tasks > 1:  # fewer edges after a pass may need fewer tasks
        before, edges = edges, scratch.save(edges.repartition(tasks, "u", "v").mapInArrow(_unite, "u long, v long"))
        now = -(-edges.count() // task_links)
        if before is not whole:
            scratch.drop(before)
        if now >= tasks or now == 1:
            tasks = now
            break
        tasks = now
    if tasks <= 1:
        edges = scratch.save(edges.coalesce(1).mapInArrow(_unite, "u long, v long"))
    else:
        edges = _stars(scratch, edges, most_rounds)
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots)


def _stars(scratch: Scratch, edges: DataFrame, most_rounds: int) -> DataFrame:
    """Edges (u, v), u > v, rewired until every node hangs on the least of its component."""
    seen = None
    for _ in range(most_rounds):
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        up = both.where("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        up = up.union(least.select("u", F.col("m").alias("v")).where("u <> v")).distinct()
        low = up.groupBy("u").agg(F.min("v").alias("m"))
        down = up.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        after = scratch.save(down.union(low.select("u", F.col("m").alias("v"))).distinct())
        mark = after.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        edges = after
        if mark == seen or not mark[0]:
            return edges
        seen = mark
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")


# --- tiles --------------------------------------------------------------------------------------------------------

#: Members of one block; a tile of more is worked through in pairs of blocks.
BLOCK = 4096
#: Sum of the set sizes of one block.
BLOCK_WEIGHT = 4_000_000
#: Members of a tile whose pairs are simply listed.
SMALL = 32


def linked(a: np.ndarray, b: np.ndarray, num: int, den: int) -> bool:
    """Exact intersection of two sorted arrays of distinct hashes; empty sets are linked with nothing."""
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    if not len(small) or den * len(small) < num * len(large):  # no more in common than the smaller has
        return False
    at = np.searchsorted(large, small)
    both = int((large[np.minimum(at, len(large) - 1)] == small).sum())
    return den * both >= num * (len(a) + len(b) - both)


def bitmap(hashes: np.ndarray, per: int = 2) -> bytes:
    """Hashed bitmap of a set of 64-bit hashes; its width is a power of two, per to twice per times the set's size. With
    two, unrelated sets differ in a third of their bits and more, which is far from what a link allows."""
    bits = 64
    while bits < per * len(hashes) and bits < 1 << 17:
        bits *= 2
    out = np.zeros(bits, np.uint8)
    out[(hashes * _SPREAD >> np.uint64(64 - bits.bit_length() + 1)).astype(np.int64)] = 1
    return np.packbits(out, bitorder="little").tobytes()


def fold(bits: np.ndarray, words: int) -> np.ndarray:
    """A bitmap in fewer words: neighbouring bits are joined, as a narrower bitmap of the set has them."""
    while len(bits) > words:
        raw = np.unpackbits(bits.view(np.uint8), bitorder="little")
        bits = np.packbits(raw[0::2] | raw[1::2], bitorder="little").view(np.uint64)
    return bits


def overlap_bound(n_a: np.ndarray, a: np.ndarray, n_b: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Sets with these bitmaps (rows of equal width) have no more elements in common: a bit that is set in one only
    stands for an element that the other lacks."""
    only_a, only_b = np.bitwise_count(a & ~b).sum(-1, dtype=np.int64), np.bitwise_count(b & ~a).sum(-1, dtype=np.int64)
    return np.minimum(n_a - only_a, n_b - only_b)


def least_overlap(n_a: np.ndarray, n_b: np.ndarray, num: int, den: int) -> np.ndarray:
    """The overlap from which two sets of these sizes have a Jaccard similarity of num / den."""
    return -(-num * (n_a + n_b) // (den + num))


def _pair_bound(batch: pa.RecordBatch, num: int, den: int):
    keep = []
    for na, ba, nb, bb in zip(*(batch.column(i) for i in range(2, 6)), strict=True):
        na, nb = na.as_py(), nb.as_py()
        least = -(-num * (na + nb) // (den + num))
        a, b = np.frombuffer(ba.as_buffer(), np.uint64), np.frombuffer(bb.as_buffer(), np.uint64)
        w = min(len(a), len(b))
        keep.append(min(na, nb) >= least and int(overlap_bound(na, fold(a, w), nb, fold(b, w))) >= least)
    yield batch.select([0, 1]).filter(pa.array(keep, pa.bool_()))


def _tile_pairs(tile: int, m: np.ndarray, label: np.ndarray, n: np.ndarray, bits: list[np.ndarray], block: np.ndarray, shared: list[np.ndarray], num: int, den: int, exact: list[np.ndarray] | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of one tile, or of two blocks of it, that lie in different components, that sizes and bitmaps allow, and of
    whose common tiles this is the first. With the sets themselves (exact), only linked pairs, and of those only such as
    join components of the tile: no more than it has members."""
    sets: dict[int, set[int]] = {}
    root = list(range(len(m)))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    def join(i: int, j: int) -> bool:
        x, y = find(i), find(j)
        if x == y or not linked(exact[i], exact[j], num, den):
            return False
        root[y] = x
        return True

    def mine(i: int) -> set[int]:
        if i not in sets:
            sets[i] = set(shared[i].tolist())
        return sets[i]

    # pairs are compared at the width of the narrower bitmap
    width = np.array([len(x) for x in bits])
    two = bool(len(block)) and block.min() != block.max()
    one, other = [], []
    widths = np.unique(width).tolist()
    for w in widths:
        own = np.flatnonzero(width == w)
        mine_at = np.stack([bits[i] for i in own])
        for v in (x for x in widths if x >= w):
            wide = np.flatnonzero(width == v)
            if min(n[own].max(), n[wide].max()) < least_overlap(n[own].min(), n[wide].min(), num, den):
                continue
            rows = mine_at if v == w else np.stack([fold(bits[j], w) for j in wide])
            for k, i in enumerate(own.tolist()):
                at = np.arange(k + 1 if v == w else 0, len(wide))
                j = wide[at]
                ok = (label[j] != label[i]) & (np.minimum(n[i], n[j]) >= least_overlap(n[i], n[j], num, den))
                at = at[ok & (block[j] != block[i])] if two else at[ok]
                if len(at):
                    j = wide[at]
                    j = j[overlap_bound(n[i], mine_at[k], n[j], rows[at]) >= least_overlap(n[i], n[j], num, den)]
                    j = j[[min(mine(i) & mine(x)) == tile for x in j.tolist()]] if len(j) else j
                    j = j[[join(i, x) for x in j.tolist()]] if len(j) and exact is not None else j
                    one.append(np.full(len(j), m[i]))
                    other.append(m[j])
    if not one:
        return m[:0], m[:0]
    a, b = np.concatenate(one), np.concatenate(other)
    return np.minimum(a, b), np.maximum(a, b)


def _tiles_in_order(batches: Iterator[pa.RecordBatch], num: int, den: int, expand: Callable[[list[bytes]], list[np.ndarray]] | None = None) -> Iterator[pa.RecordBatch]:
    """Groups of rows (tile, i, j, m, l, n, bits, block, shared) that stand together, one after the other; holds one group.
    With expand, bits holds what the sets are made of."""
    rest = None
    last = object()
    for batch in chain(batches, [last]):
        if batch is last:
            if rest is None:
                return
            now, done = rest, rest.num_rows
        else:
            now = pa.Table.from_batches([batch]) if rest is None else pa.concat_tables([rest, pa.Table.from_batches([batch])])
            if not now.num_rows:
                continue
            done = None
        keys = np.stack([now.column(c).to_numpy() for c in ("tile", "i", "j")])
        edges = np.concatenate(([0], np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(0)) + 1, [now.num_rows]))
        stop = len(edges) - 1 if done is not None else len(edges) - 2
        m, label, n, block = (now.column(c).to_numpy() for c in ("m", "l", "n", "block"))
        maps, lists = now.column("bits"), now.column("shared")
        for k in range(stop):
            at = slice(edges[k], edges[k + 1])
            exact, size = None, n[at]
            if expand is not None:
                exact = expand(maps.slice(at.start, at.stop - at.start).to_pylist())
                bits, size = [np.frombuffer(bitmap(s, 8), np.uint64) for s in exact], np.array([len(s) for s in exact], np.int64)
            else:
                bits = [np.frombuffer(x.as_buffer(), np.uint64) for x in maps.slice(at.start, at.stop - at.start)]
            shared = [np.frombuffer(x.values.buffers()[1], np.int64)[x.values.offset : x.values.offset + len(x.values)] for x in lists.slice(at.start, at.stop - at.start)]
            a, b = _tile_pairs(int(keys[0, at.start]), m[at], label[at], size, bits, block[at], shared, num, den, exact)
            if len(a):
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], ["a", "b"])
        rest = now.slice(edges[stop]) if done is None else None


def distinct_tiles(scratch: Scratch, tiles: DataFrame) -> DataFrame:
    """One of the tiles that have the same members, without tiles of one member: close copies share most of theirs. tiles
    (tile, m) has no repeated rows. Members are told apart by their number and 128 bits of their hashes."""
    marks = tiles.groupBy("tile").agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("m")).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "m")).alias("y"))
    first = marks.where("n > 1").groupBy("n", "x", "y").agg(F.min("tile").alias("tile")).select("tile")
    return scratch.save(tiles.join(first, "tile", "left_semi"))


def resolve_tiles(scratch: Scratch, tiles: DataFrame, load: Callable[[DataFrame], None], sketch: Callable[[DataFrame], DataFrame], verify: Callable[[DataFrame], DataFrame], num: int, den: int, bound: bool = True, small: int | None = None, expand: Callable[[list[bytes]], list[np.ndarray]] | None = None, rounds: int = 2) -> tuple[DataFrame, DataFrame]:
    """Components of the graph whose links are the verified pairs that share a tile: (node, component), and the links.

    tiles: (tile, m), without repeated rows; load is called once with the members (m) that are left; sketch: members (m) ->
    (m, n, bits), the size and bitmap of each set; verify: pairs (a, b) -> those linked. With bound, pairs are verified only
    if sizes and bitmaps allow a link; without, bitmaps serve for large tiles alone (small sets are verified as fast). With
    expand, sketch gives as bits what a set is made of, from which expand makes it; large tiles are then verified in place.

    First every tile picks a leader - in the same order everywhere, so tiles of one group agree on it -, which is compared
    with the members that are not in its component and then leaves: all its pairs there are settled. So a group of linked
    copies falls into one component without all its pairs. A tile whose members share a component is settled. The tiles
    that are left - members truly apart - give their pairs if they are small; large ones are worked through on bitmaps, in
    the task that holds them, and only pairs that the bitmaps allow come out. A tile of more than BLOCK members or BLOCK_WEIGHT
    elements is dealt into blocks, and each pair of blocks is a task of its own. No pair of one tile stays unsettled.

    What is known of a tile (leader, size, least and largest label) comes from aggregates that are combined before the
    shuffle; its rows learn it by a plain join of two written tables, so that Spark can split the partition of a hot tile.
    """
    small = SMALL if small is None else small
    members = distinct_tiles(scratch, tiles).select("tile", "m", F.col("m").alias("l"))
    links = parts = None
    wanted = scratch.save(members.select("m").distinct())
    load(wanted)
    sketches = sketch(wanted) if bound else None

    def facts(r: int) -> DataFrame:
        lead = F.min(F.struct(F.xxhash64(F.lit(r), "m").alias("o"), F.col("m").alias("m"), F.col("l").alias("l"))).alias("lead")
        per = scratch.save(members.groupBy("tile").agg(F.count("*").alias("size"), F.min("l").alias("lo"), F.max("l").alias("hi"), lead).where("lo <> hi"))
        return members.join(per, "tile")

    def settle(near: DataFrame) -> None:
        nonlocal links, parts
        found = scratch.save(verify(scratch.save(near)))
        if links is not None and not found.limit(1).count():
            return
        links = found if links is None else scratch.save(links.union(found))
        parts = scratch.save(connected_components(scratch, links))

    def bounded(pairs: DataFrame) -> DataFrame:
        if not bound:
            return pairs
        one, two = (sketches.select(F.col("m").alias(x), F.col("n").alias("n" + x), F.col("bits").alias("bits" + x)) for x in "ab")
        wide = pairs.join(one, "a").join(two, "b").select("a", "b", "na", "bitsa", "nb", "bitsb")
        return map_arrow(wide, lambda b: _pair_bound(b, num, den), "a long, b long")

    for r in range(rounds):
        led = scratch.save(facts(r).select("tile", "m", "l", "lead"))
        settle(bounded(led.where("m <> lead.m and l <> lead.l").select(F.col("lead.m").alias("a"), F.col("m").alias("b")).distinct()))
        rest = led.where("m <> lead.m").select("tile", "m").join(parts.select(F.col("node").alias("m"), "component"), "m", "left")
        scratch.drop(members)
        members = scratch.save(rest.select("tile", "m", F.coalesce("component", "m").alias("l")))
        scratch.drop(led)
        if not members.limit(1).count():
            return parts, links

    # small tiles give their pairs, of which close copies share nearly all: no more than small / 2 for each row
    sized = scratch.save(facts(rounds).select("tile", "m", "l", "size"))
    few = sized.where(F.col("size") <= small)
    x, y = few.select("tile", F.col("m").alias("a"), F.col("l").alias("la")), few.select("tile", F.col("m").alias("b"), F.col("l").alias("lb"))
    listed = bounded(x.join(y, "tile").where("a < b and la <> lb").select("a", "b").distinct())

    # large ones are worked through in place. A tile of several blocks goes into a group for each pair of its blocks: of a
    # pair of one block only the group (i, i) takes it, groups of two blocks take pairs across. A pair may share many tiles:
    # with the tiles that its members are left in (as many as a set has segments at most), one of them takes it
    many = sized.where(F.col("size") > small)
    if not many.limit(1).count():
        settle(listed)
        return parts, links
    if sketches is None:
        sketches = scratch.save(sketch(scratch.save(many.select("m").distinct())), codec="none")
    heavy = many.join(sketches.select("m", "n"), "m").groupBy("tile").agg(F.sum("n").alias("weight"), F.count("*").alias("size"))
    heavy = heavy.select("tile", "size", F.ceil(F.greatest(F.col("size") / BLOCK, F.col("weight") / BLOCK_WEIGHT)).cast("int").alias("blocks"))
    block = many.select("tile", "m", "l").join(scratch.save(heavy), "tile").withColumn("block", F.pmod(F.xxhash64("m"), F.col("blocks")).cast("int"))
    own = many.groupBy("m").agg(F.collect_list("tile").alias("shared")).join(sketches, "m")
    dealt = block.withColumn("with", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("tile", F.least("block", "with").alias("i"), F.greatest("block", "with").alias("j"), "m", "l", "block").join(own, "m")
    dealt = dealt.select("tile", "i", "j", "m", "l", F.col("n").cast("long").alias("n"), "bits", "block", "shared")
    parts_n = max(8, scratch.spark.sparkContext.defaultParallelism, int(scratch.spark.conf.get("spark.sql.shuffle.partitions")))
    large = dealt.repartition(parts_n, "tile", "i", "j").sortWithinPartitions("tile", "i", "j").mapInArrow(lambda b: _tiles_in_order(b, num, den, expand), "a long, b long")
    settle(listed.union(large).distinct())
    return parts, links
