"""The stages of Deflate on bytes: matching, code lengths, canonical codes, blocks in the three modes, and inflating.

The stream that deflate_blocks writes is raw Deflate, which any inflater reads.
"""

from __future__ import annotations

import heapq
from collections import Counter

#: Token: (literal byte, 0, 0) or (-1, length, distance).
Token = tuple[int, int, int]
WINDOW, MAX_LENGTH, MIN_MATCH, STORED = 32768, 258, 3, 65535


def lz77_tokens(data: bytes, window: int = WINDOW, max_length: int = MAX_LENGTH, min_match: int = MIN_MATCH, chain: int = 64) -> list[Token]:
    """Greedy matching of the longest repeat within the window; `chain` bounds the earlier places that are tried."""
    out: list[Token] = []
    seen: dict[bytes, list[int]] = {}
    at, n = 0, len(data)
    while at < n:
        best, where = 0, 0
        key = data[at : at + min_match]
        limit, least = min(max_length, n - at), key
        for p in reversed(seen.get(key, ())[-chain:]) if len(key) == min_match else ():
            if at - p > window:
                break
            # only a longer match than the best one counts
            k = len(least)
            if data[p : p + k] != least:
                continue
            while k < limit and data[p + k] == data[at + k]:
                k += 1
            best, where = k, p
            if k == limit:
                break
            least = data[at : at + k + 1]
        step = best if best >= min_match else 1
        out.append((-1, best, at - where) if step > 1 else (data[at], 0, 0))
        for i in range(at, min(at + step, n - min_match + 1)):
            places = seen.setdefault(data[i : i + min_match], [])
            places.append(i)
            if len(places) > 4 * chain:
                del places[: 2 * chain]
        at += step
    return out


def lz77_expand(tokens: list[Token]) -> bytes:
    out = bytearray()
    for literal, length, distance in tokens:
        if literal >= 0:
            out.append(literal)
        else:
            piece = bytes(out[-distance:][:length])
            out += (piece * (length // distance + 1))[:length]
    return bytes(out)


def huffman_lengths(freqs: dict[int, int], limit: int = 15) -> dict[int, int]:
    """Optimal code lengths of at most `limit` bits: in each of `limit` rounds symbols and pairs of the round before are
    merged by weight; a symbol's length is the number of rounds in which the cheapest 2n - 2 items hold it."""
    live = sorted((f, s) for s, f in freqs.items() if f > 0)
    if len(live) <= 1:
        return {s: 1 for _, s in live}
    if len(live) > 1 << limit:
        raise ValueError("too many symbols")
    items: list[tuple[int, tuple[int, ...]]] = []
    leaves = [(f, (s,)) for f, s in live]
    for _ in range(limit):
        pairs = [(a[0] + b[0], a[1] + b[1]) for a, b in zip(items[::2], items[1::2])]
        items = list(heapq.merge(leaves, pairs, key=lambda x: x[0]))
    return dict(Counter(s for _, group in items[: 2 * len(live) - 2] for s in group))


def huffman_codes(lengths: dict[int, int]) -> dict[int, tuple[int, int]]:
    """Canonical prefix code (code, length): shorter codes first, equal lengths by symbol."""
    out, code, last = {}, 0, 0
    for length, symbol in sorted((n, s) for s, n in lengths.items() if n):
        code <<= length - last
        out[symbol] = (code, length)
        code, last = code + 1, length
    return out


class _Bits:
    def __init__(self):
        self.out, self.acc, self.n = bytearray(), 0, 0

    def put(self, value: int, width: int) -> None:
        self.acc |= value << self.n
        self.n += width
        while self.n >= 8:
            self.out.append(self.acc & 255)
            self.acc >>= 8
            self.n -= 8

    def code(self, code: tuple[int, int]) -> None:
        value, width = code
        self.put(int(format(value, f"0{width}b")[::-1], 2), width)

    def align(self) -> None:
        if self.n:
            self.put(0, 8 - self.n)


# length and distance symbols: classes of doubling width, from a rule
def _classes(first: int, per_width: int, count: int) -> list[tuple[int, int]]:
    out, base = [], first
    for k in range(count):
        extra = max(0, k // per_width - 1)
        out.append((base, extra))
        base += 1 << extra
    return out


_LENGTHS = [*_classes(3, 4, 28), (258, 0)]
_DISTANCES = _classes(1, 2, 30)
# fixed value of the format: order in which code-length lengths are sent
_ORDER = (16, 17, 18, 0, 8, 7, 9, 6, 10, 5, 11, 4, 12, 3, 13, 2, 14, 1, 15)
_FIXED = {s: 8 if s < 144 else 9 if s < 256 else 7 if s < 280 else 8 for s in range(288)}


def _symbol(x: int, classes: list[tuple[int, int]]) -> tuple[int, int, int]:
    lo, hi = 0, len(classes) - 1
    while lo < hi:
        mid = (lo + hi + 1) // 2
        lo, hi = (mid, hi) if classes[mid][0] <= x else (lo, mid - 1)
    return lo, x - classes[lo][0], classes[lo][1]


def _run_lengths(lengths: list[int]) -> list[tuple[int, int, int]]:
    """Code lengths as symbols (symbol, extra value, extra bits): repeats of the last one, and runs of zeros."""
    out, i = [], 0
    while i < len(lengths):
        j = i
        while j < len(lengths) and lengths[j] == lengths[i]:
            j += 1
        run, value = j - i, lengths[i]
        if value:
            out.append((value, 0, 0))
            run -= 1
        while run >= 3:
            if value:
                take = min(6, run)
                out.append((16, take - 3, 2))
            else:
                take = min(138, run)
                out.append((17, take - 3, 3) if take < 11 else (18, take - 11, 7))
            run -= take
        out += [(value, 0, 0)] * run
        i = j
    return out


def _token_bits(tokens: list[Token], lit: dict[int, int], dist: dict[int, int]) -> int:
    total = lit.get(256, 0)
    for literal, length, distance in tokens:
        if literal >= 0:
            total += lit[literal]
        else:
            s, _, e = _symbol(length, _LENGTHS)
            d, _, f = _symbol(distance, _DISTANCES)
            total += lit[257 + s] + e + dist[d] + f
    return total


def _dynamic(tokens: list[Token]):
    lits, dists = Counter({256: 1}), Counter()
    for literal, length, distance in tokens:
        if literal >= 0:
            lits[literal] += 1
        else:
            lits[257 + _symbol(length, _LENGTHS)[0]] += 1
            dists[_symbol(distance, _DISTANCES)[0]] += 1
    lit = huffman_lengths(lits)
    dist = huffman_lengths(dists) or {0: 1}
    n_lit, n_dist = max(257, max(lit) + 1), max(dist) + 1
    sent = _run_lengths([lit.get(s, 0) for s in range(n_lit)] + [dist.get(s, 0) for s in range(n_dist)])
    meta = huffman_lengths(Counter(s for s, _, _ in sent), 7)
    n_meta = max(4, max(i for i, s in enumerate(_ORDER) if meta.get(s)) + 1)
    bits = 14 + 3 * n_meta + sum(meta[s] + e for s, _, e in sent) + _token_bits(tokens, lit, dist)
    return bits, lit, dist, sent, meta, n_lit, n_dist, n_meta


def deflate_blocks(tokens: list[Token], mode: str = "auto", block_tokens: int = 16384) -> tuple[bytes, list[tuple[str, int, int]]]:
    """Raw Deflate stream of the tokens, and (mode, bits, bytes covered) of its blocks. mode: stored, fixed, dynamic, or
    auto for the cheapest of them in each block. A stored block holds up to 65,535 bytes; more take several."""
    out, stats = _Bits(), []
    data = lz77_expand(tokens)
    groups = [tokens[i : i + block_tokens] for i in range(0, len(tokens), block_tokens)] or [[]]
    at = 0
    for g, group in enumerate(groups):
        last = g == len(groups) - 1
        size = sum(1 if t[0] >= 0 else t[1] for t in group)
        dyn = _dynamic(group)
        fixed = _token_bits(group, _FIXED, dict.fromkeys(range(30), 5))
        cost = {"stored": (size + 5 * max(1, -(-size // STORED))) * 8, "fixed": fixed, "dynamic": dyn[0]}
        chosen = min(cost, key=cost.get) if mode == "auto" else mode
        began = len(out.out) * 8 + out.n
        if chosen == "stored":
            part = data[at : at + size]
            for i in range(0, max(1, size), STORED):
                piece = part[i : i + STORED]
                out.put(int(last and i + STORED >= size), 1)
                out.put(0, 2)
                out.align()
                out.put(len(piece), 16)
                out.put(len(piece) ^ 0xFFFF, 16)
                for b in piece:
                    out.put(b, 8)
        else:
            out.put(int(last), 1)
            out.put(1 if chosen == "fixed" else 2, 2)
            if chosen == "fixed":
                lit, dist = huffman_codes(_FIXED), {d: (d, 5) for d in range(30)}
            else:
                _, lit_n, dist_n, sent, meta, n_lit, n_dist, n_meta = dyn
                out.put(n_lit - 257, 5)
                out.put(n_dist - 1, 5)
                out.put(n_meta - 4, 4)
                for s in _ORDER[:n_meta]:
                    out.put(meta.get(s, 0), 3)
                codes = huffman_codes(meta)
                for s, value, extra in sent:
                    out.code(codes[s])
                    out.put(value, extra)
                lit, dist = huffman_codes(lit_n), huffman_codes(dist_n)
            for literal, length, distance in group:
                if literal >= 0:
                    out.code(lit[literal])
                else:
                    s, value, extra = _symbol(length, _LENGTHS)
                    out.code(lit[257 + s])
                    out.put(value, extra)
                    s, value, extra = _symbol(distance, _DISTANCES)
                    out.code(dist[s])
                    out.put(value, extra)
            out.code(lit[256])
        stats.append((chosen, len(out.out) * 8 + out.n - began, size))
        at += size
    out.align()
    return bytes(out.out), stats


def inflate_blocks(data: bytes) -> bytes:
    """Bytes of a raw Deflate stream; a block of the reserved mode, or a damaged one, raises ValueError."""
    out, at, last = bytearray(), 0, False

    def get(width: int) -> int:
        nonlocal at
        x = 0
        for k in range(width):
            byte = at >> 3
            if byte >= len(data):
                raise ValueError("stream ends early")
            x |= (data[byte] >> (at & 7) & 1) << k
            at += 1
        return x

    def symbol(table: dict[tuple[int, int], int]) -> int:
        code = 0
        for width in range(1, 16):
            code = code << 1 | get(1)
            if (code, width) in table:
                return table[code, width]
        raise ValueError("no such code")

    turn = lambda lengths: {c: s for s, c in huffman_codes(lengths).items()}
    while not last:
        last, mode = bool(get(1)), get(2)
        if mode == 3:
            raise ValueError("reserved block mode")
        if mode == 0:
            at = (at + 7) & ~7
            size, check = get(16), get(16)
            if size ^ check != 0xFFFF:
                raise ValueError("damaged stored block")
            out += data[at >> 3 : (at >> 3) + size]
            at += 8 * size
            continue
        if mode == 1:
            lit, dist = turn(_FIXED), {(d, 5): d for d in range(30)}
        else:
            n_lit, n_dist, n_meta = get(5) + 257, get(5) + 1, get(4) + 4
            meta = turn({s: get(3) for s in _ORDER[:n_meta]})
            lengths: list[int] = []
            while len(lengths) < n_lit + n_dist:
                s = symbol(meta)
                if s < 16:
                    lengths.append(s)
                else:
                    value, width, least = (lengths[-1], 2, 3) if s == 16 else (0, 3, 3) if s == 17 else (0, 7, 11)
                    lengths += [value] * (get(width) + least)
            lit, dist = turn(dict(enumerate(lengths[:n_lit]))), turn(dict(enumerate(lengths[n_lit:])))
        while (s := symbol(lit)) != 256:
            if s < 256:
                out.append(s)
            else:
                base, extra = _LENGTHS[s - 257]
                length = base + get(extra)
                base, extra = _DISTANCES[symbol(dist)]
                distance = base + get(extra)
                for _ in range(length):
                    out.append(out[-distance])
    return bytes(out)
