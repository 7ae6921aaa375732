"""Byte and text codes of bipartitions and tree-id lists. Pure functions on bytes and arrays.

Packed bipartition code: the bitstring in chunks of eight bits, zero-padded at the end. Marker 0 and a count stand for
chunks of zeros, marker 1 and a count for chunks of ones, a marker v >= 2 for v literal chunks that follow. Rules for what
that leaves open: a single literal chunk borrows a neighbouring uniform chunk (rather from a run of one, else from the
left), and a string of one mixed chunk gets a zero chunk after it; runs and literals are cut at 255, no literal piece
being one chunk.

Packed id code: the first id in two bytes, then differences of one byte; 0 announces a difference in two bytes. Fields are
big-endian. In the wide form the first id has four bytes, and 0 with a zero two-byte field announces four bytes.
"""

from __future__ import annotations

import re

import numpy as np

_RUNS = re.compile(rb"\x00+|\xff+|[^\x00\xff]+")


def pack_bits(members: np.ndarray, n: int) -> bytes:
    """Bitstring of a set of ordinals, most significant bit first, zero-padded to whole bytes."""
    row = np.zeros(n, np.uint8)
    row[members] = 1
    return np.packbits(row).tobytes()


def unpack_bits(bits: bytes, n: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(bits, np.uint8))[:n].astype(bool)


# --- gap keys: sets in the space of their members, in the order of their bitstrings -------------------------------


def gap_keys(row: np.ndarray, at: np.ndarray, value: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Keys of k zero-padded bitstrings, end to end, and their offsets, from the bytes that are not zero (row, place and value,
    by row and place). For each such byte: a zero for 255 zero bytes before it, 255 less what is left of them, and the value.
    Keys are equal when the bitstrings are, and ascend with them."""
    first = np.concatenate(([True], row[1:] != row[:-1])) if len(row) else np.zeros(0, bool)
    gap = at - np.where(first, -1, np.concatenate(([0], at[:-1]))[: len(at)]) - 1
    end = np.cumsum(gap // 255 + 2)
    out = np.zeros(int(end[-1]) if len(end) else 0, np.uint8)
    out[end - 2], out[end - 1] = 255 - gap % 255, value
    return out, np.concatenate(([0], end))[np.searchsorted(row, np.arange(k + 1))]


def gap_tokens(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The bytes that are not zero of the bitstrings of keys: row, place and value, by row and place."""
    raw = np.frombuffer(b"".join(keys), np.uint8)
    some = np.flatnonzero(raw)
    head, tail = some[0::2], some[1::2]
    row = np.searchsorted(np.cumsum([len(x) for x in keys]), head, "right")
    before = np.concatenate(([0], tail[:-1] + 1))[: len(head)]
    at = np.cumsum(255 * (head - before) + 256 - raw[head].astype(np.int64))
    start = np.searchsorted(row, row)
    return row, at - np.where(start > 0, at[start - 1], 0) - 1, raw[tail]


def members_of(keys: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(row, ordinal) of the members of the sets of keys, by row and ordinal."""
    row, at, value = gap_tokens(keys)
    token, bit = np.nonzero(np.unpackbits(value[:, None], axis=1))
    return row[token], 8 * at[token] + bit


def keys_of_members(row: np.ndarray, member: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """gap_keys of k sets given by their members (row, ordinal), by row and ordinal."""
    at = member >> 3
    new = np.flatnonzero(np.concatenate(([True], (row[1:] != row[:-1]) | (at[1:] != at[:-1])))) if len(row) else np.zeros(0, np.int64)
    value = np.add.reduceat(128 >> (member & 7), new) if len(new) else new
    return gap_keys(row[new], at[new], value.astype(np.uint8), k)


def keys_of_bits(rows: list[bytes]) -> list[bytes]:
    """The key of each of some bitstrings of one length."""
    width = -(-len(rows[0]) // 8) if rows else 0  # most bytes are zero: words of eight are looked at first
    table = np.frombuffer(b"".join([x.ljust(8 * width, b"\0") for x in rows]), np.uint64).reshape(len(rows), width)
    row, word = np.nonzero(table)
    some = table[row, word].view(np.uint8).reshape(-1, 8)
    k, j = np.nonzero(some)
    return cut(*gap_keys(row[k], 8 * word[k] + j, some[k, j], len(rows)))


def cut(raw: np.ndarray, off: np.ndarray) -> list[bytes]:
    whole, off = raw.tobytes(), off.tolist()
    return [whole[a:b] for a, b in zip(off[:-1], off[1:])]


def bits_of_key(key: bytes, n: int) -> bytes:
    """The zero-padded bitstring of n bits of a key."""
    _, at, value = gap_tokens([key])
    out = np.zeros((n + 7) // 8, np.uint8)
    out[at] = value
    return out.tobytes()


def packed_bits_of_key(key: bytes, n: int) -> bytes:
    """packed_bits_encode of the bitstring of a key, whose runs are found among the bytes that are not zero."""
    _, at, value = gap_tokens([key])
    out = np.zeros((n + 7) // 8, np.uint8)
    out[at] = value
    full = value == 255
    cuts = np.concatenate(([True], (at[1:] != at[:-1] + 1) | (full[1:] != full[:-1])))
    starts = at[cuts].tolist()
    ends = (at[np.concatenate((cuts[1:], [True]))] + 1).tolist()
    spans, last = [], 0
    for a, b in zip(starts, ends, strict=True):
        if a > last:
            spans.append((last, a))
        spans.append((a, b))
        last = b
    if last < len(out):
        spans.append((last, len(out)))
    return packed_bits_encode(out.tobytes(), spans)


def card_of_key(key: bytes) -> int:
    raw = np.frombuffer(key, np.uint8)
    return int(np.bitwise_count(raw[raw != 0][1::2]).sum())


def _pieces(total: int, literal: bool) -> list[int]:
    out = []
    while total > 255:
        take = 254 if literal and total == 256 else 255
        out.append(take)
        total -= take
    return [*out, total]


def packed_bits_encode(bits: bytes, spans: list[tuple[int, int]] | None = None) -> bytes:
    """Code of a zero-padded bitstring; spans: its runs of zeros, of ones and of others, if they are known."""
    if spans is None:
        spans = [(m.start(), m.end()) for m in _RUNS.finditer(bits)]
    if all(b - a < 256 and (b - a > 1 or bits[a] in (0, 255)) for a, b in spans):  # nothing to borrow or to cut
        return b"".join(bytes((bits[a] & 1, b - a)) if bits[a] in (0, 255) else bytes((b - a,)) + bits[a:b] for a, b in spans)
    runs = [[0 if bits[a] == 0 else 1 if bits[a] == 255 else 2, a, b] for a, b in spans]
    if runs == [[2, 0, 1]]:
        return bytes((2, bits[0], 0))
    for k, run in enumerate(runs):
        if run[0] == 2 and run[2] - run[1] == 1:
            # a neighbour that is itself literal has borrowed already or is none: literals never stand side by side
            near = [j for j in (k - 1, k + 1) if 0 <= j < len(runs) and runs[j][0] != 2 and runs[j][2] > runs[j][1]]
            if not near:  # its neighbours were borrowed whole: join the literal on the left
                run[1] = runs[k - 1][1] if k else run[1]
                continue
            j = min(near, key=lambda j: (runs[j][2] - runs[j][1] > 1, j > k))
            if j < k:
                runs[j][2] -= 1
                run[1] -= 1
            else:
                runs[j][1] += 1
                run[2] += 1
    merged: list[list[int]] = []
    for kind, a, b in runs:
        if a >= b:
            continue
        if merged and kind == 2 and merged[-1][0] == 2:
            merged[-1][2] = b
        else:
            merged.append([kind, a, b])
    out = bytearray()
    for kind, a, b in merged:
        if kind != 2:
            many = (b - a - 1) // 255
            out += bytes((kind, 255)) * many + bytes((kind, b - a - 255 * many))
            continue
        for size in _pieces(b - a, True):
            out.append(size)
            out += bits[a : a + size]
            a += size
    return bytes(out)


def packed_bits_decode(code: bytes, n: int, at: int = 0) -> tuple[bytes, int]:
    """Zero-padded bitstring of n bits that is coded from position at on, and the position after it."""
    want, out = (n + 7) // 8, bytearray()
    while len(out) < want:
        mark = code[at]
        if mark < 2:
            out += (b"\x00", b"\xff")[mark] * code[at + 1]
            at += 2
        else:
            out += code[at + 1 : at + 1 + mark]
            at += 1 + mark
    return bytes(out[:want]), at


#: Lists of so many ids are encoded one by one.
_SHORT = 32


def _short_ids_encode(ids: list[int], wide: bool) -> bytes:
    if not wide and ids[-1] > 65535 and (ids[0] > 65535 or max(b - a for a, b in zip(ids, ids[1:])) > 65535):
        raise ValueError("ids need the wide form")
    out, last = bytearray(ids[0].to_bytes(4 if wide else 2, "big")), ids[0]
    for x in ids[1:]:
        gap, last = x - last, x
        if gap < 1:
            raise ValueError("ids must ascend strictly")
        if gap < 256:
            out.append(gap)
        elif gap < 65536:
            out += bytes((0, gap >> 8, gap & 255))
        else:
            out += b"\x00\x00\x00" + gap.to_bytes(4, "big")
    return bytes(out)


def packed_ids_encode(ids, wide: bool = False) -> bytes:
    """Code of strictly ascending ids."""
    if not len(ids):
        return b""
    if len(ids) <= _SHORT:  # most lists are short, and then plain loops are faster
        return _short_ids_encode(np.asarray(ids).tolist(), wide)
    ids = np.asarray(ids, np.int64)
    first, gaps = int(ids[0]), np.diff(ids)
    if len(gaps) and gaps.min() < 1:
        raise ValueError("ids must ascend strictly")
    if not wide and (first > 65535 or (len(gaps) and gaps.max() > 65535)):
        raise ValueError("ids need the wide form")
    head = first.to_bytes(4 if wide else 2, "big")
    if not len(gaps) or gaps.max() <= 255:
        return head + gaps.astype(np.uint8).tobytes()
    sizes = np.where(gaps <= 255, 1, np.where(gaps <= 65535, 3, 7))
    at = np.cumsum(sizes) - sizes
    out = np.zeros(int(sizes.sum()), np.uint8)
    out[at[sizes == 1]] = gaps[sizes == 1]
    for size, shift in ((3, (8, 0)), (7, (24, 16, 8, 0))):
        pick = sizes == size
        for k, s in enumerate(shift):
            out[at[pick] + size - len(shift) + k] = (gaps[pick] >> s) & 255
    return head + out.tobytes()


def packed_ids_decode(code: bytes, count: int, at: int = 0, wide: bool = False) -> tuple[np.ndarray, int]:
    if not count:
        return np.zeros(0, np.int64), at
    width = 4 if wide else 2
    first = int.from_bytes(code[at : at + width], "big")
    at += width
    flat = code[at : at + count - 1]
    if 0 not in flat:
        gaps = np.frombuffer(flat, np.uint8).astype(np.int64)
        return first + np.concatenate(([0], np.cumsum(gaps))), at + count - 1
    out = [first]
    for _ in range(count - 1):
        gap = code[at]
        at += 1
        if gap == 0:
            gap = int.from_bytes(code[at : at + 2], "big")
            at += 2
            if gap == 0:
                gap = int.from_bytes(code[at : at + 4], "big")
                at += 4
        out.append(out[-1] + gap)
    return np.array(out, np.int64), at


def varint(x: int) -> bytes:
    out = bytearray()
    while x > 127:
        out.append(x & 127 | 128)
        x >>= 7
    out.append(x)
    return bytes(out)


def read_varint(data: bytes, at: int) -> tuple[int, int]:
    x = shift = 0
    while True:
        b = data[at]
        at += 1
        x |= (b & 127) << shift
        if b < 128:
            return x, at
        shift += 7


def runs_encode(ids) -> bytes:
    """Strictly ascending ids as runs of consecutive ones: for each the gap before it and its length, as varints. A full
    range takes a few bytes."""
    ids = np.asarray(ids, np.int64)
    if not len(ids):
        return b""
    cuts = np.flatnonzero(np.diff(ids) != 1) + 1
    starts, ends = ids[np.concatenate(([0], cuts))], ids[np.concatenate((cuts - 1, [len(ids) - 1]))] + 1
    gaps = starts - np.concatenate(([0], ends[:-1]))
    return b"".join(varint(g) + varint(n) for g, n in zip(gaps.tolist(), (ends - starts).tolist(), strict=True))


def runs_decode(data: bytes) -> np.ndarray:
    out, at, end = [], 0, 0
    while at < len(data):
        gap, at = read_varint(data, at)
        n, at = read_varint(data, at)
        out.append(np.arange(end + gap, end + gap + n))
        end += gap + n
    return np.concatenate(out) if out else np.zeros(0, np.int64)


# --- text codes of the baseline -----------------------------------------------------------------------------------

_TEXT = re.compile(r"0+|1+")
_UNTEXT = re.compile(r"([LK])(\d+)|([AB])")
_FIRST_DIGIT = "ABCDEFGHIJ"


def bit_text(bits: bytes, n: int) -> str:
    return format(int.from_bytes(bits, "big"), f"0{len(bits) * 8}b")[:n] if bits else ""


def textrun_bits_encode(text: str) -> str:
    """Runs of two or more zeros (L) or ones (K) with their decimal length; A and B for single ones."""
    return "".join(("LK" if m.end() - m.start() > 1 else "AB")[m[0][0] == "1"] + (str(m.end() - m.start()) if m.end() - m.start() > 1 else "") for m in _TEXT.finditer(text))


def textrun_bits_decode(code: str) -> str:
    return "".join("01"[m[1] == "K"] * int(m[2]) if m[1] else "01"[m[3] == "B"] for m in _UNTEXT.finditer(code))


def textrun_ids_encode(ids) -> str:
    """First id and differences in decimal; the first digit of each as a letter A to J."""
    ids = [int(i) for i in ids]
    return "".join(_FIRST_DIGIT[int(d[0])] + d[1:] for d in map(str, ids[:1] + [b - a for a, b in zip(ids, ids[1:])]))


def textrun_ids_decode(code: str) -> list[int]:
    out: list[int] = []
    for m in re.finditer(r"([A-J])(\d*)", code):
        gap = int(str(_FIRST_DIGIT.index(m[1])) + m[2])
        out.append(out[-1] + gap if out else gap)
    return out


def fixed_ids_encode(ids, width: int = 2) -> bytes:
    """The same number of bytes for the first id and every difference."""
    ids = [int(i) for i in ids]
    return b"".join(x.to_bytes(width, "big") for x in ids[:1] + [b - a for a, b in zip(ids, ids[1:])])
