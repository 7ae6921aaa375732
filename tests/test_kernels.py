"""Worked examples and properties of the kernels."""

import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cladepack.kernels import codes, deflate
from cladepack.kernels import newick as nw
from cladepack.kernels import trees as tk


def pack(text):
    return np.packbits(np.array(list(text), np.uint8)).tobytes()


EXAMPLE = "0" * 40 + "000011001110010111000101" + "1" * 56 + "0" * 120


def test_worked_bipartition():
    assert codes.packed_bits_encode(pack(EXAMPLE)).hex() == "0005030ce5c50107000f"
    assert codes.textrun_bits_encode(EXAMPLE) == "L44K2L2K3L2BAK3L3BAK57L120"
    assert codes.textrun_bits_encode("0001101") == "L3K2AB"


def test_worked_support_list():
    ids = [345, 544, 1599, 1721, 1970]
    assert codes.packed_ids_encode(ids).hex() == "0159c700041f7af9"
    assert codes.textrun_ids_encode(ids) == "D45B99B055B22C49"


def test_single_mixed_chunk():
    assert codes.packed_bits_encode(b"\xaa").hex() == "02aa00"
    assert codes.packed_bits_decode(bytes.fromhex("02aa00"), 8) == (b"\xaa", 3)


chunk = st.one_of(st.just(0), st.just(255), st.integers(1, 254))


@settings(max_examples=400, deadline=None)
@given(st.lists(st.tuples(chunk, st.integers(1, 300)), min_size=1, max_size=8))
def test_packed_bits_roundtrip(runs):
    raw = bytes(b for value, n in runs for b in [value] * n)
    code = codes.packed_bits_encode(raw)
    assert codes.packed_bits_decode(code, 8 * len(raw)) == (raw, len(code))
    at = 0
    while at < len(code):  # no literal piece of one chunk, none empty
        assert code[at] != 0 or code[at + 1] > 0
        at += 2 if code[at] < 2 else 1 + code[at]


@pytest.mark.parametrize("n", [1, 2, 7, 8, 9, 15, 16, 17, 2039, 2040, 2041, 2048, 2554])
def test_packed_bits_of_any_length(n):
    rng = np.random.default_rng(n)
    for row in (np.zeros(n, bool), np.ones(n, bool), np.arange(n) % 2 == 0, rng.random(n) < 0.5, rng.random(n) < 0.01):
        bits = codes.pack_bits(np.flatnonzero(row), n)
        assert (codes.unpack_bits(codes.packed_bits_decode(codes.packed_bits_encode(bits), n)[0], n) == row).all()
        assert codes.textrun_bits_decode(codes.textrun_bits_encode(codes.bit_text(bits, n))) == codes.bit_text(bits, n)


@settings(max_examples=300, deadline=None)
@given(st.integers(0, 70000), st.lists(st.sampled_from([1, 2, 254, 255, 256, 300, 65535, 65536, 70000]), max_size=12))
def test_ids_roundtrip(first, gaps):
    ids = np.cumsum([first, *gaps])
    code = codes.packed_ids_encode(ids, True)
    back, at = codes.packed_ids_decode(code, len(ids), 0, True)
    assert (back == ids).all() and at == len(code)
    assert codes.textrun_ids_decode(codes.textrun_ids_encode(ids)) == ids.tolist()
    if first <= 65535 and max(gaps, default=1) <= 65535:
        short = codes.packed_ids_encode(ids)
        assert (codes.packed_ids_decode(short, len(ids))[0] == ids).all()
    else:
        with pytest.raises(ValueError):
            codes.packed_ids_encode(ids)


def test_empty_list():
    assert codes.packed_ids_encode([]) == b"" and codes.textrun_ids_encode([]) == ""


@settings(max_examples=60, deadline=None)
@given(st.one_of(st.binary(max_size=600), st.lists(st.sampled_from([b"abc", b"ab", b"xyz", b"\x00"]), max_size=200).map(b"".join)))
def test_deflate_stages(data):
    tokens = deflate.lz77_tokens(data)
    assert deflate.lz77_expand(tokens) == data
    for mode in ("auto", "stored", "fixed", "dynamic"):
        stream, stats = deflate.deflate_blocks(tokens, mode, 100)
        assert zlib.decompress(stream, -15) == data
        assert deflate.inflate_blocks(stream) == data
        assert sum(s[2] for s in stats) == len(data)
    assert deflate.inflate_blocks(zlib.compress(data, 9)[2:-4]) == data


def test_deflate_limits():
    tokens = deflate.lz77_tokens(b"a" * 1000)
    assert max(t[1] for t in tokens) == 258
    far = b"abcdef" + bytes(40000) + b"abcdef"
    assert all(t[2] <= 32768 for t in deflate.lz77_tokens(far))
    big = bytes(np.random.default_rng(0).integers(0, 256, 70000, dtype=np.uint8))
    stream, _ = deflate.deflate_blocks([(b, 0, 0) for b in big], "stored", 10**6)
    assert zlib.decompress(stream, -15) == big
    with pytest.raises(ValueError):
        deflate.inflate_blocks(b"\x07")


@settings(max_examples=100, deadline=None)
@given(st.dictionaries(st.integers(0, 285), st.integers(1, 10**6), min_size=2, max_size=120))
def test_huffman(freqs):
    for limit in (7, 15) if len(freqs) <= 128 else (15,):
        lengths = deflate.huffman_lengths(freqs, limit)
        assert max(lengths.values()) <= limit and sum(2.0**-n for n in lengths.values()) == 1.0
        words = [format(c, f"0{n}b") for c, n in deflate.huffman_codes(lengths).values()]
        assert not any(a != b and b.startswith(a) for a in words for b in words)
    order = sorted(freqs, key=freqs.get)
    lengths = deflate.huffman_lengths(freqs)
    assert lengths[order[0]] >= lengths[order[-1]]


def test_newick_examples():
    assert nw.canonical(nw.parse("((A,B),(C,D));")) == nw.canonical(nw.parse("((D,C),(B,A));"))
    assert nw.canonical(nw.parse("((A:9,B:18):13,(D:10,C:12):16):10;")) == "((A:9,B:18):13,(C:12,D:10):16):10;"
    assert nw.canonical(nw.parse("((D,C)Y,(B,A)Z)X;")) == "((A,B)Z,(C,D)Y)X;"
    assert nw.canonical(nw.parse("((A:1):2,B:3e-2);")) == "(A:3,B:3e-2);"
    assert nw.canonical(nw.parse("('it''s a',c[note]:-1.5,B)")) == "(B,c:-1.5,'it''s a');"


@pytest.mark.parametrize("text,error", [("", "empty"), (None, "empty"), ("(A,B", "unbalanced"), ("(A,B));", "unbalanced"), ("(A,A);", "duplicate"), ("(A:x,B);", "length"), ("(A:,B);", "length"), ("(A,,B);", "label"), ("(A,B);C", "syntax"), ("(A,B)(C);", "syntax"), ("A;", None), ("(A,B,C,D);", None)])
def test_newick_errors(text, error):
    assert nw.error_of(text) == error


def test_deep_tree():
    n = 3000
    text = "(" * (n - 1) + "L0" + "".join(f",L{i})" for i in range(1, n)) + ";"
    assert nw.canonical(nw.parse(text)).count("(") == n - 1


def test_batch_parser_agrees():
    rng = np.random.default_rng(3)
    taxa = [f"T{i}" for i in range(20)]
    hashes = np.array([nw.hash_label(t.encode()) for t in taxa], np.uint64)
    order = np.argsort(hashes)
    texts = []
    for _ in range(30):
        parts = list(rng.permutation(taxa))
        while len(parts) > 1:
            k = min(len(parts), int(rng.integers(2, 5)))
            at = int(rng.integers(0, len(parts) - k + 1))
            parts[at : at + k] = ["(" + ",".join(parts[at : at + k]) + ")"]
        texts.append(parts[0] + ";")
    raw = np.frombuffer("".join(texts).encode(), np.uint8)
    taxon, off, tree, first, last = nw.batch_topology(raw, np.concatenate(([0], np.cumsum([len(t) for t in texts]))), hashes[order], order)
    for i, text in enumerate(texts):
        t = nw.parse(text)
        names = t.leaves()
        want = {frozenset(names[a : b + 1]) for a, b in zip(t.first, t.last) if a < b}
        assert {frozenset(taxa[x] for x in taxon[a : b + 1]) for a, b in zip(first[tree == i], last[tree == i])} == want
        assert [taxa[x] for x in taxon[off[i] : off[i + 1]]] == names


def laminar(rng, n):
    rows, stack = [], [np.arange(n)]
    while stack:
        part = rng.permutation(stack.pop())
        for piece in np.array_split(part, int(rng.integers(2, 4))):
            if 1 < len(piece) < n:
                row = np.zeros(n, bool)
                row[piece] = True
                rows.append(row)
                stack.append(piece)
    return np.array(rows).reshape(-1, n)


@pytest.mark.parametrize("seed", range(20))
def test_rebuild_methods_agree(seed):
    rng = np.random.default_rng(seed)
    rows = tk.sort_clusters(np.unique(laminar(rng, int(rng.integers(3, 40))), axis=0))
    assert tk.is_laminar(rows)
    results = [fn(rows) for fn in tk.METHODS.values()]
    for leaf, parent in results[1:]:
        assert (leaf == results[0][0]).all() and (parent == results[0][1]).all()


def test_worked_rebuild():
    rows = tk.sort_clusters(np.array([[0, 1, 1, 0, 0], [0, 0, 0, 1, 1], [1, 1, 1, 0, 0]], bool))
    kids = tk.children_lists(*tk.leaf_path(rows))
    text = nw.write(len(kids) - 1, kids, [*"ABCDE", None, None, None, None], [None] * 9)
    assert nw.canonical(nw.parse(text)) == "((A,(B,C)),(D,E));"
    assert not tk.is_laminar(np.array([[1, 1, 0], [0, 1, 1]], bool))


@pytest.mark.parametrize("n", [1, 7, 8, 300, 5000, 9001])
def test_gap_keys_are_exact_and_in_the_order_of_the_bits(n):
    rng = np.random.default_rng(n)
    sets = [np.flatnonzero(rng.random(n) < p) for p in (0, 0.0005, 0.001, 0.01, 0.5, 0.99, 1) for _ in range(6)] + [np.array([0]), np.array([n - 1])]
    bits = [codes.pack_bits(s, n) for s in sets]
    keys = codes.keys_of_bits(bits)
    assert [codes.bits_of_key(k, n) for k in keys] == bits and [codes.card_of_key(k) for k in keys] == [len(s) for s in sets]
    assert sorted(range(len(keys)), key=lambda i: keys[i]) == sorted(range(len(keys)), key=lambda i: bits[i])
    assert [codes.packed_bits_of_key(k, n) for k in keys if k] == [codes.packed_bits_encode(b) for b, k in zip(bits, keys, strict=True) if k]
    row, at = codes.members_of(keys)
    assert row.tolist() == np.repeat(np.arange(len(sets)), [len(s) for s in sets]).tolist() and at.tolist() == np.concatenate(sets).tolist()
    assert codes.cut(*codes.keys_of_members(row, at, len(sets))) == keys
