"""Newick text: a parser with an explicit stack, a batch parser in numpy, a writer and the canonical form.

A tree is a list of nodes in postorder: (label, length lexeme, first leaf, last leaf, parent). Leaves are numbered in text
order; a node's leaves are consecutive. A node with one child is joined with it, their lengths being added.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from decimal import Decimal, InvalidOperation

import numpy as np

_TOKEN = re.compile(r"\s*(\(|\)|,|:|;|'(?:[^']|'')*'|\[[^\]]*\]|[^\s(),:;'\[]+)")
_NUMBER = re.compile(r"[+-]?(\d+\.?\d*|\.\d+)([eE][+-]?\d+)?\Z")
_PLAIN = re.compile(r"[^\s(),:;'\[\]]+\Z")


class NewickError(ValueError):
    """The reason is the first word: unbalanced, syntax, label, duplicate, length, empty."""


@dataclass
class Tree:
    """Arrays over nodes in postorder; the root is last."""

    label: list[str | None] = field(default_factory=list)
    length: list[str | None] = field(default_factory=list)
    first: list[int] = field(default_factory=list)
    last: list[int] = field(default_factory=list)
    parent: list[int] = field(default_factory=list)
    leaf: list[bool] = field(default_factory=list)

    def leaves(self) -> list[str]:
        return [x for x, is_leaf in zip(self.label, self.leaf, strict=True) if is_leaf]


def _sum(a: str | None, b: str | None) -> str | None:
    if a is None or b is None:
        return a if b is None else b
    return str(Decimal(a) + Decimal(b))


def parse(text: str | None) -> Tree:
    """Parse one tree. Comments in brackets are skipped; a quoted label keeps its blanks, doubled quotes are one; the last
    semicolon may be missing. Raises NewickError."""
    if text is None or not text.strip():
        raise NewickError("empty text")
    tree, at, done = Tree(), 0, False
    # open nodes: [first leaf, children]; `item` collects the node being read
    stack: list[list] = []
    state, children, first, n_leaves, seen = "start", None, 0, 0, set()
    label = length = None

    def close(is_leaf: bool) -> int:
        nonlocal n_leaves, label, length
        if is_leaf:
            if label is None:
                raise NewickError("label missing at a leaf")
            if label in seen:
                raise NewickError(f"duplicate leaf {label}")
            seen.add(label)
            lo = hi = n_leaves
            n_leaves += 1
        elif len(children) == 1:
            node = children[0]
            tree.length[node] = _sum(tree.length[node], length)
            if not tree.leaf[node] and label is not None:
                tree.label[node] = tree.label[node] or label
            label = length = None
            return node
        else:
            lo, hi = first, n_leaves - 1
        tree.label.append(label)
        tree.length.append(length)
        tree.first.append(lo)
        tree.last.append(hi)
        tree.parent.append(-1)
        tree.leaf.append(is_leaf)
        node = len(tree.label) - 1
        for c in children or ():
            tree.parent[c] = node
        label = length = None
        return node

    is_leaf = True
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            if text[at:].strip():
                raise NewickError("syntax at " + str(at))
            break
        tok, at = m[1], m.end()
        if tok[0] == "[":
            continue
        if done:
            raise NewickError("syntax after the end")
        if tok == "(":
            if state not in ("start",):
                raise NewickError("syntax before an opening bracket")
            stack.append([n_leaves, []])
            state, is_leaf = "start", True
        elif tok in ",);":
            if state == "start" and is_leaf:
                raise NewickError("label missing at a leaf" if stack or tok != ";" else "empty text")
            if state == "colon":
                raise NewickError("length missing")
            node = close(is_leaf)
            if tok == ";":
                if stack:
                    raise NewickError("unbalanced brackets")
                done = True
                continue
            if not stack:
                raise NewickError("unbalanced brackets")
            stack[-1][1].append(node)
            if tok == ")":
                first, children = stack.pop()
                is_leaf, state = False, "inner"
            else:
                is_leaf, state, children = True, "start", None
        elif tok == ":":
            if state == "length":
                raise NewickError("length twice")
            if state == "start" and is_leaf:
                raise NewickError("label missing at a leaf")
            state = "colon"
        elif state == "colon":
            if not _NUMBER.match(tok):
                raise NewickError(f"length {tok[:20]}")
            length, state = tok, "length"
        elif state in ("start", "inner"):
            label = tok[1:-1].replace("''", "'") if tok[0] == "'" else tok
            state = "label"
        else:
            raise NewickError("syntax at a label")
        if tok == "(":
            children = None
    if not done:
        if stack:
            raise NewickError("unbalanced brackets")
        if state == "colon":
            raise NewickError("length missing")
        close(is_leaf)
    if tree.leaf[-1] and len(tree.leaf) > 1:
        raise NewickError("unbalanced brackets")
    return tree


def error_of(text: str | None) -> str | None:
    try:
        parse(text)
    except (NewickError, InvalidOperation) as e:
        return str(e).split()[0]
    return None


def quote(label: str | None) -> str:
    if label is None:
        return ""
    return label if _PLAIN.match(label) else "'" + label.replace("'", "''") + "'"


def write(root: int, children: list[list[int]], label: list[str | None], length: list[str | None]) -> str:
    """Newick text of a tree given by child lists."""
    out, stack = [], [(root, 0)]
    while stack:
        node, k = stack.pop()
        kids = children[node]
        if kids and k < len(kids):
            out.append("," if k else "(")
            stack.append((node, k + 1))
            stack.append((kids[k], 0))
            continue
        if kids:
            out.append(")")
        out.append(quote(label[node]))
        if length[node] is not None:
            out.append(":" + length[node])
    return "".join(out) + ";"


def children_of(tree: Tree) -> list[list[int]]:
    kids: list[list[int]] = [[] for _ in tree.label]
    for node, p in enumerate(tree.parent):
        if p >= 0:
            kids[p].append(node)
    return kids


def canonical(tree: Tree, labels: bool = True, lengths: bool = True) -> str:
    """Text with the children of every node in the order of the least leaf label below them; without inner labels or
    lengths if so asked. Equal for equal trees, whatever the order of children."""
    kids, least = children_of(tree), list(tree.label)
    for node in range(len(tree.label)):
        if kids[node]:
            kids[node].sort(key=lambda c: least[c])
            least[node] = least[kids[node][0]]
    label = [x if leaf or labels else None for x, leaf in zip(tree.label, tree.leaf, strict=True)]
    return write(len(tree.label) - 1, kids, label, tree.length if lengths else [None] * len(tree.label))


# --- many trees at once -------------------------------------------------------------------------------------------

_OPEN, _CLOSE, _COMMA, _COLON, _SEMI = b"(),:;"
_B = np.uint64(0x9E3779B97F4A7C15)
_BI = np.uint64(pow(int(_B), -1, 1 << 64))


def hash_label(raw: bytes) -> int:
    x = 0
    for i, b in enumerate(raw):
        x += (b + 1) * pow(int(_B), i, 1 << 64)
    return x & 0xFFFFFFFFFFFFFFFF


def batch_topology(raw: np.ndarray, off: np.ndarray, taxa_hash: np.ndarray, taxa_at: np.ndarray):
    """Topology of the trees in a text buffer of plain Newick (no quotes, comments, blanks or one-child nodes).

    Returns leaf ordinals in text order with their tree offsets, and for every bracket pair its tree and the first and last
    leaf (numbered over the buffer), children before parents; None if the text is not of that plain form. Brackets are
    matched without a stack: at each depth, the i-th opening one belongs to the i-th closing one.
    """
    n = len(raw)
    if not n:
        return None
    is_open, is_close = raw == _OPEN, raw == _CLOSE
    depth = np.cumsum(is_open.astype(np.int32) - is_close)
    edges = off[1:-1]
    if depth[-1] != 0 or depth.min() < 0 or (len(edges) and depth[edges - 1].any()):
        return None
    special = is_open | is_close | (raw == _COMMA) | (raw == _COLON) | (raw == _SEMI)
    at = np.flatnonzero(special)
    kind = raw[at]
    # a leaf starts after an opening bracket or a comma and ends before the next special character
    lead = np.flatnonzero((kind == _OPEN) | (kind == _COMMA))
    lead = lead[lead + 1 < len(at)]
    start, end = at[lead] + 1, at[lead + 1]
    leaf = kind[lead + 1] != _OPEN
    start, end = start[leaf], end[leaf]
    if (end <= start).any():
        return None
    pw = np.full(n, _B, np.uint64)
    pw[0] = 1
    pw = np.cumprod(pw, dtype=np.uint64)
    total = np.cumsum((raw.astype(np.uint64) + np.uint64(1)) * pw, dtype=np.uint64)
    inv = np.full(n, _BI, np.uint64)
    inv[0] = 1
    inv = np.cumprod(inv, dtype=np.uint64)
    h = (total[end - 1] - np.where(start > 0, total[start - 1], np.uint64(0))) * inv[start]
    pos = np.minimum(np.searchsorted(taxa_hash, h), len(taxa_hash) - 1)
    if (taxa_hash[pos] != h).any():
        return None
    taxon = taxa_at[pos]
    opens, closes = np.flatnonzero(is_open), np.flatnonzero(is_close)
    o = opens[np.argsort(depth[opens], kind="stable")]
    c = closes[np.argsort(depth[closes] + 1, kind="stable")]
    order = np.argsort(c, kind="stable")
    o, c = o[order], c[order]
    first, last = np.searchsorted(start, o), np.searchsorted(start, c) - 1
    if (last <= first).any():
        return None
    tree = np.searchsorted(off, o, "right") - 1
    leaf_off = np.searchsorted(start, off)
    return taxon, leaf_off, tree, first, last
