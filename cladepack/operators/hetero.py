"""Collections whose trees have different leaf sets: the union of the taxa, and a mask for each tree."""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernels import codes
from ..kernels import newick as nw
from ..kernels import trees as tk

_TAG = re.compile(r"<(/?)([a-zA-Z][a-zA-Z0-9]*)[^>]*?(/?)>")
_VOID = frozenset(("br", "hr", "img", "input", "link", "meta"))


def page_trees(pages: DataFrame) -> DataFrame:
    """(tree_id, newick) of the nesting of each page's elements: a leaf is an element without elements, named by its tag
    and its number among those of the page. Pages with fewer than two leaves give no tree."""

    def run(batches):
        for batch in batches:
            ids, texts = [], []
            for page, html in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                kids: list[list[int]] = [[]]
                tag, stack = ["#"], [0]
                for m in _TAG.finditer(html or ""):
                    name = m[2].lower()
                    if m[1]:
                        for i in range(len(stack) - 1, 0, -1):
                            if tag[stack[i]] == name:
                                del stack[i:]
                                break
                        continue
                    kids[stack[-1]].append(len(kids))
                    kids.append([])
                    tag.append(name)
                    if name not in _VOID and not m[3]:
                        stack.append(len(kids) - 1)
                seen: dict[str, int] = {}
                label: list[str | None] = [None] * len(kids)
                for x in range(1, len(kids)):
                    if not kids[x]:
                        seen[tag[x]] = seen.get(tag[x], 0) + 1
                        label[x] = f"{tag[x]}{seen[tag[x]]}"
                if sum(seen.values()) >= 2:
                    ids.append(page)
                    texts.append(nw.canonical(nw.parse(nw.write(0, kids, label, [None] * len(kids)))))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(texts, pa.string())], ["tree_id", "newick"])

    return pages.select("page_id", "html").mapInArrow(run, "tree_id long, newick string")


def union_taxa(trees: DataFrame) -> list[str]:
    """All labels of a collection, in order; the caller answers for their number."""

    def run(batches):
        for batch in batches:
            names = sorted({x for t in batch.column(0).to_pylist() for x in nw.parse(t).leaves()})
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.string())], ["label"])

    return [r[0] for r in trees.select("newick").mapInArrow(run, "label string").distinct().orderBy("label").collect()]


def compress_hetero(trees: DataFrame, taxa: list[str]) -> DataFrame:
    """(mask, bits, n_trees, mask_code, bits_code, ids_code): clusters grouped by the leaf set of their trees, coded over
    the union; the full set of a mask stands for the trees themselves."""
    n, ordinal = len(taxa), {t: i for i, t in enumerate(taxa)}

    def extract(batches):
        for batch in batches:
            rows = []
            for tree_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                t = nw.parse(text)
                at = np.array([ordinal[x] for x in t.leaves()])
                mask = codes.pack_bits(at, n)
                rows.append((mask, mask, tree_id))
                rows += [(mask, codes.pack_bits(at[a : b + 1], n), tree_id) for a, b in zip(t.first, t.last, strict=True) if 0 < b - a < len(at) - 1]
            cols = list(zip(*rows, strict=True)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.binary()), pa.array(cols[1], pa.binary()), pa.array(cols[2], pa.int64())], ["mask", "bits", "tree_id"])

    found = trees.select(F.col("tree_id").cast("long"), "newick").mapInArrow(extract, "mask binary, bits binary, tree_id long").distinct()
    lists = found.groupBy("mask", "bits").agg(F.count("*").alias("n_trees"), F.array_sort(F.collect_list("tree_id")).alias("ids"))

    def encode(batches):
        for batch in batches:
            mask, bits, count, ids = (batch.column(i).to_pylist() for i in range(4))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array([codes.packed_bits_encode(m) for m in mask], pa.binary()), pa.array([codes.packed_bits_encode(b) for b in bits], pa.binary()), pa.array([codes.packed_ids_encode(i, True) for i in ids], pa.binary())], ["mask", "bits", "n_trees", "mask_code", "bits_code", "ids_code"])

    return lists.mapInArrow(encode, "mask binary, bits binary, n_trees long, mask_code binary, bits_code binary, ids_code binary")


def decompress_hetero(packed: DataFrame, taxa: list[str]) -> DataFrame:
    """(tree_id, newick) of a table of compress_hetero."""
    n = len(taxa)

    def decode(batches):
        for batch in batches:
            rows = []
            for count, mask, bits, ids in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                m, b = codes.packed_bits_decode(mask, n)[0], codes.packed_bits_decode(bits, n)[0]
                rows += [(int(i), m, b) for i in codes.packed_ids_decode(ids, count, 0, True)[0]]
            cols = list(zip(*rows, strict=True)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.binary()), pa.array(cols[2], pa.binary())], ["tree_id", "mask", "bits"])

    per_tree = packed.select("n_trees", "mask_code", "bits_code", "ids_code").mapInArrow(decode, "tree_id long, mask binary, bits binary").groupBy("tree_id").agg(F.first("mask").alias("mask"), F.collect_list("bits").alias("bits"))

    def rebuild(batches):
        for batch in batches:
            texts = []
            for mask, bits in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                at = np.flatnonzero(codes.unpack_bits(mask, n))
                rows = np.array([codes.unpack_bits(b, n)[at] for b in bits if b != mask], bool).reshape(-1, len(at))
                kids = tk.children_lists(*tk.leaf_path(tk.sort_clusters(rows)))
                texts.append(nw.write(len(kids) - 1, kids, [*[taxa[x] for x in at], *[None] * len(kids)], [None] * len(kids)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["tree_id", "newick"])

    return per_tree.mapInArrow(rebuild, "tree_id long, newick string")
