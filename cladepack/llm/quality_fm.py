"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

score = sigmoid(b + sum_i w_i x_i + sum_{i<j} <v_i, v_j> x_i x_j). The pairwise sum is taken in linear time by the identity
sum_{i<j} <v_i, v_j> x_i x_j = 1/2 sum_f [(sum_i v_if x_i)^2 - sum_i v_if^2 x_i^2].

Features are the log-scaled, length-normalised counts of hashed words in 2**BITS cells and some statistics of the text,
each put into one of a few ranges. The model is fitted on the driver from a bounded number of labelled documents, whose
features are made on the executors; it has (FACTORS + 1) * cells numbers, whatever the input, and is broadcast.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, map_arrow, text_buffer, word_hashes

BITS, FACTORS = 14, 8
#: Labelled documents to learn from at most: those with the least hash of their id.
TRAIN_ROWS = 3_000
_RANGES = 16
_EDGES = {
    "symbols": np.array([0.002, 0.005, 0.01, 0.02, 0.04, 0.06, 0.08, 0.1, 0.13, 0.16, 0.2, 0.25, 0.3, 0.4, 0.6]),
    "digits": np.array([0.0005, 0.001, 0.002, 0.005, 0.01, 0.02, 0.05, 0.1, 0.15, 0.2, 0.3, 0.4, 0.5, 0.6, 0.8]),
    "distinct": np.array([0.05, 0.1, 0.15, 0.2, 0.25, 0.3, 0.35, 0.4, 0.5, 0.55, 0.6, 0.7, 0.8, 0.9, 0.97]),
    "word_length": np.array([2, 3, 3.5, 4, 4.4, 4.7, 5, 5.3, 5.6, 6, 6.5, 7, 8, 10, 14.0]),
    "log_words": np.array([0.5, 1, 2, 3, 3.5, 4, 4.5, 5, 5.5, 6, 6.5, 7, 8, 9, 10.0]),
    "line_words": np.array([1, 2, 3, 5, 8, 12, 16, 20, 30, 40, 60, 80, 120, 200, 400.0]),
    "upper": np.array([0.002, 0.005, 0.01, 0.015, 0.02, 0.03, 0.04, 0.05, 0.07, 0.1, 0.15, 0.2, 0.3, 0.5, 0.8]),
    "stops": np.array([0.001, 0.004, 0.008, 0.012, 0.016, 0.02, 0.025, 0.03, 0.035, 0.04, 0.05, 0.06, 0.08, 0.1, 0.2]),
}
SIZE = (1 << BITS) + len(_EDGES) * _RANGES
_CLASS = np.zeros(256, np.uint8)  # 1 symbol, 2 digit, 3 upper-case letter, 4 line end, 5 end mark
_CLASS[[ord(c) for c in "#$%&*|@^~<>{}[]\\_=+"]] = 1
_CLASS[48:58] = 2
_CLASS[65:91] = 3
_CLASS[10] = 4
_CLASS[[ord(c) for c in ".!?"]] = 5


def features(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse rows (offsets, cells, values) of a column of texts: distinct cells within a row."""
    raw, off = text_buffer(column)
    words, at = word_hashes(column)
    n, n_words = len(off) - 1, np.diff(at)
    row = np.repeat(np.arange(n), n_words)
    both, count = np.unique((row.astype(np.int64) << BITS) | (words >> np.uint64(64 - BITS)).astype(np.int64), return_counts=True)
    of, cell = both >> BITS, both & ((1 << BITS) - 1)
    value = np.log1p(count)
    norm = np.sqrt(np.bincount(of, value**2, minlength=n))
    value = value / norm[of]
    classes = np.zeros((n, 6))
    step = 1 << 20
    for a in range(0, len(raw), step):
        part = np.searchsorted(off, np.arange(a, min(len(raw), a + step)), "right") - 1
        classes += np.bincount(part * 6 + _CLASS[raw[a : a + step]], minlength=6 * n).reshape(n, 6)
    length = np.maximum(1, np.diff(off))
    distinct = np.bincount(of, minlength=n) / np.maximum(1, n_words)
    stats = {
        "symbols": classes[:, 1] / length, "digits": classes[:, 2] / length, "distinct": distinct, "word_length": (length - n_words) / np.maximum(1, n_words),
        "log_words": np.log1p(n_words), "line_words": n_words / (classes[:, 4] + 1), "upper": classes[:, 3] / length, "stops": classes[:, 5] / length,
    }
    base, extra = 1 << BITS, []
    for k, (name, edges) in enumerate(_EDGES.items()):
        extra.append(base + k * _RANGES + np.searchsorted(edges, stats[name], "right"))
    k = len(_EDGES)
    cells = np.concatenate([cell, *extra])
    values = np.concatenate([value, np.full(n * k, 0.5)])
    of = np.concatenate([of, np.tile(np.arange(n), k)])
    order = np.argsort(of, kind="stable")
    return np.concatenate(([0], np.cumsum(np.bincount(of, minlength=n)))), cells[order], values[order]


class FactorisationMachine:
    def __init__(self, bias: float, w: np.ndarray, v: np.ndarray):
        self.bias, self.w, self.v = bias, w, v

    def raw(self, off: np.ndarray, cells: np.ndarray, values: np.ndarray) -> np.ndarray:
        """Scores before the sigmoid, in time linear in the number of features."""
        n = len(off) - 1
        if not len(cells):
            return np.full(n, self.bias)
        vx = self.v[cells] * values[:, None]
        pad = lambda x: np.add.reduceat(x, off[:-1], axis=0)  # every row has its statistics, so none is empty
        return self.bias + pad(self.w[cells] * values) + 0.5 * (pad(vx) ** 2 - pad(vx**2)).sum(1)

    def predict(self, column: pa.Array) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw(*features(column)), -30, 30)))

    @classmethod
    def train(cls, off: np.ndarray, cells: np.ndarray, values: np.ndarray, y: np.ndarray, epochs: int = 12, rate: float = 0.05, decay: float = 1e-4, seed: int = 7) -> FactorisationMachine:
        """Mini-batch Adagrad on the log loss; the two classes weigh as they occur."""
        rng = np.random.default_rng(seed)
        w, v = np.zeros(SIZE), rng.normal(0, 0.02, (SIZE, FACTORS))
        mean = min(0.99, max(0.01, float(y.mean()))) if len(y) else 0.5
        fm = cls(float(np.log(mean / (1 - mean))), w, v)
        gw, gv = np.full(SIZE, 1e-6), np.full((SIZE, FACTORS), 1e-6)
        gb, size = 1e-6, 64
        for _ in range(epochs):
            order = rng.permutation(len(y))
            for a in range(0, len(y), size):
                ids = order[a : a + size]
                parts = [np.arange(off[i], off[i + 1]) for i in ids]
                at, lens = np.concatenate(parts), np.array([len(p) for p in parts])
                c, x, row = cells[at], values[at], np.repeat(np.arange(len(ids)), lens)
                starts = np.concatenate(([0], np.cumsum(lens)))
                vx = v[c] * x[:, None]
                total = np.add.reduceat(vx, starts[:-1], axis=0)
                z = fm.bias + np.add.reduceat(w[c] * x, starts[:-1]) + 0.5 * (total**2 - np.add.reduceat(vx**2, starts[:-1], axis=0)).sum(1)
                err = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[ids]
                u, inv = np.unique(c, return_inverse=True)
                dw = np.bincount(inv, err[row] * x) / len(ids) + decay * w[u]
                each = (err[row] * x)[:, None] * (total[row] - vx)
                dv = np.stack([np.bincount(inv, each[:, f]) for f in range(FACTORS)], 1) / len(ids) + decay * v[u]
                db = float(err.mean())
                gw[u] += dw**2
                gv[u] += dv**2
                gb += db**2
                w[u] -= rate * dw / np.sqrt(gw[u])
                v[u] -= rate * dv / np.sqrt(gv[u])
                fm.bias -= rate * db / gb**0.5
        return fm


def fit(docs: DataFrame, labels: DataFrame, most: int = TRAIN_ROWS) -> FactorisationMachine:
    """Learn from docs joined with labels (doc_id, quality); at most `most` labelled rows, those with the least hash of
    their id; of rows with one id the text with the least hash. Without labels the score is 0.5 everywhere."""
    mine = labels.where("quality is not null and doc_id is not null").select("doc_id", F.col("quality").cast("int").alias("quality")).groupBy("doc_id").agg(F.max("quality").alias("quality"))
    mine = mine.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)  # bounded, so broadcast is safe

    def fn(batch: pa.RecordBatch):
        off, cells, values = features(batch.column(1))
        ends = pa.array(off, pa.int32())
        yield batch_of({"y": batch.column(0), "cells": pa.ListArray.from_arrays(ends, pa.array(cells, pa.int32())), "x": pa.ListArray.from_arrays(ends, pa.array(values, pa.float32()))})

    rows = docs.select("doc_id", "text").join(F.broadcast(mine), "doc_id").groupBy("doc_id").agg(F.max("quality").alias("quality"), F.min_by("text", F.xxhash64("text")).alias("text"))
    got = map_arrow(rows.select("quality", "text"), fn, "y int, cells array<int>, x array<float>", 128).toArrow()
    if not got.num_rows:
        return FactorisationMachine(0.0, np.zeros(SIZE), np.zeros((SIZE, FACTORS)))
    cells, x = got.column("cells").combine_chunks(), got.column("x").combine_chunks()
    lens = np.asarray(cells.value_lengths().fill_null(0))
    # a fixed order of the rows, so that reruns learn the same model
    off = np.concatenate(([0], np.cumsum(lens)))
    flat, val, y = np.asarray(cells.flatten()), np.asarray(x.flatten(), dtype=np.float64), np.asarray(got.column("y"), dtype=np.float64)
    first = np.add.reduceat(flat.astype(np.float64) * val, off[:-1])
    order = np.lexsort((lens, first, y))
    at = np.concatenate([np.arange(off[i], off[i + 1]) for i in order])
    off = np.concatenate(([0], np.cumsum(lens[order])))
    return FactorisationMachine.train(off, flat[at], val[at], y[order])


def score_quality(docs: DataFrame, labels: DataFrame, folds: int = 3, most: int = TRAIN_ROWS) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs, learned from labels whose crc32(doc_id) mod folds is
    not 1. Null and empty texts get the score of a text without words. Repeated labels of one document count once, the
    larger one; rows with a null id are scored and not held out. Empty tables are allowed; other columns are ignored."""
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds
    model = fit(docs, labels.where(fold != 1), most)
    sent = docs.sparkSession.sparkContext.broadcast((model.bias, model.w.astype(np.float32), model.v.astype(np.float32)))

    def fn(batch: pa.RecordBatch):
        p = FactorisationMachine(*sent.value).predict(batch.column(1))
        yield batch_of({"doc_id": batch.column(0), "score": pa.array(p.astype(np.float64))})

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = map_arrow(rows, fn, "doc_id long, score double", 128)
    return out.select("doc_id", F.coalesce(fold == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
