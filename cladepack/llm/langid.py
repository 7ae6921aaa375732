"""Language identification: multinomial naive Bayes over hashed character n-grams.

Counts of the n-grams of orders 1 to 3 in 2**BITS hashed cells are learned per language; the matrix of log probabilities
(languages x cells, float32) is broadcast, its size being fixed by the parameters and a checked number of languages.
Texts are scored in batches in numpy: the n-gram counts of a batch are a sparse matrix of (text, cell, count), whose product
with the log-probability matrix gathers the rows of its entries and sums them by text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, batch_of, map_arrow, numbered, without

BITS = 15
ORDERS = (1, 2, 3)
#: Documents that a model learns from at most: those with the least hash of their id.
TRAIN_ROWS = 4_000
#: Languages a model may have; more raise an error, since the matrix is broadcast.
MOST_LANGS = 512
_PIECE = 1 << 17
#: Texts whose counts are taken together.
_ROWS = 32


def _cells(text: str) -> Iterator[np.ndarray]:
    """Cells of all character n-grams of a text, lower-cased; a piece at a time, each with the characters before it that its
    first n-grams begin with, so that none is lost between pieces."""
    code = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    lead = max(ORDERS) - 1
    for at in range(0, len(code), _PIECE):
        back = min(at, lead)
        part = code[at - back : at + _PIECE].astype(np.uint64)
        out, key = [], np.zeros(len(part) + 1, np.uint64)
        for n in range(1, lead + 2):
            if len(part) < n:
                break
            key = key[: len(part) - n + 1] * np.uint64(0x9E3779B97F4A7C15) + part[n - 1 :]
            if n in ORDERS:
                # n-grams that end before the piece were the last piece's
                out.append(((key[max(0, back - n + 1) :] + np.uint64(n)) * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(64 - BITS))
        yield np.concatenate(out).astype(np.int64)


def batch_counts(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The sparse matrix of a batch: (row, cell, count) of its entries, by row and cell."""
    total = np.zeros(len(texts) << BITS, np.int64)
    held, size = [], 0
    for i, text in enumerate(texts):
        for cells in _cells(text):
            held.append(cells + (i << BITS))
            size += len(cells)
            if size > 1 << 20:
                total += np.bincount(np.concatenate(held), minlength=len(total))
                held, size = [], 0
    if held:
        total += np.bincount(np.concatenate(held), minlength=len(total))
    hit = np.flatnonzero(total)
    return hit >> BITS, hit & ((1 << BITS) - 1), total[hit]


class NaiveBayes:
    def __init__(self, langs: list[str], log_p: np.ndarray, prior: np.ndarray):
        self.langs, self.log_p, self.prior = langs, log_p, prior

    def scores(self, texts: list[str]) -> np.ndarray:
        """Log joint probability of each text and language: the product of the sparse counts with the matrix."""
        out = np.tile(self.prior, (len(texts), 1))
        for at in range(0, len(texts), _ROWS):
            row, cell, n = batch_counts(texts[at : at + _ROWS])
            if len(row):
                first = np.flatnonzero(np.concatenate(([True], row[1:] != row[:-1])))
                out[at + row[first]] += np.add.reduceat(n[:, None] * self.log_p[cell].astype(np.float64), first)
        return out


def fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", most: int = TRAIN_ROWS) -> NaiveBayes:
    """Learn from the whole texts of at most `most` rows of docs with a language, those with the least hash of their id."""
    rows = docs.where(F.col(lang_col).isNotNull() & F.col(text_col).isNotNull()).select(F.xxhash64(F.col(id_col)).alias("h"), F.col(id_col).alias("id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    # the bound is found on ids alone, so that no text is sorted
    edge = rows.select("h").orderBy("h").limit(most).agg(F.max("h")).first()[0]
    if edge is None:
        return NaiveBayes([], np.zeros((1 << BITS, 0), np.float32), np.zeros(0))

    def fn(batch: pa.RecordBatch):
        totals: dict[str, list] = {}
        langs = batch.column(0).to_pylist()
        for at in range(0, len(langs), _ROWS):
            row, cell, n = batch_counts(batch.column(1).slice(at, _ROWS).to_pylist())
            edges = np.searchsorted(row, np.arange(_ROWS + 1))
            for i, lang in enumerate(langs[at : at + _ROWS]):
                got = totals.setdefault(lang, [0, np.zeros(1 << BITS, np.int64)])
                got[0] += 1
                got[1][cell[edges[i] : edges[i + 1]]] += n[edges[i] : edges[i + 1]]
        for lang, (n, cells) in totals.items():
            hit = np.flatnonzero(cells)
            at = np.concatenate(([-1], hit))
            yield batch_of({"lang": pa.array([lang] * len(at)), "cell": pa.array(at), "n": pa.array(np.concatenate(([n], cells[hit])))})

    found = map_arrow(rows.where(F.col("h") <= edge).select("lang", "text"), fn, "lang string, cell long, n long").groupBy("lang", "cell").agg(F.sum("n").alias("n"))
    langs = sorted(r[0] for r in found.where("cell = -1").select("lang").limit(MOST_LANGS + 1).collect())
    if len(langs) > MOST_LANGS:
        raise ValueError(f"more than {MOST_LANGS} languages")
    got = found.toPandas()
    counts, n_docs = np.zeros((1 << BITS, len(langs))), np.zeros(len(langs))
    col = got["lang"].map({x: i for i, x in enumerate(langs)}).to_numpy()
    cell, n = got["cell"].to_numpy(), got["n"].to_numpy()
    counts[cell[cell >= 0], col[cell >= 0]] = n[cell >= 0]
    n_docs[col[cell < 0]] = n[cell < 0]
    counts += 0.5
    return NaiveBayes(langs, np.log(counts / counts.sum(0)).astype(np.float32), np.log(n_docs / n_docs.sum()))


def predict(docs: DataFrame, model: NaiveBayes, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score): the likeliest language and its posterior probability; `und` and 0 if the text is null,
    has no letter, or nothing was learned."""
    spark = docs.sparkSession
    sent = spark.sparkContext.broadcast((model.langs, model.log_p, model.prior))

    def fn(batch: pa.RecordBatch):
        langs, log_p, prior = sent.value
        texts = ["" if t is None else t for t in batch.column(1).to_pylist()]
        lettered = np.array([any(map(str.isalpha, t)) for t in texts], bool)
        if langs:
            score = NaiveBayes(langs, log_p, prior).scores(texts)
            best = score.argmax(1)
            p = 1 / np.exp(score - score.max(1, keepdims=True)).sum(1)
            names = [langs[b] if ok else "und" for b, ok in zip(best, lettered, strict=True)]
            p = np.where(lettered, p, 0.0)
        else:
            names, p = ["und"] * len(texts), np.zeros(len(texts))
        yield batch_of({"doc_id": batch.column(0), "lang_pred": pa.array(names, pa.string()), "score": pa.array(p, pa.float64())})

    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return map_arrow(rows, fn, "doc_id long, lang_pred string, score double", 128)


def _fold(folds: int) -> Column:
    return F.crc32(F.col("doc_id").cast("string").cast("binary")) % folds


def identify_languages(docs: DataFrame, folds: int = 5, most: int = TRAIN_ROWS) -> DataFrame:
    """(doc_id, held_out, lang_pred, score) for every row of docs, learned from the rows whose crc32(doc_id) mod folds is
    not 0. Rows with a null id are never learned from and not held out. An empty table gives an empty result."""
    model = fit(docs.where(_fold(folds) != 0), most=most)
    return predict(docs, model).withColumn("held_out", F.coalesce(_fold(folds) == 0, F.lit(False))).select("doc_id", "held_out", "lang_pred", "score")


def keep_identified(docs: DataFrame, least: float = 0.5, folds: int = 5) -> DataFrame:
    """The rows of docs with a language found at a probability of `least` or more, columns unchanged. Each row is judged by
    its own text, whatever its id; null and empty texts and those without a letter go."""
    scratch = Scratch(docs.sparkSession, "language")
    rows, row = numbered(scratch, docs)
    found = predict(rows, fit(rows.where(_fold(folds) != 0)), id_col=row)
    return without(rows, row, found.where(~((F.col("lang_pred") != "und") & (F.col("score") >= least))).select(F.col("doc_id").alias("row")))
