"""Functions of the codecs for SQL: scalar ones over Arrow batches, an aggregate, and table functions."""

from __future__ import annotations

import zlib
from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..kernels import codes
from ..kernels import deflate as df
from ..kernels import newick as nw


# types as objects: names would need a running session when the module is imported
_KINDS = {"boolean": T.BooleanType(), "string": T.StringType(), "binary": T.BinaryType()}


def _row(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


def _scalar(fn, kind: str):
    @F.pandas_udf(_KINDS[kind])
    def run(x: pd.Series) -> pd.Series:
        return x.map(lambda v: None if v is None else fn(v))

    return run


def _raw_deflate(data: bytes, level: int = 6) -> bytes:
    pack = zlib.compressobj(level, zlib.DEFLATED, -15)
    return pack.compress(bytes(data)) + pack.flush()


newick_valid = _scalar(lambda x: nw.error_of(x) is None, "boolean")
canonical_newick = _scalar(lambda x: nw.canonical(nw.parse(x)), "string")
packed_bits_encode = _scalar(lambda x: codes.packed_bits_encode(bytes(x)), "binary")
packed_ids_encode = _scalar(lambda x: codes.packed_ids_encode(np.asarray(x), True), "binary")
textrun_bits_encode = _scalar(codes.textrun_bits_encode, "string")
textrun_ids_encode = _scalar(codes.textrun_ids_encode, "string")
textrun_bits_decode = _scalar(codes.textrun_bits_decode, "string")
deflate = _scalar(_raw_deflate, "binary")
inflate = _scalar(lambda x: zlib.decompress(bytes(x), -15), "binary")
own_deflate = _scalar(lambda x: df.deflate_blocks(df.lz77_tokens(bytes(x)))[0], "binary")
own_inflate = _scalar(lambda x: df.inflate_blocks(bytes(x)), "binary")


@F.pandas_udf(T.BinaryType())
def packed_bits_decode(code: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([None if c is None else codes.packed_bits_decode(bytes(c), int(k))[0] for c, k in zip(code, n, strict=True)])


@F.pandas_udf(T.ArrayType(T.IntegerType()))
def packed_ids_decode(code: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([None if c is None else codes.packed_ids_decode(bytes(c), int(k), 0, True)[0].tolist() for c, k in zip(code, n, strict=True)])


@F.pandas_udf(T.BinaryType())
def support_pack(ids: pd.Series) -> bytes:
    """Aggregate: code of a group's ids, whatever their order. A group is a cluster in one block."""
    return codes.packed_ids_encode(np.sort(ids.to_numpy()), True)


@F.udtf(returnType=_row(node_id=T.IntegerType(), parent_id=T.IntegerType(), card=T.IntegerType(), label=T.StringType(), length_lex=T.StringType()))
class NewickNodes:
    def eval(self, text: str):
        t = nw.parse(text)
        for i in range(len(t.label)):
            yield i, t.parent[i], t.last[i] - t.first[i] + 1, t.label[i], t.length[i]


@F.udtf(returnType=_row(literal=T.IntegerType(), length=T.IntegerType(), distance=T.IntegerType()))
class Lz77Tokens:
    def eval(self, data: bytes):
        yield from df.lz77_tokens(bytes(data))


@F.udtf(returnType=_row(symbol=T.IntegerType(), n=T.LongType(), code_length=T.IntegerType()))
class HuffmanTable:
    def eval(self, data: bytes):
        counts = Counter(bytes(data))
        for symbol, length in sorted(df.huffman_lengths(counts).items()):
            yield symbol, counts[symbol], length


SCALARS = {"newick_valid": newick_valid, "canonical_newick": canonical_newick, "packed_bits_encode": packed_bits_encode, "packed_bits_decode": packed_bits_decode, "packed_ids_encode": packed_ids_encode, "packed_ids_decode": packed_ids_decode, "textrun_bits_encode": textrun_bits_encode, "textrun_ids_encode": textrun_ids_encode, "textrun_bits_decode": textrun_bits_decode, "deflate": deflate, "inflate": inflate, "own_deflate": own_deflate, "own_inflate": own_inflate, "support_pack": support_pack}
TABLES = {"newick_nodes": NewickNodes, "lz77_tokens": Lz77Tokens, "huffman_table": HuffmanTable}


def register(spark: SparkSession) -> None:
    for name, fn in SCALARS.items():
        spark.udf.register(name, fn)
    for name, fn in TABLES.items():
        spark.udtf.register(name, fn)
