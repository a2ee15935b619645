"""Functions for SQL: scalar functions over Arrow batches, an aggregate and table functions."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..operators import bits as b
from ..operators.curve import fit_double_exponential
from ..operators.value_codecs import unpack_map
from .hashing import hash_array


@pandas_udf(T.BooleanType())
def bloom_may_contain(words: pd.Series, idx: pd.Series, k: pd.Series, m: pd.Series, seed: pd.Series) -> pd.Series:
    """Hashes of a whole batch at once, for each seed that it holds; a row looks only its own bits up."""
    keys, size, hashes, seeds = (x.to_numpy(np.int64) for x in (idx, m, k, seed))
    hit = np.ones(len(keys), bool)
    for s in np.unique(seeds).tolist():
        for j in range(int(hashes[seeds == s].max(initial=0))):
            left = np.flatnonzero(hit & (seeds == s) & (hashes > j))
            pos = hash_array(keys[left], j, s) % size[left]
            word = np.fromiter((words.iat[i][p] for i, p in zip(left.tolist(), (pos // 64).tolist(), strict=True)), np.int64, len(left))
            hit[left] = (word >> (pos % 64)) & 1 == 1
    return pd.Series(hit)


@pandas_udf(T.BinaryType())
def deflate_floats(values: pd.Series) -> pd.Series:
    return values.map(lambda v: None if v is None else zlib.compress(np.asarray(v, "<f4").tobytes()))


@pandas_udf(T.ArrayType(T.FloatType()))
def inflate_floats(data: pd.Series) -> pd.Series:
    return data.map(lambda x: None if x is None else np.frombuffer(zlib.decompress(x), "<f4"))


@pandas_udf(T.ArrayType(T.IntegerType()))
def unpack_ranks(data: pd.Series, n: pd.Series) -> pd.Series:
    return pd.Series([unpack_map(x, int(k)).astype(np.int32) for x, k in zip(data, n, strict=True)])


@pandas_udf(T.ArrayType(T.FloatType()))
def half_cast(values: pd.Series) -> pd.Series:
    return values.map(lambda v: None if v is None else np.asarray(v, np.float16).astype(np.float32))


@pandas_udf(T.BinaryType())
def huffman_encode(symbols: pd.Series) -> pd.Series:
    """Code lengths of all 256 symbols, the count, then the bits."""

    def one(x):
        x = np.asarray(x, np.int64)
        freqs = dict(zip(*(c.tolist() for c in np.unique(x, return_counts=True)), strict=True))
        lengths = b.prefix_lengths(freqs) if freqs else {}
        return bytes(lengths.get(s, 0) for s in range(256)) + len(x).to_bytes(4, "little") + (b.huffman_encode(x, b.huffman_code(freqs))[0] if freqs else b"")

    return symbols.map(one)


@pandas_udf(T.ArrayType(T.IntegerType()))
def huffman_decode(data: pd.Series) -> pd.Series:
    from ..operators.index_codecs import canonical

    def one(x):
        lengths = {s: n for s, n in enumerate(x[:256]) if n}
        return b.huffman_decode(x[260:], canonical(lengths), int.from_bytes(x[256:260], "little")).astype(np.int32) if lengths else np.zeros(0, np.int32)

    return data.map(one)


@pandas_udf(T.ArrayType(T.DoubleType()))
def double_exp_fit(rank: pd.Series, value: pd.Series) -> list[float]:
    """Aggregate: the four numbers of a group's curve by rank; null for fewer than five points."""
    y = value.to_numpy()[np.argsort(rank.to_numpy())]
    return fit_double_exponential(y).tolist() if len(y) >= 5 else None


@udtf(returnType=T.StructType([T.StructField("idx", T.LongType())]))
class RunExpand:
    """The ones of alternating runs: (first symbol, lengths)."""

    def eval(self, first: int, lengths: list) -> Iterator[tuple]:
        at, symbol = 0, first
        for n in lengths:
            if symbol:
                yield from ((i,) for i in range(at, at + n))
            at, symbol = at + n, 1 - symbol


@udtf(returnType=T.StructType([T.StructField("symbol", T.IntegerType()), T.StructField("code", T.StringType())]))
class HuffmanCodes:
    def eval(self, symbols: list, freqs: list) -> Iterator[tuple]:
        yield from sorted(b.huffman_code(dict(zip(symbols, freqs, strict=True))).items())


@udtf(returnType=T.StructType([T.StructField("idx", T.LongType()), T.StructField("value", T.DoubleType())]))
class DecodeBitmapFloats:
    """A container of a bitmap (d bits) and 32-bit floats."""

    def eval(self, d: int, keys: bytes, values: bytes) -> Iterator[tuple]:
        idx = np.flatnonzero(np.unpackbits(np.frombuffer(keys, np.uint8), count=d))
        yield from zip(idx.tolist(), np.frombuffer(values, "<f4").astype(float).tolist(), strict=True)


def bloom_words(pos: str = "pos") -> tuple:
    """Grouping key and aggregate of a filter's words over bit positions."""
    return F.expr(f"{pos} div 64").alias("word_no"), F.bit_or(F.expr(f"shiftleft(1L, CAST({pos} % 64 AS INT))")).alias("word")


def register(spark: SparkSession) -> None:
    for f in (bloom_may_contain, deflate_floats, inflate_floats, unpack_ranks, half_cast, huffman_encode, huffman_decode, double_exp_fit):
        spark.udf.register(f.__name__, f)
    for name, f in (("run_expand", RunExpand), ("huffman_codes", HuffmanCodes), ("decode_container", DecodeBitmapFloats)):
        spark.udtf.register(name, f)
