"""User functions for the SQL front end: expressions where possible, table functions where rows are made."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


class _Neighbors:
    def eval(self, code: int, n_bits: int, radius: int):
        for r in range(radius + 1):
            for at in combinations(range(n_bits), r):
                out = code
                for b in at:
                    out ^= 1 << b if b < 63 else -(1 << 63)
                yield (out,)


class _Ngrams:
    def eval(self, text: str, n: int):
        text = text or ""
        for i in range(len(text) - n + 1):
            yield (i, text[i : i + n])


class _Bands:
    def eval(self, code: int, n_bits: int, bands: int):
        value = code & ((1 << 64) - 1)
        cuts = [int(x) for x in np.linspace(0, n_bits, bands + 1)]
        for i, (lo, hi) in enumerate(zip(cuts, cuts[1:])):
            yield (i, value >> lo & ((1 << (hi - lo)) - 1))


def _row(**kinds) -> T.StructType:
    return T.StructType([T.StructField(n, k) for n, k in kinds.items()])


# types as objects: workers import this module and have no session to parse them
code_neighbors = F.udtf(_Neighbors, returnType=_row(neighbor=T.LongType()))
char_ngrams = F.udtf(_Ngrams, returnType=_row(pos=T.IntegerType(), gram=T.StringType()))
bit_bands = F.udtf(_Bands, returnType=_row(band=T.IntegerType(), value=T.LongType()))
_VECTOR = T.ArrayType(T.DoubleType())

_SQL = {
    "hamming(a BIGINT, b BIGINT) RETURNS INT": "bit_count(a ^ b)",
    "code_l1(a BIGINT, b BIGINT) RETURNS INT": "2 * bit_count(a ^ b)",
    "vec_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
    "vec_l2(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
    "pack_bits(bits ARRAY<INT>) RETURNS BIGINT": "aggregate(transform(bits, (x, i) -> shiftleft(CAST(x AS BIGINT), i)), 0L, (s, x) -> s | x)",
}


def register(spark: SparkSession) -> None:
    """hamming, code_l1, vec_dot, vec_l2, pack_bits as SQL functions; code_neighbors, char_ngrams, bit_bands as table functions."""
    for head, body in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("code_neighbors", code_neighbors)
    spark.udtf.register("char_ngrams", char_ngrams)
    spark.udtf.register("bit_bands", bit_bands)


def encode_udf(model) -> Column:
    """A vectorized function from vectors to codes of a fitted model (at most 64 bits)."""
    from ..operators.network import forward
    from .bits import pack_array

    spec, theta, normalizer = model.spec, model.theta, model.normalizer

    @F.pandas_udf(T.LongType())
    def run(vec: pd.Series) -> pd.Series:
        x = np.stack(vec.to_numpy()).astype(float) if len(vec) else np.zeros((0, spec.dim))
        return pd.Series(pack_array(forward(spec, theta, normalizer.apply(x), "sign") > 0)) if len(vec) else pd.Series([], dtype="int64")

    return run


def normalize_udf(normalizer) -> Column:
    @F.pandas_udf(_VECTOR)
    def run(vec: pd.Series) -> pd.Series:
        return pd.Series(list(normalizer.apply(np.stack(vec.to_numpy()).astype(float)))) if len(vec) else vec

    return run


@F.pandas_udf(_VECTOR)
def mean_vector(vec: pd.Series) -> list:
    """Mean of a group's vectors; groups have to fit a task (posexplode and avg do not need that)."""
    return np.stack(vec.to_numpy()).astype(float).mean(0).tolist()


@F.pandas_udf(_VECTOR)
def vector_sum(vec: pd.Series) -> list:
    return np.stack(vec.to_numpy()).astype(float).sum(0).tolist()


@F.pandas_udf(T.LongType())
def medoid_code(code: pd.Series) -> int:
    """The code of a group with the smallest sum of differing bits, the smallest such code."""
    kinds, n = np.unique(code.to_numpy(), return_counts=True)
    d = np.bitwise_count((kinds[:, None] ^ kinds[None, :]).view(np.uint64)) @ n
    return int(kinds[int(d.argmin())])
