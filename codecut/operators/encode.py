"""Codes of all rows and their counts: vectors never leave the scan's stage."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.bits import pack_array
from ..functions.vectors import int_dot
from .features import Normalizer, matrix_of
from .network import EncoderSpec, forward


def encode(df: DataFrame, spec: EncoderSpec, params: np.ndarray, normalizer: Normalizer = Normalizer("none"), vec: str = "vec") -> DataFrame:
    """df without vec and with ``code`` (BIGINT, or an array of words beyond 64 bits); narrow."""
    others = [c for c in df.columns if c != vec]
    wide = spec.bits > 64
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema if f.name != vec)
    shared = df.sparkSession.sparkContext.broadcast(params)

    def run(batches):
        for b in batches:
            x = matrix_of(b.column(b.num_columns - 1))
            codes = pack_array(forward(spec, shared.value, normalizer.apply(x), "sign") > 0) if len(x) else np.zeros(0, np.int64)
            column = pa.array(list(codes), pa.list_(pa.int64())) if wide else pa.array(codes, pa.int64())
            yield pa.RecordBatch.from_arrays([*[b.column(i) for i in range(len(others))], column], names=[*others, "code"])

    return df.select(*others, vec).mapInArrow(run, f"{schema + ', ' if schema else ''}code {'array<bigint>' if wide else 'bigint'}")


def nearest_labels(codes: np.ndarray, known: np.ndarray, degrees: np.ndarray, labels: np.ndarray, block: int = 1 << 22) -> np.ndarray:
    """Label of the closest known code of each code; ties by larger degree, then smaller code."""
    order = np.lexsort((known, -degrees))
    known, labels = known[order].view(np.uint64), labels[order]
    out = np.zeros(len(codes), labels.dtype)
    step = max(1, block // max(1, len(known)))
    for lo in range(0, len(codes), step):
        out[lo : lo + step] = labels[np.bitwise_count(codes[lo : lo + step].view(np.uint64)[:, None] ^ known[None, :]).argmin(1)]
    return out


def encode_and_label(df: DataFrame, spec: EncoderSpec, params: np.ndarray, normalizer: Normalizer, codes: np.ndarray, degrees: np.ndarray, labels: np.ndarray, vec: str = "vec") -> DataFrame:
    """df without vec and with ``code`` and ``cluster`` in one narrow pass.

    A code has the label of the model, or of the model's nearest code. What is broadcast is 20 bytes a code of
    the model, which the caller bounds. Codes have at most 64 bits.
    """
    others = [c for c in df.columns if c != vec]
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema if f.name != vec)
    order = np.argsort(codes)
    shared = df.sparkSession.sparkContext.broadcast((params, codes[order], degrees[order], labels[order].astype(np.int32)))

    def run(batches):
        p, known, sizes, of = shared.value
        for b in batches:
            x = matrix_of(b.column(b.num_columns - 1))
            got = pack_array(forward(spec, p, normalizer.apply(x), "sign") > 0) if len(x) else np.zeros(0, np.int64)
            mine, back = np.unique(got, return_inverse=True)
            at = np.minimum(np.searchsorted(known, mine), max(0, len(known) - 1))
            cluster = of[at] if len(known) else np.zeros(len(mine), np.int32)
            new = np.flatnonzero(known[at] != mine) if len(known) else np.zeros(0, int)
            cluster[new] = nearest_labels(mine[new], known, sizes, of)
            yield pa.RecordBatch.from_arrays([*[b.column(i) for i in range(len(others))], pa.array(got, pa.int64()), pa.array(cluster[back.ravel()], pa.int32())], names=[*others, "code", "cluster"])

    return df.select(*others, vec).mapInArrow(run, f"{schema + ', ' if schema else ''}code bigint, cluster int")


def fixed_weight(bit: int, i: Column) -> Column:
    """Closed-form integer weights for codes that any engine computes alike."""
    return F.pmod((i + 1) * (bit * bit + 3 * bit + 7) + i * i * (bit + 5), F.lit(23)).cast("long") - 11


def _weights(places: Column, bit: int) -> Column:
    return F.transform(places, lambda i: fixed_weight(bit, i))


def encode_fixed(qvec: Column, dim: int, bits: int) -> Column:
    """The code of an integer vector by the closed-form linear map, as an expression: bit set where the sum is >= 0."""
    places = F.sequence(F.lit(0).cast("long"), F.lit(dim - 1).cast("long"))
    code = F.lit(0).cast("long")
    for b in range(bits):
        w = _weights(places, b)
        value = (1 << b) - (1 << 64) if b == 63 else 1 << b
        code = code.bitwiseOR(F.when(int_dot(qvec, w) >= 0, F.lit(value).cast("long")).otherwise(F.lit(0).cast("long")))
    return code


def site_degrees(encoded: DataFrame) -> DataFrame:
    """``site_id, code, degree``; counts combine at the sites before anything moves."""
    return encoded.groupBy("site_id", "code").agg(F.count("*").alias("degree"))


def merge_degrees(degrees: DataFrame) -> DataFrame:
    return degrees.groupBy("code").agg(F.sum("degree").alias("degree"))


def code_usage(degrees: DataFrame, bits: int) -> DataFrame:
    """Distinct codes, their share of all possible ones, and the entropy of their use, of merged degrees."""
    total = degrees.agg(F.sum("degree").alias("n"))
    p = F.col("degree") / F.col("n")
    return degrees.crossJoin(F.broadcast(total)).agg(F.count("*").alias("n_codes"), (F.count("*") / float(2.0**bits)).alias("share_of_codes"), F.sum(-p * F.log(p)).alias("entropy"))


def random_hyperplane_params(spec: EncoderSpec, seed: int) -> np.ndarray:
    """Parameters of a data-independent linear encoder."""
    rng = np.random.default_rng(seed)
    return np.concatenate([rng.normal(size=(spec.dim, spec.bits)).ravel(), np.zeros(spec.bits)])
