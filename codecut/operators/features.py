"""Vectors out of tables, and their normalization."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("none", "l2", "minmax", "zscore", "zscore_sqrt_dim")


def matrix_of(column: pa.Array) -> np.ndarray:
    """(rows, D) of a list column of equal sizes without nulls."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(float)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


@dataclass(frozen=True)
class Normalizer:
    """A frozen map of vectors; four numbers a dimension, whatever the rows."""

    kind: str
    mean: tuple[float, ...] = ()
    sd: tuple[float, ...] = ()
    low: tuple[float, ...] = ()
    high: tuple[float, ...] = ()

    def apply(self, x: np.ndarray) -> np.ndarray:
        if self.kind == "none" or not len(x):
            return x
        if self.kind == "l2":
            return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        if self.kind == "minmax":
            low, high = np.array(self.low), np.array(self.high)
            return (x - low) / np.where(high > low, high - low, 1)
        sd = np.array(self.sd)
        z = (x - np.array(self.mean)) / np.where(sd > 1e-12, sd, 1)
        return z / np.sqrt(x.shape[1]) if self.kind == "zscore_sqrt_dim" else z


def _sums(batches):
    state = None
    for batch in batches:
        x = matrix_of(batch.column(0))
        if not len(x):
            continue
        new = [x.sum(0), (x * x).sum(0), x.min(0), x.max(0)]
        n = len(x)
        state = [n, *new] if state is None else [state[0] + n, state[1] + new[0], state[2] + new[1], np.minimum(state[3], new[2]), np.maximum(state[4], new[3])]
    if state is not None:
        yield pa.RecordBatch.from_arrays([pa.array([state[0]], pa.int64()), *[pa.array([v.tolist()], pa.list_(pa.float64())) for v in state[1:]]], names=["n", "s", "q", "lo", "hi"])


def fit_normalizer(df: DataFrame, kind: str = "zscore_sqrt_dim", vec: str = "vec") -> Normalizer:
    """One pass; each task sends one row of sums."""
    if kind not in KINDS:
        raise ValueError(kind)
    if kind in ("none", "l2"):
        return Normalizer(kind)
    parts = df.select(vec).mapInArrow(_sums, "n long, s array<double>, q array<double>, lo array<double>, hi array<double>")
    at = parts.select("n", F.posexplode(F.arrays_zip("s", "q", "lo", "hi")).alias("i", "x"))
    rows = at.groupBy("i").agg(F.sum("n").alias("n"), F.sum("x.s").alias("s"), F.sum("x.q").alias("q"), F.min("x.lo").alias("lo"), F.max("x.hi").alias("hi")).orderBy("i").collect()
    mean = [r["s"] / r["n"] for r in rows]
    sd = [max(r["q"] / r["n"] - m * m, 0.0) ** 0.5 for r, m in zip(rows, mean)]
    return Normalizer(kind, tuple(mean), tuple(sd), tuple(r["lo"] for r in rows), tuple(r["hi"] for r in rows))


def normalize(df: DataFrame, stats: Normalizer, vec: str = "vec") -> DataFrame:
    """df with vec normalized, in expressions that stay in the JVM."""
    v = F.transform(vec, lambda x: x.cast("double"))
    if stats.kind == "none":
        return df
    if stats.kind == "l2":
        n = F.greatest(F.sqrt(F.aggregate(v, F.lit(0.0), lambda a, x: a + x * x)), F.lit(1e-12))
        return df.withColumn(vec, F.transform(v, lambda x: x / n))
    lit = lambda xs: F.array(*[F.lit(float(x)) for x in xs])
    if stats.kind == "minmax":
        shift, scale = stats.low, [h - lo if h > lo else 1.0 for lo, h in zip(stats.low, stats.high)]
    else:
        by = len(stats.mean) ** 0.5 if stats.kind == "zscore_sqrt_dim" else 1.0
        shift, scale = stats.mean, [by * (s if s > 1e-12 else 1.0) for s in stats.sd]
    return df.withColumn(vec, F.zip_with(F.zip_with(v, lit(shift), lambda x, m: x - m), lit(scale), lambda x, s: x / s))


def _ngrams(n: int, dim: int):
    def run(batches):
        for batch in batches:
            out = np.zeros((batch.num_rows, dim), np.float32)
            for r, text in enumerate(batch.column(1).to_pylist()):
                points = np.frombuffer((text or "").encode("utf-32-le"), np.uint32).astype(np.uint64)
                if len(points) >= n:
                    h = points[: len(points) - n + 1].copy()
                    for j in range(1, n):
                        h = h * np.uint64(1_000_003) + points[j : len(points) - n + 1 + j]
                    out[r] = np.bincount((h % np.uint64(dim)).astype(np.int64), minlength=dim)
            out /= np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-12)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.FixedSizeListArray.from_arrays(pa.array(out.ravel()), dim).cast(pa.list_(pa.float32()))], names=["row_id", "vec"])

    return run


def char_ngram_vectors(df: DataFrame, key: str, text: str, n: int = 1, dim: int = 64) -> DataFrame:
    """``row_id, vec``: hashed counts of runs of n characters, of length 1."""
    return df.select(F.col(key).cast("long").alias("row_id"), F.col(text).cast("string").alias("t")).mapInArrow(_ngrams(n, dim), "row_id long, vec array<float>")


def char_counts_sql(text: Column, dim: int) -> Column:
    """Counts of characters by code point modulo dim, as an expression."""
    each = F.transform(F.split(text, ""), lambda c: F.when(c == "", None).otherwise(F.expr("0") + F.ascii(c) % dim))
    return F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda b: F.size(F.filter(each, lambda x: x == b)))


def word_vectors(df: DataFrame, key: str, text: str, dim: int = 256, idf: bool = True) -> DataFrame:
    """``row_id, vec``: hashed word counts, weighted by inverse document frequency if asked."""
    from pyspark.ml.feature import IDF, HashingTF
    from pyspark.ml.functions import vector_to_array

    words = df.select(F.col(key).cast("long").alias("row_id"), F.split(F.lower(F.coalesce(F.col(text), F.lit(""))), r"\s+").alias("w"))
    out = HashingTF(numFeatures=dim, inputCol="w", outputCol="v").transform(words)
    if idf:
        out = IDF(inputCol="v", outputCol="u").fit(out).transform(out).drop("v").withColumnRenamed("u", "v")
    return out.select("row_id", vector_to_array("v", "float32").alias("vec"))


def text_shape(df: DataFrame, key: str, text: str) -> DataFrame:
    """``row_id`` and length, words, lines, distinct lines, digit and punctuation counts."""
    t = F.coalesce(F.col(text), F.lit(""))
    lines = F.split(t, "\n")
    return df.select(F.col(key).cast("long").alias("row_id"), F.length(t).alias("n_chars"), F.size(F.array_remove(F.split(t, r"[ \t\n\r]+"), "")).alias("n_words"), F.size(lines).alias("n_lines"), F.size(F.array_distinct(lines)).alias("n_distinct_lines"), F.regexp_count(t, F.lit("[0-9]")).alias("n_digits"), F.regexp_count(t, F.lit("[.,;:!?]")).alias("n_marks"))


def html_features(pages: DataFrame) -> DataFrame:
    """``row_id``, counts of tags and links, size of the text, host, and the language that the markup names."""
    h = F.coalesce(F.col("html"), F.lit(""))
    return pages.select(F.col("page_id").cast("long").alias("row_id"), F.regexp_count(h, F.lit("<[a-z]")).alias("n_tags"), F.regexp_count(h, F.lit("<a ")).alias("n_links"), F.length(F.regexp_replace(h, "<[^>]*>", "")).alias("text_chars"), F.regexp_extract("url", r"^[a-z]+://([^/?#]*)", 1).alias("host"), F.regexp_extract(h, 'lang="([a-z]+)"', 1).alias("lang"))


def json_number(column: Column, path: str) -> Column:
    return F.get_json_object(column, path).cast("double")


def profile(df: DataFrame, by: str, pivot: str, values: str, kinds: list[str]) -> DataFrame:
    """``row_id, vec``: count, mean and deviation of values for each kind (the kinds are given, so no pass looks for them)."""
    x = lambda k: F.when(F.col(pivot) == k, F.col(values))
    parts = [c for k in kinds for c in (F.count(x(k)).cast("double"), F.coalesce(F.avg(x(k)), F.lit(0.0)), F.coalesce(F.stddev_pop(x(k)), F.lit(0.0)))]
    return df.groupBy(F.col(by).cast("long").alias("row_id")).agg(F.array(*parts).alias("vec"))


def one_hot(column: Column, values: list) -> Column:
    return F.array(*[(column.eqNullSafe(F.lit(v))).cast("double") for v in values])


def bucketize(column: Column, cuts: list[float]) -> Column:
    """How many of the ascending cuts a value reaches."""
    return sum(((column >= c).cast("int") for c in cuts), F.lit(0))


def quantile_bucket(df: DataFrame, column: str, n: int, out: str = "bucket") -> DataFrame:
    """Buckets between exact-enough quantiles of the whole column."""
    cuts = df.approxQuantile(column, [i / n for i in range(1, n)], 0.001)
    return df.withColumn(out, bucketize(F.col(column), sorted(set(cuts))))


def projection_matrix(dim: int, to: int, seed: int = 0) -> np.ndarray:
    return np.random.default_rng(seed).normal(0, 1 / np.sqrt(to), (dim, to))


def project(df: DataFrame, to: int, kind: str = "random", seed: int = 0, dim: int | None = None, vec: str = "vec") -> DataFrame:
    """df(row_id, vec) with vec reduced to ``to`` components: random, or the principal ones."""
    if kind == "pca":
        from pyspark.ml.feature import PCA
        from pyspark.ml.functions import array_to_vector, vector_to_array

        v = df.withColumn("_v", array_to_vector(F.col(vec).cast("array<double>")))
        return PCA(k=to, inputCol="_v", outputCol="_p").fit(v).transform(v).withColumn(vec, vector_to_array("_p")).drop("_v", "_p")
    m = df.sparkSession.sparkContext.broadcast(projection_matrix(dim or len(df.first()[vec]), to, seed))

    def run(batches):
        for b in batches:
            y = matrix_of(b.column(1)) @ m.value
            yield pa.RecordBatch.from_arrays([b.column(0), pa.FixedSizeListArray.from_arrays(pa.array(y.ravel()), to).cast(pa.list_(pa.float64()))], names=["row_id", "vec"])

    return df.select("row_id", vec).mapInArrow(run, "row_id long, vec array<double>")


def planted_vectors(df: DataFrame, category: str, key: str, dim: int = 64, jitter: float = 1.0) -> DataFrame:
    """``row_id, vec, truth``: an integer center for each category (from its own bytes) and bounded jitter from the key.

    Category and key count by their remainders only, so the 17 * 201 vectors are made once, in expressions, and each row looks its own up.
    """
    c, k = F.crc32(F.col(category).cast("string").cast("binary")), F.col(key).cast("long")
    at = F.pmod(F.pmod(c, F.lit(1_000_003)), F.lit(17)) * 201 + F.pmod(k + 1, F.lit(201))
    kind = F.col("_kind")
    center = lambda i: F.pmod(F.floor(kind / 201) * (i * i + 7 * i + 13) + i * 7919, F.lit(17)).cast("double") - 8
    noise = lambda i: (F.pmod(F.pmod(kind, F.lit(201)) * (i * 31 + 17) + i * i * 11, F.lit(201)).cast("double") - 100) / 100 * jitter
    vec = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(dim - 1).cast("long")), lambda i: center(i) + noise(i))
    table = df.sparkSession.range(17 * 201).select(F.col("id").alias("_kind"), vec.alias("vec"))
    named = df.select(k.alias("row_id"), at.alias("_kind"), F.col(category).alias("truth"))
    none = F.array_repeat(F.lit(None).cast("double"), dim)
    return named.join(F.broadcast(table), "_kind", "left").select("row_id", F.coalesce("vec", none).alias("vec"), "truth")
