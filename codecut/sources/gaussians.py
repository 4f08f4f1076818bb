"""Synthetic data: Gaussian clusters on random low-dimensional subspaces, and noisy waveforms."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition


def subspace_cluster(dim: int, latent_dim: int, n: int, seed, log_base: float = 2.0) -> np.ndarray:
    """(n, dim): a random map of unit Frobenius norm, a uniform shift of +-20 / log(dim), noise of variance 1 / (10 dim)."""
    rng = np.random.default_rng(seed)
    t = rng.normal(size=(dim, latent_dim))
    t /= np.linalg.norm(t)
    reach = 20 / math.log(dim, log_base)
    u = rng.uniform(-reach, reach, dim)
    return rng.normal(size=(n, latent_dim)) @ t.T + u + rng.normal(0, math.sqrt(1 / (10 * dim)), (n, dim))


def subspace_plan(j: int, per_latent: int = 20) -> list[tuple[int, int]]:
    """(cluster, latent dimensions) of the j-th data set: dimension 2**(j + 5), latent 2 to the whole, per_latent clusters each."""
    return [(i * per_latent + c, 2 ** (i + 1)) for i in range(j + 5) for c in range(per_latent)]


def _rows(dim: int, clusters: list[tuple[int, int]], per_cluster: int, seed: int):
    for cluster, latent in clusters:
        x = subspace_cluster(dim, latent, per_cluster, [seed, dim, cluster]).astype(np.float32)
        ids = np.arange(per_cluster, dtype=np.int64) + cluster * per_cluster
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.FixedSizeListArray.from_arrays(pa.array(x.ravel()), dim).cast(pa.list_(pa.float32())), pa.array(np.full(per_cluster, cluster, np.int32)), pa.array(np.full(per_cluster, latent, np.int32))], names=["row_id", "vec", "truth", "latent_dim"])


SCHEMA = "row_id long, vec array<float>, truth int, latent_dim int"


def subspace_dataset(spark: SparkSession, j: int, per_latent: int = 20, per_cluster: int = 2500, seed: int = 0) -> DataFrame:
    """The j-th data set, made in parallel, a seed for each cluster: the same rows in any partitioning."""
    dim, plan = 2 ** (j + 5), subspace_plan(j, per_latent)
    todo = spark.createDataFrame(plan, "cluster int, latent int").repartition(min(len(plan), 64))

    def run(batches):
        for b in batches:
            yield from _rows(dim, list(zip(b.column(0).to_pylist(), b.column(1).to_pylist())), per_cluster, seed)

    return todo.mapInArrow(run, SCHEMA)


def waveform_noise(n: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """(n, 40) features and classes 0 to 2: convex mixtures of two of three triangular waves, with noise on all features."""
    rng = np.random.default_rng(seed)
    at = np.arange(1, 22)
    wave = [np.maximum(6 - np.abs(at - c), 0) for c in (7, 15, 11)]
    pairs = ((0, 1), (0, 2), (1, 2))
    y = rng.integers(0, 3, n)
    u = rng.random(n)[:, None]
    a = np.stack([wave[pairs[c][0]] for c in range(3)])[y]
    b = np.stack([wave[pairs[c][1]] for c in range(3)])[y]
    x = np.zeros((n, 40))
    x[:, :21] = u * a + (1 - u) * b
    return x + rng.normal(size=(n, 40)), y


def waveform_dataset(spark: SparkSession, n: int = 5000, seed: int = 0, block: int = 1000) -> DataFrame:
    """``row_id, vec, truth``."""

    def run(batches):
        for b in batches:
            for lo in b.column(0).to_pylist():
                size = min(block, n - lo)
                x, y = waveform_noise(size, seed * 1_000_003 + lo)
                yield pa.RecordBatch.from_arrays([pa.array(np.arange(lo, lo + size)), pa.array(list(x.astype(np.float32)), pa.list_(pa.float32())), pa.array(y.astype(np.int32))], names=["row_id", "vec", "truth"])

    return spark.range(0, n, block).mapInArrow(run, "row_id long, vec array<float>, truth int")


class _Part(InputPartition):
    def __init__(self, dim, clusters):
        super().__init__(0)
        self.dim, self.clusters = dim, clusters


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.dim = int(options.get("dim", 64))
        self.per_cluster = int(options.get("per_cluster", 100))
        self.per_latent = int(options.get("per_latent", 2))
        self.seed = int(options.get("seed", 0))

    def partitions(self):
        plan = subspace_plan(int(math.log2(self.dim)) - 5, self.per_latent)
        return [_Part(self.dim, plan[i::8]) for i in range(min(8, len(plan)))]

    def read(self, partition):
        yield from _rows(partition.dim, partition.clusters, self.per_cluster, self.seed)


class _Stream(DataSourceStreamReader):
    """One more cluster an offset, up to ``clusters`` of them."""

    def __init__(self, options):
        self.inner = _Reader(options)
        self.plan = subspace_plan(int(math.log2(self.inner.dim)) - 5, self.inner.per_latent)

    def initialOffset(self):
        return {"cluster": 0}

    def latestOffset(self):
        return {"cluster": len(self.plan)}

    def partitions(self, start, end):
        return [_Part(self.inner.dim, [self.plan[i]]) for i in range(start["cluster"], end["cluster"])]

    def read(self, partition):
        yield from _rows(partition.dim, partition.clusters, self.inner.per_cluster, self.inner.seed)


class SubspaceGaussians(DataSource):
    """``format("subspace_gaussians")`` with options dim, per_cluster, per_latent, seed; batch and streaming."""

    @classmethod
    def name(cls):
        return "subspace_gaussians"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return _Reader(self.options)

    def streamReader(self, schema):
        return _Stream(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(SubspaceGaussians)
