"""The ledger of transmitted bits, modelled and measured."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def training_bits(n_sites: int, n_params: int, n_rounds: int, word: int = 32) -> int:
    """Parameters down and gradients up, every round."""
    return n_sites * n_params * 2 * n_rounds * word


def code_bits(site_degrees: DataFrame, bits: int, degree_bits: int = 32) -> DataFrame:
    """One row ``code_bits``: each site's distinct codes with their counts."""
    return site_degrees.agg((F.count("*") * (degree_bits + bits)).alias("code_bits"))


def total_bits(n_sites: int, n_params: int, n_rounds: int, n_codes_by_site: list[int], bits: int, word: int = 32) -> int:
    """Training, the last broadcast, and codes."""
    return word * (2 * n_rounds + 1) * n_sites * n_params + sum(n_codes_by_site) * (32 + bits)


def bound_bits(n_sites: int, n_params: int, n_rounds: int, bits: int, rows_by_site: list[int] | None = None) -> int:
    """Upper bound: every site sends all codes; with rows_by_site no more than its rows."""
    sizes = [2**bits] * n_sites if rows_by_site is None else [min(2**bits, v) for v in rows_by_site]
    return total_bits(n_sites, n_params, n_rounds, sizes, bits)


def label_return_bits(n_codes_by_site: list[int], bits: int, k: int) -> int:
    """Clusters of codes back to the sites."""
    return sum(n_codes_by_site) * (bits + max(1, (k - 1).bit_length()))


def raw_bits(n_rows: int, dim: int, word: int = 32) -> int:
    return n_rows * dim * word


def to_megabytes(bits, unit: int = 10**6):
    return bits / 8 / unit


def baseline_bits(method: str, *, n_rows: int, dim: int, n_sites: int, k: int, passes: int = 10, models: int = 0, latent: int = 0, reps: int = 0, layouts: int = 10) -> int:
    """Words of 32 bits that each baseline moves."""
    per = {
        "central": n_rows * dim,
        "kmeans_parallel": passes * 2 * n_sites * k * dim,
        "partition_merge": n_sites * k * (dim + 1) + n_sites * k * dim,
        "density_representatives": reps * (dim + 1) * 2,
        "hashed_density_peaks": 2 * layouts * n_rows * dim,
        "subspace_models": models * (1 + dim + dim * latent + latent),
        "gaussian_models": models * (1 + dim + dim * (dim + 1) // 2),
        "grid": reps * (dim + 1),
    }
    return per[method] * 32


def cost_growth(points: DataFrame, x: str = "dim", y: str = "bits") -> DataFrame:
    """One row ``slope`` of log y over log x: 1 is linear."""
    return points.agg(F.regr_slope(F.log(F.col(y).cast("double")), F.log(F.col(x).cast("double"))).alias("slope"))


def megabytes(column: Column, unit: int = 10**6) -> Column:
    return column / 8 / unit


class Ledger:
    """Wall time by phase, and bytes that the driver knows it sent or got."""

    def __init__(self, spark: SparkSession):
        self.spark, self.seconds, self.bytes, self.sent, self.got = spark, {}, {}, 0, 0

    @contextmanager
    def timed(self, phase: str):
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[phase] = self.seconds.get(phase, 0.0) + time.perf_counter() - began

    def rounds(self, n_sites: int, n_params: int, n_rounds: int) -> None:
        self.sent += 4 * n_params * n_rounds * n_sites
        self.got += 4 * n_params * n_rounds * n_sites

    def rows_per_second(self, phase: str, rows: int) -> float:
        return rows / max(self.seconds.get(phase, 0.0), 1e-9)

    def moved(self) -> dict[str, int]:
        """Bytes that the application's executors have shuffled and read so far, as Spark's own status store counts them."""
        store = self.spark.sparkContext._jsc.sc().statusStore()
        rows = store.executorList(True)
        out = {"shuffle_read": 0, "shuffle_write": 0, "input": 0}
        for i in range(rows.size()):
            e = rows.apply(i)
            out["shuffle_read"] += e.totalShuffleRead()
            out["shuffle_write"] += e.totalShuffleWrite()
            out["input"] += e.totalInputBytes()
        return out

    @contextmanager
    def counted(self, phase: str):
        """Time a phase and keep what it moved in ``bytes``."""
        before = self.moved()
        with self.timed(phase):
            yield
        after = self.moved()
        self.bytes[phase] = {k: after[k] - before[k] for k in after}
