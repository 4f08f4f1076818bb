"""Accuracy and convergence measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

AVERAGES = ("geometric", "arithmetic", "max", "min", "printed_product")


def contingency(df: DataFrame, cluster: str = "cluster", truth: str = "truth", count: str | None = None) -> DataFrame:
    """Rows by cluster and class; with ``count`` a row stands for as many."""
    return df.groupBy(F.col(cluster).alias("cluster"), F.col(truth).alias("truth")).agg((F.sum(count) if count else F.count("*")).alias("n"))


def purity(df: DataFrame, cluster: str = "cluster", truth: str = "truth", count: str | None = None) -> DataFrame:
    """Rows in the largest class of their cluster, as a share; from the majority's share to 1."""
    best = contingency(df, cluster, truth, count).groupBy("cluster").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    return best.agg((F.sum("top") / F.sum("n")).alias("purity"))


def entropy_terms(df: DataFrame, cluster: str = "cluster", truth: str = "truth", count: str | None = None) -> DataFrame:
    """One row ``n, h_cluster, h_truth, mutual``, natural logarithms; all sums are over the small table of cells."""
    cells = contingency(df, cluster, truth, count)
    c = cells.groupBy("cluster").agg(F.sum("n").alias("nc"))
    t = cells.groupBy("truth").agg(F.sum("n").alias("nt"))
    whole = cells.agg(F.sum("n").alias("n_all"))
    h = lambda df, col: df.crossJoin(F.broadcast(whole)).agg(F.sum(-(F.col(col) / F.col("n_all")) * F.log(F.col(col) / F.col("n_all"))).alias("h"))
    joined = cells.join(c, cells["cluster"].eqNullSafe(c["cluster"])).drop(c["cluster"]).join(t, cells["truth"].eqNullSafe(t["truth"])).drop(t["truth"]).crossJoin(F.broadcast(whole))
    mi = joined.agg(F.max("n_all").alias("n"), F.sum(F.col("n") / F.col("n_all") * F.log(F.col("n") * F.col("n_all") / (F.col("nc") * F.col("nt")))).alias("mutual"))
    return mi.crossJoin(h(c, "nc").select(F.col("h").alias("h_cluster"))).crossJoin(h(t, "nt").select(F.col("h").alias("h_truth"))).select("n", "h_cluster", "h_truth", "mutual")


def nmi(df: DataFrame, cluster: str = "cluster", truth: str = "truth", average: str = "geometric", count: str | None = None) -> DataFrame:
    """One row ``nmi``. Two trivial partitions agree (1), one trivial against another does not (0)."""
    a, b = F.col("h_cluster"), F.col("h_truth")
    by = {"geometric": F.sqrt(a * b), "arithmetic": (a + b) / 2, "max": F.greatest(a, b), "min": F.least(a, b), "printed_product": a * b}[average]
    none = F.lit(1e-12)
    value = F.when((a < none) & (b < none), 1.0).when((a < none) | (b < none), 0.0).otherwise(F.col("mutual") / by)
    return entropy_terms(df, cluster, truth, count).select(value.alias("nmi"))


def pair_scores(df: DataFrame, cluster: str = "cluster", truth: str = "truth") -> DataFrame:
    """One row of pair counts, pair F1 and the adjusted Rand index."""
    cells = contingency(df, cluster, truth)
    pairs = lambda col: F.sum(F.col(col).cast("double") * (F.col(col) - 1) / 2)
    both = cells.agg(pairs("n").alias("both"), F.sum("n").alias("n"))
    c = cells.groupBy("cluster").agg(F.sum("n").alias("m")).agg(pairs("m").alias("same_cluster"))
    t = cells.groupBy("truth").agg(F.sum("n").alias("m")).agg(pairs("m").alias("same_truth"))
    row = both.crossJoin(c).crossJoin(t)
    every = F.col("n").cast("double") * (F.col("n") - 1) / 2
    expected = F.col("same_cluster") * F.col("same_truth") / every
    top = (F.col("same_cluster") + F.col("same_truth")) / 2
    return row.select("n", "both", "same_cluster", "same_truth", (2 * F.col("both") / (F.col("same_cluster") + F.col("same_truth"))).alias("pair_f1"), F.when(top == expected, 1.0).otherwise((F.col("both") - expected) / (top - expected)).alias("adjusted_rand"))


def relative_error_ratio(history: DataFrame) -> DataFrame:
    """history(run, round, loss) with ``rer`` = (loss - least) / (largest - least) of the run; 0 where they are equal."""
    w = Window.partitionBy("run")
    low, high = F.min("loss").over(w), F.max("loss").over(w)
    return history.withColumn("rer", F.when(high == low, 0.0).otherwise((F.col("loss") - low) / (high - low)))


def rounds_to(history: DataFrame, eps: float) -> DataFrame:
    """``run, rounds``: the first round whose ratio is at most eps."""
    return relative_error_ratio(history).where(F.col("rer") <= eps).groupBy("run").agg(F.min("round").alias("rounds"))
