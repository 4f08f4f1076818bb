"""Where rows live: a site is a column, never a machine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def assign_sites(df: DataFrame, key: str | None = None, n_sites: int = 10, seed: int = 0, by: str | None = None, weights: list[float] | None = None, min_rows: int = 0, uniform: Column | None = None) -> DataFrame:
    """df with ``site_id``: by the hash of key (even or by weights), or from a natural column.

    min_rows is a floor on the size of each site; it costs one count by site. uniform
    takes the place of the hash for weights: a number in [0, 1).
    """
    if by is not None:
        from pyspark.sql import Window

        # distinct values are few against rows; the join stays a shuffle where they are not
        names = df.select(by).distinct().withColumn("site_id", F.dense_rank().over(Window.orderBy(by)) - 1)
        out = df.join(names, df[by].eqNullSafe(names[by]), "left").drop(names[by])
    elif weights:
        total, at = sum(weights), 0.0
        u = F.pmod(F.xxhash64(F.col(key), F.lit(seed)), F.lit(1 << 30)) / float(1 << 30) if uniform is None else uniform
        site = F.lit(len(weights) - 1)
        ends = []
        for w in weights[:-1]:
            at += w / total
            ends.append(at)
        for i, end in reversed(list(enumerate(ends))):
            site = F.when(u < end, i).otherwise(site)
        out = df.withColumn("site_id", site)
    else:
        out = df.withColumn("site_id", F.pmod(F.xxhash64(F.col(key), F.lit(seed)), F.lit(n_sites)).cast("int"))
    if min_rows:
        small = out.groupBy("site_id").count().where(F.col("count") < min_rows).limit(1).collect()
        if small:
            raise ValueError(f"site {small[0][0]} has {small[0][1]} rows, fewer than {min_rows}")
    return out


def site_profile(df: DataFrame, vec: str = "vec") -> DataFrame:
    return df.groupBy("site_id").agg(F.count("*").alias("n_rows"), F.sum(4 * F.size(vec)).alias("vector_bytes"))


def check_vectors(df: DataFrame, dim: int, policy: str = "fail", vec: str = "vec") -> DataFrame:
    """Rows whose vector is null, of another size, or holds null or NaN: ``fail``, ``drop``, or ``quarantine`` (a column ``bad``)."""
    v = F.col(vec)
    bad = v.isNull() | (F.size(v) != dim) | F.exists(v, lambda x: x.isNull() | F.isnan(x.cast("double")))
    bad = F.coalesce(bad, F.lit(True))
    if policy == "drop":
        return df.where(~bad)
    if policy == "quarantine":
        return df.withColumn("bad", bad)
    if policy != "fail":
        raise ValueError(policy)
    return df.withColumn(vec, F.when(bad, F.raise_error(F.lit(f"bad vector, {dim} components wanted"))).otherwise(v))
