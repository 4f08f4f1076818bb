"""Batches whose samples differ, from bounded candidate pools."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def uniform_batch(n: int, size: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).permutation(n)[:size]


def diverse_batch(codes: np.ndarray, size: int, seed: int) -> np.ndarray:
    """Row indexes of a batch: a random first row, then rows of the code with the largest sum of
    differing bits to all chosen ones.

    codes: (n, L) of -1 and +1. A code's sum depends on the counts of chosen bits alone, so no
    pair of samples is ever compared. Codes already used wait until unused ones run out;
    ties are broken at random, and the row within a code's group is random.
    """
    rng = np.random.default_rng(seed)
    n, bits = codes.shape
    kinds, of = np.unique(codes > 0, axis=0, return_inverse=True)
    of = of.ravel()
    signs = kinds * 2.0 - 1
    members = [list(rng.permutation(np.flatnonzero(of == c))) for c in range(len(kinds))]
    size = min(size, n)
    sums, used = np.zeros(bits), np.zeros(len(kinds), int)
    first = int(rng.integers(n))
    chosen = [first]
    members[of[first]].remove(first)
    while True:
        last = of[chosen[-1]]
        used[last] += 1
        sums += signs[last]
        if len(chosen) == size:
            return np.array(chosen)
        free = np.array([len(m) > 0 for m in members])
        low = used[free].min()
        score = code_scores(signs, sums, len(chosen))
        score[~free | (used > low)] = -np.inf
        best = np.flatnonzero(score == score.max())
        chosen.append(int(members[int(rng.choice(best))].pop()))


def code_scores(kinds: np.ndarray, sums: np.ndarray, chosen: int) -> np.ndarray:
    """Each code's sum of differing bits to the chosen rows, from the sums of their signs alone."""
    return (chosen * kinds.shape[1] - kinds @ sums) / 2


def bottom_rows(df: DataFrame, per_site: int, seed: int = 0, key: str = "row_id", vec: str = "vec") -> DataFrame:
    """``site_id, r, key, vec``: at most per_site rows a site, those with the smallest hash of their key, r from 1.

    The bottom-k by hash is a uniform sample that does not depend on partitions. A
    threshold on the hash, from the counts of sites, cuts the input before anything is sorted or shuffled.
    """
    counts = df.groupBy("site_id").agg(F.count("*").alias("v"))
    h = F.pmod(F.xxhash64(F.col(key), F.lit(seed)), F.lit(1 << 40))
    slim = df.select("site_id", F.col(vec).alias("vec"), h.alias("h"), F.col(key).alias("key"))
    limit = F.least(F.lit(1.0), (F.lit(2.0 * per_site) + 64) / F.col("v")) * float(1 << 40)
    rows = slim.join(counts, "site_id").where(F.col("h") < limit)
    ranked = rows.withColumn("r", F.row_number().over(Window.partitionBy("site_id").orderBy("h", "key")))
    return ranked.where(F.col("r") <= per_site).select("site_id", "r", "key", "vec")


def candidate_pool(df: DataFrame, per_site: int, seed: int = 0, key: str = "row_id", vec: str = "vec") -> DataFrame:
    """One row a site: ``site_id, n, vecs``, its bottom rows in their order."""
    packed = bottom_rows(df, per_site, seed, key, vec).groupBy("site_id").agg(F.array_sort(F.collect_list(F.struct("r", "vec"))).alias("s"))
    return packed.select("site_id", F.size("s").alias("n"), F.col("s.vec").alias("vecs"))
