"""The graph of codes: vertices are distinct codes, weights grow with degrees and fall with distance."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bits import band_keys, hamming
from ..session import checkpoint
from .components import connected_components


def cap_codes(degrees: DataFrame, max_codes: int) -> DataFrame:
    """The max_codes codes of largest degree (ties by code)."""
    return degrees.orderBy(F.desc("degree"), "code").limit(max_codes)


def edge_weights(vertices: DataFrame, alpha: float = 1.0, p: float = 1.0, max_hamming: int | None = None, most: int = 4096) -> DataFrame:
    """``src, dst, weight`` with src < dst; vertices(code, degree) has at most ``most`` rows, which is checked before it is broadcast."""
    n = vertices.limit(most + 1).count()
    if n > most:
        raise ValueError(f"more than {most} codes: cap them, or use the matrix-free solver")
    a = vertices.select(F.col("code").alias("src"), F.col("degree").alias("da"))
    b = vertices.select(F.col("code").alias("dst"), F.col("degree").alias("db"))
    h = hamming(F.col("src"), F.col("dst"))
    pairs = a.join(F.broadcast(b), F.col("src") < F.col("dst")).withColumn("h", h)
    if max_hamming is not None:
        pairs = pairs.where(F.col("h") <= max_hamming)
    d = F.pow(F.col("da").cast("double") * F.col("db"), F.lit(float(alpha)))
    return pairs.select("src", "dst", (d / F.pow("h", F.lit(float(p)))).alias("weight"))


def both_ways(edges: DataFrame) -> DataFrame:
    return edges.union(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))


def vertex_strength(edges: DataFrame) -> DataFrame:
    return both_ways(edges).groupBy(F.col("src").alias("code")).agg(F.sum("weight").alias("strength"))


def cut_value(edges: DataFrame, labels: DataFrame, volume: str = "degree") -> DataFrame:
    """One row ``cut_value`` of labels(code, cluster) on edges."""
    a = labels.select(F.col("code").alias("src"), F.col("cluster").alias("ca"))
    b = labels.select(F.col("code").alias("dst"), F.col("cluster").alias("cb"))
    e = both_ways(edges).join(a, "src").join(b, "dst")
    each = e.groupBy("ca").agg(F.sum(F.when(F.col("ca") != F.col("cb"), F.col("weight")).otherwise(0.0)).alias("out"), F.sum("weight").alias("vol"))
    if volume == "vertices":
        sizes = labels.groupBy(F.col("cluster").alias("ca")).agg(F.count("*").alias("n"))
        each = each.drop("vol").join(sizes, "ca").withColumnRenamed("n", "vol")
    return each.agg((0.5 * F.sum(F.col("out") / F.col("vol"))).alias("cut_value"))


def nearest_code(codes: DataFrame, vertices: DataFrame, most: int = 100_000, n_bits: int = 64) -> DataFrame:
    """``code, near, distance`` for distinct codes: the closest vertex; ties by larger degree, then smaller code.

    At most ``most`` vertices (counted) are broadcast. Beyond that, banded joins of growing radius find
    the vertices around each code that has none yet.
    """
    v = vertices.select(F.col("code").alias("near"), "degree")
    best = F.min_by(F.struct("near", F.col("d").alias("distance")), F.struct("d", -F.col("degree"), "near"))
    if vertices.limit(most + 1).count() <= most:
        pairs = codes.select("code").join(F.broadcast(v)).withColumn("d", hamming(F.col("code"), F.col("near")))
        return pairs.groupBy("code").agg(best.alias("b")).select("code", "b.near", "b.distance")
    left, out, radius = checkpoint(codes.select("code").distinct()), None, 1
    while not left.isEmpty():
        radius = min(radius, n_bits - 1)
        pairs = hamming_join(left, vertices, radius, n_bits) if radius < n_bits - 1 else left.select(F.col("code").alias("a")).join(v.select(F.col("near").alias("b"))).withColumn("distance", hamming(F.col("a"), F.col("b")))
        near = pairs.select(F.col("a").alias("code"), F.col("b").alias("near"), F.col("distance").alias("d")).join(v, "near")
        found = checkpoint(near.groupBy("code").agg(best.alias("b")).select("code", "b.near", "b.distance"))
        out = found if out is None else out.union(found)
        left, radius = checkpoint(left.join(found, "code", "left_anti")), radius * 2
    return found.limit(0) if out is None else out


def contract_codes(degrees: DataFrame, max_codes: int, n_bits: int = 64) -> DataFrame:
    """The max_codes codes of largest degree, each with the degrees of the codes that it is nearest to added: no row is lost."""
    top = checkpoint(cap_codes(degrees, max_codes))
    rest = degrees.join(top.select("code"), "code", "left_anti")
    gained = nearest_code(rest, top, n_bits=n_bits).join(rest, "code").select(F.col("near").alias("code"), "degree")
    return top.union(gained).groupBy("code").agg(F.sum("degree").alias("degree"))


def hamming_join(a: DataFrame, b: DataFrame, radius: int, n_bits: int) -> DataFrame:
    """``a, b, distance`` of codes within radius: radius + 1 bands, of which two close codes share one; then checked.

    A pair is kept in the first band that it shares, so nothing has to be made distinct.
    """
    left = a.select(F.col("code").alias("a")).select("a", F.inline(band_keys(F.col("a"), n_bits, radius + 1)))
    right = b.select(F.col("code").alias("b")).select("b", F.inline(band_keys(F.col("b"), n_bits, radius + 1)))
    pairs = left.join(right, ["band", "value"]).withColumn("distance", hamming(F.col("a"), F.col("b"))).where(F.col("distance") <= radius)
    same = F.zip_with(band_keys(F.col("a"), n_bits, radius + 1), band_keys(F.col("b"), n_bits, radius + 1), lambda x, y: x["value"] == y["value"])
    return pairs.where(F.array_position(same, True) == F.col("band") + 1).select("a", "b", "distance")


def graph_components(edges: DataFrame) -> DataFrame:
    return connected_components(edges)


def knn_codes(vertices: DataFrame, k: int, most: int = 4096) -> DataFrame:
    """The k nearest other codes of each code: ``src, dst, distance, rank``."""
    pairs = both_ways(edge_weights(vertices, most=most)).select("src", "dst", hamming(F.col("src"), F.col("dst")).alias("distance"))
    ranked = pairs.withColumn("rank", F.row_number().over(Window.partitionBy("src").orderBy("distance", "dst")))
    return ranked.where(F.col("rank") <= k)


def canonical_labels(df: DataFrame, cluster: str = "cluster", key: str = "row_id") -> DataFrame:
    """``row_id, label``: clusters named by the smallest row in them."""
    low = df.groupBy(cluster).agg(F.min(key).alias("label"))
    return df.join(low, cluster).select(key, "label")
