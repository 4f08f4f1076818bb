"""Graphs of many codes and rows: none refused, and weights made once for both of their rows."""

import numpy as np
import pytest

from codecut.operators.spectral import blocked_code_weights, code_weights


def test_pretrained_start_takes_many_codes(spark, sf, monkeypatch):
    """w10_pretrained_start stopped at 100,000 codes."""
    from pyspark.sql import functions as F

    from codecut.plans import pipeline, queries_workloads

    asked = []

    class Kept(pipeline.CodeGraphClustering):
        def _fit(self, dataset):
            asked.append(self.settings)
            return super()._fit(dataset)

    monkeypatch.setattr(queries_workloads, "CodeGraphClustering", Kept)
    assert queries_workloads.w10_pretrained_start(spark, sf).count() == 3
    degrees = spark.range(100_001).select(F.col("id").alias("code"), F.lit(0).alias("site_id"), (F.col("id") % 3 + 1).alias("degree"))
    assert len(asked) == 4
    for settings in {s.max_codes: s for s in asked}.values():
        codes, counts = pipeline.graph_vertices(degrees, settings)
        assert len(set(codes.tolist())) == 100_001 and counts.sum() == sum(i % 3 + 1 for i in range(100_001))


@pytest.mark.parametrize("bits, p", [(64, 1.0), (100, 1.5)])
def test_halved_products_equal_the_matrix(spark, bits, p):
    rng = np.random.default_rng(bits)
    low, high = rng.integers(-(2**63), 2**63 - 1, 1500), rng.integers(0, 1 << 36, 1500)
    codes = low if bits == 64 else np.stack([low, high], 1)
    codes[7] = codes[3]  # no distance: no weight
    degrees = rng.integers(1, 50, 1500).astype(float)
    b = blocked_code_weights(spark, codes, degrees, bits, 0.5, p)
    assert b.tiles is None
    b = blocked_code_weights(spark, codes, degrees, bits, 0.5, p, halved_above=100)
    x, full = rng.normal(size=(1500, 3)), code_weights(codes, degrees, bits, 0.5, p)
    for some in (64 << 20, 1):  # all turns in one job, and a job a turn
        got = np.sqrt(degrees)[:, None] * b._halved(np.sqrt(degrees)[:, None] * x, some)
        assert np.abs(got - full @ x).max() < 1e-6 * (full @ np.abs(x)).max()
    e, whole = b.embed(3), blocked_code_weights(spark, codes, degrees, bits, 0.5, p).embed(3)
    assert np.allclose(e @ e.T, whole @ whole.T, atol=1e-2)


def test_halved_products_of_rows(spark):
    from codecut.operators.baselines import landmark_start, rbf_rows
    from codecut.operators.spectral import BlockedWeights, spectral_embed

    rng = np.random.default_rng(5)
    x, c = np.concatenate([rng.normal(m, 0.2, size=(500, 3)) for m in (-0.5, 0, 0.5)]).astype(np.float32), rng.integers(1, 4, 1500).astype(float)
    payload = x, (x * x).sum(1), (1 - 1 / c).astype(np.float32)
    w = np.exp(-((x[:, None].astype(float) - x[None]) ** 2).sum(2))
    np.fill_diagonal(w, 1 - 1 / c)
    w = c[:, None] * w * c
    b = BlockedWeights(spark, 1500, payload, rbf_rows(1.0), scale=c, tiled=True, tiles=rbf_rows(1.0), halved_above=100)
    y, want = rng.normal(size=(1500, 2)), spectral_embed(w, 3)
    assert np.abs(b.times(y) - w @ y).max() < 1e-6 * (w @ np.abs(y)).max()
    made, times = [], b.times
    b.times = lambda y: made.append(y.shape[1]) or times(y)
    e = b.embed(3)
    plain = len(made)
    assert np.allclose(e @ e.T, want @ want.T, atol=1e-3)
    e = b.embed(3, start=landmark_start(spark, payload, b.payload, 1.0, c, 3, count=300))
    assert np.allclose(e @ e.T, want @ want.T, atol=1e-3) and len(made) - plain < plain  # fewer products, the same vectors
