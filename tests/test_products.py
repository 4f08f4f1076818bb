"""Leading vectors from few products and one basis."""

import tracemalloc

import numpy as np

from codecut.operators.spectral import leading_vectors


def test_no_product_after_the_vectors_are_found():
    rng = np.random.default_rng(0)
    q = np.linalg.qr(rng.normal(size=(400, 400)))[0]
    for gap, most in ((1.0, 12), (0.01, 40)):
        a = q * np.concatenate([[2, 1.9, 1.8], 1.8 - gap - rng.uniform(0, 0.5, 397)]) @ q.T
        steps = []
        v = leading_vectors(lambda x: steps.append(1) or a @ x, 400, 3, 40)
        assert len(steps) <= most
        assert np.allclose(np.linalg.norm(q[:, :3].T @ v, axis=0), 1, atol=1e-6)


def test_basis_is_held_once():
    n, scale = 20_000, np.linspace(1, 2, 20_000)[:, None]
    tracemalloc.start()
    leading_vectors(lambda x: x * scale, n, 3, 14)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 2 * 8 * n * 7 * 14  # twice the basis of 14 products with 7 vectors each


def test_tiled_products(spark):
    from codecut.operators.baselines import rbf_rows
    from codecut.operators.spectral import BlockedWeights

    rng = np.random.default_rng(2)
    x, c = rng.normal(size=(1300, 3)), rng.integers(1, 4, 1300).astype(float)
    payload = x, (x * x).sum(1), 1 - 1 / c
    w = np.exp(-0.7 * ((x[:, None] - x[None]) ** 2).sum(2))
    np.fill_diagonal(w, 1 - 1 / c)
    y = rng.normal(size=(1300, 2))
    got = BlockedWeights(spark, 1300, payload, rbf_rows(0.7), block=500, scale=c, tiled=True).times(y)
    assert np.allclose(got, (c[:, None] * w * c) @ y)


def test_copies_are_one_vertex(spark, monkeypatch):
    """A graph of 4,500 rows that are 90 different ones is cut as one of 90 vertices, with the parts of the graph of rows."""
    from codecut.operators import baselines as B
    from codecut.operators.spectral import spectral_embed

    def refuse(*a, **k):
        raise AssertionError("copies are vertices of their own")

    monkeypatch.setattr(B, "BlockedWeights", refuse)
    rng = np.random.default_rng(7)
    kinds = np.concatenate([rng.normal(m, 0.3, size=(30, 2)) for m in ((0, 0), (3, 0), (0, 3))])
    of = np.concatenate([np.arange(90), rng.integers(0, 90, 4410)])
    df = spark.createDataFrame([(i, i % 5, kinds[c].tolist()) for i, c in enumerate(of)], "row_id long, site_id int, vec array<double>")
    got = {r["row_id"]: r["cluster"] for r in B.central_spectral(df, 3).labels.collect()}
    assert len({(c // 30, got[i]) for i, c in enumerate(of)}) == 3 and len(got) == 4500
    # its vectors are those of the graph of rows
    few = of[:300]
    w = np.exp(-((kinds[few][:, None] - kinds[few][None]) ** 2).sum(2)) - np.eye(300)
    at, first, n = np.unique(few, return_index=True, return_counts=True)
    s = np.exp(-((kinds[at][:, None] - kinds[at][None]) ** 2).sum(2)) * n[:, None] * n
    np.fill_diagonal(s, n * (n - 1))
    a, b = spectral_embed(w, 3)[first], spectral_embed(s.astype(float), 3)
    assert np.allclose(a @ a.T, b @ b.T)


def test_each_site_has_its_task(spark):
    from pyspark.sql import functions as F

    from codecut.operators.baselines import _by_site

    df = spark.range(700).select(F.col("id").alias("row_id"), (F.col("id") % 7).cast("int").alias("site_id"))
    got = _by_site(df, lambda site, f: f.groupby("site_id", as_index=False).size().assign(site=site), "site_id int, size long, site int")
    parts = got.select("site_id", "site", "size", F.spark_partition_id().alias("p")).collect()
    assert sorted((r["site_id"], r["site"], r["size"]) for r in parts) == [(i, i, 100) for i in range(7)] and len({r["p"] for r in parts}) == 7
