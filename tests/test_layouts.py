"""Densities and distances within buckets, without copies of the rows in their buckets."""

import math

import numpy as np
import pytest

from codecut.operators import baselines as B


def _by_hand(x, codes, eps):
    d = np.linalg.norm(x[:, None] - x[None], axis=2)
    same = (codes[:, None] == codes[None]).all(3)
    near = (d <= eps) & ~np.eye(len(x), dtype=bool)
    rho = (near[:, :, None] & same).sum(1).max(1)
    ids = np.arange(len(x))
    denser = (rho[None] > rho[:, None]) | ((rho[None] == rho[:, None]) & (ids[None] < ids[:, None]))
    d = np.where(denser & same.any(2), d, np.inf)
    return rho, d.min(1), [int(np.flatnonzero(r == r.min())[0]) for r in d]


@pytest.fixture(scope="module", params=["few cells", "many cells", "wide hashes"])
def case(request, spark):
    rng = np.random.default_rng(3)
    x = rng.integers(-3, 4, size=(300, 4)).astype(float)
    layouts, hashes, width = {"few cells": (2, 1, 60.0), "many cells": (4, 2, 2.0), "wide hashes": (2, 3, 1e-6)}[request.param]
    if request.param == "wide hashes":  # a tuple does not fit one number
        x = x.repeat(2, axis=0)[:300]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id long, vec array<double>")
    a, b = rng.normal(size=(4, layouts * hashes)), rng.uniform(0, width, layouts * hashes)
    codes = np.floor((x @ a + b) / width).reshape(300, layouts, hashes)
    return x, codes, layouts, B.dealt(B.lsh_codes(df, layouts, hashes, width, 4, maps=(a, b)), 50)


@pytest.mark.parametrize("most_bytes", [3_000, 1 << 20])
def test_layout_densities(case, most_bytes):
    x, codes, layouts, rows = case
    want = _by_hand(x, codes, 3.0)[0]
    assert {r["row_id"]: r["rho"] for r in B.layout_densities(rows, 3.0, layouts, most_bytes).collect()} == dict(enumerate(want))


def test_rows_stay_out_of_the_shuffle(spark, sf):
    """A row is there once, whatever the number of layouts and the size of a bucket."""
    from codecut.plans.queries_method import _int_codes

    rows = _int_codes(spark, sf)
    assert rows.count() == rows.select("row_id").distinct().count() == spark.read.parquet(f"{sf}/embeddings.parquet").count()


@pytest.mark.parametrize("most_bytes", [3_000, 1 << 20])
def test_layout_deltas(spark, case, most_bytes):
    x, codes, layouts, rows = case
    rho, delta, up = _by_hand(x, codes, 3.0)
    given = spark.createDataFrame(list(enumerate(rho.tolist())), "row_id long, rho long")
    got = {r["row_id"]: (r["delta"], r["up"]) for r in B.layout_deltas(rows, given, layouts, most_bytes).collect()}
    assert {i: (pytest.approx(d), u) for i, (d, u) in got.items()} == {i: (d, u) for i, (d, u) in enumerate(zip(delta, up)) if math.isfinite(d)}


def test_gamma_topk_many_rows(spark, sf, tmp_path):
    """Four copies of the table, moved a little apart: the query reads them all and agrees with all pairs."""
    from pyspark.sql import functions as F

    from codecut.plans import load_queries
    from codecut.plans.registry import ORACLE_SQL, QUERIES

    load_queries()

    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    copies = e.withColumn("c", F.explode(F.sequence(F.lit(0), F.lit(3)))).select((F.col("vec_id") + F.col("c") * 1000).alias("vec_id"), F.transform("embedding", lambda x: (x + F.col("c") / 64).cast("float")).alias("embedding"), "label")
    copies.coalesce(1).write.parquet(f"{tmp_path}/embeddings.parquet")
    import duckdb

    con = duckdb.connect()
    con.sql(f"create view embeddings as select * from '{tmp_path}/embeddings.parquet/*.parquet'")
    rel = con.sql(ORACLE_SQL["gamma_topk"])
    got = QUERIES["gamma_topk"](spark, str(tmp_path)).select(*rel.columns).collect()
    assert [tuple(r) for r in got] == rel.fetchall()


def test_site_representatives_hold_no_matrix():
    import tracemalloc

    x = np.random.default_rng(1).normal(size=(5000, 3))
    tracemalloc.start()
    reps = B.site_representatives(x, 0.8, 0.1)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 8 * len(x) ** 2  # one matrix of distances
    near = np.linalg.norm(x[:, None] - x[None], axis=2) <= 0.8
    rho = near.sum(1) - 1
    left, want = rho >= max(1.0, 0.1 * rho.mean()), []
    for i in np.argsort(-rho, kind="stable"):
        if left[i]:
            want.append((i, int((near[i] & left).sum())))
            left &= ~near[i]
    assert [(x[i].tolist(), n) for i, n in want] == [(r[0].tolist(), r[2]) for r in reps]


def test_hashed_density_peaks_puts_no_row_into_buckets(spark, monkeypatch):
    def refuse(*a, **k):
        raise AssertionError("rows are copied into buckets")

    for name in ("lsh_buckets", "_split_buckets", "_by_parts"):
        monkeypatch.setattr(B, name, refuse)
    rng = np.random.default_rng(5)
    x = np.repeat(np.eye(3) * 20, 40, axis=0) + rng.integers(0, 3, size=(120, 3))  # with copies
    df = spark.createDataFrame([(i, i % 3, v.tolist()) for i, v in enumerate(x)], "row_id long, site_id int, vec array<double>")
    got = {r["row_id"]: r["cluster"] for r in B.hashed_density_peaks(df, 3, layouts=2, hashes=1, width=1e6, eps=2.0).labels.collect()}
    assert [len({got[i] for i in range(c * 40, c * 40 + 40)}) for c in range(3)] == [1, 1, 1] and len(set(got.values())) == 3


def test_packed_rows_are_exact():
    x = np.array([[1, -2, 0], [0.5, 1, 2], [0.1, 1e300, 3], [-0.0, 40000, 1], [np.inf, 0, 0]])
    a = B.packed(x, B._REAL)
    assert np.array_equal(B.unpacked(a, B._REAL), x) and np.array_equal(B.unpacked(a[1:4], B._REAL), x[1:4])
    assert [len(v) for v in a.to_pylist()] == [7, 13, 25, 13, 25]
    assert B.packed(np.array([[0.0, 1]]), B._REAL) == B.packed(np.array([[-0.0, 1]]), B._REAL)
    y = np.array([[1, 200], [-(1 << 62), 5], [70_000, 0]])
    assert np.array_equal(B.unpacked(B.packed(y, B._WHOLE), B._WHOLE), y)


def test_gamma_topk_disk(spark, sf, tmp_path):
    """Vectors are kept on disk once, in few bytes: before, five times the table."""
    from pathlib import Path

    from codecut.plans import load_queries
    from codecut.plans.registry import QUERIES
    from codecut.session import shared_dir

    load_queries()
    folder = Path(shared_dir(spark).removeprefix("file:"))
    used = lambda: sum(p.stat().st_size for p in folder.rglob("part-*"))
    before = used()
    QUERIES["gamma_topk"](spark, sf).collect()
    assert used() - before < 1.5 * Path(f"{sf}/embeddings.parquet").stat().st_size


def test_copies_are_compared_once(spark, monkeypatch):
    """Copies add to densities and follow the first of their kind, but only kinds pass by the chunks."""
    rng = np.random.default_rng(8)
    kinds = rng.integers(-4, 5, size=(40, 3)).astype(float)
    x = kinds[rng.integers(0, 40, 600)]
    seen, whole = [], B._against_all
    monkeypatch.setattr(B, "_against_all", lambda k, *a: (seen.append(k.count()), whole(k, *a))[1])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "row_id long, vec array<double>")
    maps = (rng.normal(size=(3, 2)), np.zeros(2))
    rows = B.lsh_codes(df, 2, 1, 3.0, 3, maps=maps)
    rho, delta, up = _by_hand(x, np.floor(x @ maps[0] / 3.0).reshape(600, 2, 1), 2.0)
    k = B.kinds_of(rows, 600)
    first, to = B.kind_peaks(k, 2.0, 2)
    assert {r["row_id"]: r["rho"] for r in first.collect()} == {i: rho[i] for i in np.unique(x, axis=0, return_index=True)[1]}
    got = {r["row_id"]: (r["delta"], r["up"]) for r in B.of_copies(k, to).collect()}
    assert {i: (pytest.approx(d), u) for i, (d, u) in got.items()} == {i: (d, u) for i, (d, u) in enumerate(zip(delta, up)) if math.isfinite(d)}
    assert seen == [len(np.unique(x, axis=0))] * 2


def test_peaks_of_fewer_kinds_than_clusters(spark):
    """Three kinds and five clusters: copies are centers of themselves, as their gammas, all nothing, go by their ids."""
    x = np.repeat([[0.0, 0], [50, 0], [0, 50]], 4, axis=0)
    df = spark.createDataFrame([(i, 0, v.tolist()) for i, v in enumerate(x)], "row_id long, site_id int, vec array<double>")
    got = {r["row_id"]: r["cluster"] for r in B.hashed_density_peaks(df, 5, layouts=2, hashes=1, width=1e6, eps=2.0).labels.collect()}
    assert len(set(got.values())) == 5 and sorted(got) == list(range(12))
    assert got[1] not in {got[0], got[2]} and got[0] == got[3] and len({got[i] for i in range(4, 8)}) == 1


def test_planted_vectors_are_looked_up(spark):
    """Each row's vector is as the formula gives it, and the formula is worked out for 17 * 201 vectors, whatever the rows."""
    import zlib

    from codecut.operators.features import planted_vectors

    rows = [(-5, "x"), (0, "BUILDING"), (200, "BUILDING"), (10**12, "MACHINERY"), (7, None), (None, "y")]
    got = planted_vectors(spark.createDataFrame(rows, "k long, s string"), "s", "k", 5, 0.3)
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert "transform" not in plan[: plan.index("Range (0, 3417")].split("Join")[0] and "Range (0, 3417" in plan
    center = lambda s, i: float((zlib.crc32(s.encode()) % 1_000_003 * (i * i + 7 * i + 13) + i * 7919) % 17) - 8
    noise = lambda k, i: (float(((k + 1) * (i * 31 + 17) + i * i * 11) % 201) - 100) / 100 * 0.3
    want = {(k, s, tuple(None if k is None or s is None else center(s, i) + noise(k, i) for i in range(5))) for k, s in rows}
    assert {(r["row_id"], r["truth"], tuple(r["vec"])) for r in got.collect()} == want


@pytest.mark.parametrize("hashes, width", [(1, 4.0), (2, 6.0)])
def test_far_groups_are_left_out(monkeypatch, hashes, width):
    """Distances are made to groups near a row only, and counts and nearest denser rows are those by hand."""
    rng = np.random.default_rng(5)
    x = (rng.integers(0, 6, size=(1500, 1)) * 50 + rng.integers(-3, 4, size=(1500, 6))).astype(float)
    x = np.unique(x, axis=0)
    n = len(x)
    codes = np.floor((x @ rng.normal(size=(6, 2 * hashes)) + 3) / width).astype(np.int64).reshape(n, 2, hashes)
    rho, delta, up = _by_hand(x, codes, 4.0)
    groups, made, squares = B.leaves(x), [], B._strip_squares
    true = ((x[:, None] - x[None]) ** 2).sum(2)
    bound = groups.squares(x)
    for g, (lo, hi) in enumerate(zip(groups.ends, groups.ends[1:])):
        assert (bound[:, g] <= true[:, groups.order[lo:hi]].min(1)).all()
    monkeypatch.setattr(B, "_strip_squares", lambda a, sa, b, sb: (made.append(len(a) * len(b)), squares(a, sa, b, sb))[1])
    ids = np.arange(n)
    near = B._near_by_layout(4.0)((ids, np.ones(n, int), x, codes, None), (ids, np.ones(n, int), x, codes, None, groups)).to_pydict()
    assert [max(c) for c in near["near"]] == rho.tolist() and sum(made) < 0.5 * n * n
    made.clear()
    got = B._nearest_denser((ids, None, x, codes, rho), (ids, None, x, codes, rho, groups)).to_pydict()
    some = np.isfinite(delta)
    assert got["row_id"] == ids[some].tolist() and np.allclose(got["delta"], delta[some]) and got["up"] == np.array(up)[some].tolist()
    assert sum(made) < 0.5 * n * n


@pytest.mark.parametrize("hashes, width", [(1, 3.0), (2, 9.0)])
def test_groups_hardly_apart_meet_in_wide_blocks(monkeypatch, hashes, width):
    rng = np.random.default_rng(hashes)
    x = np.unique(rng.integers(-9, 10, size=(1300, 12)).astype(float), axis=0)
    n, groups = len(x), B.leaves(x)
    codes = np.floor((x @ rng.normal(size=(12, 2 * hashes)) + 3) / width).astype(np.int64).reshape(n, 2, hashes)
    rho, delta, up = _by_hand(x, codes, 22.0)
    ids, one, some, wide, squares = np.arange(n), np.ones(n, int), np.isfinite(delta), [], B._strip_squares
    monkeypatch.setattr(B, "_strip_squares", lambda a, sa, b, sb: (wide.append(len(b)), squares(a, sa, b, sb))[1])
    near = B._near_by_layout(22.0)((ids, one, x, codes, None), (ids, one, x, codes, None, groups)).to_pydict()
    assert [max(c) for c in near["near"]] == rho.tolist() and min(wide) > B._LEAF
    wide.clear()
    got = B._nearest_denser((ids, None, x, codes, rho), (ids, None, x, codes, rho, groups)).to_pydict()
    assert got["row_id"] == ids[some].tolist() and np.allclose(got["delta"], delta[some]) and got["up"] == np.array(up)[some].tolist()
    assert max(wide) > B._LEAF
