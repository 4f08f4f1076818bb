"""The method's parts against worked examples, exact baselines, and their own invariants."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from codecut.functions.bits import pack_array, unpack_array
from codecut.operators import baselines as B
from codecut.operators import cost as C
from codecut.operators import metrics as M
from codecut.operators.encode import encode
from codecut.operators.features import Normalizer, fit_normalizer, matrix_of, normalize, planted_vectors
from codecut.operators.graph import cut_value as cut_frame
from codecut.operators.graph import edge_weights, hamming_join, nearest_code
from codecut.operators.loss import loss_gradient, pair_loss, suggest_lambda
from codecut.operators.network import backward, conv_encoder, dense_encoder, forward, init_params, linear_encoder
from codecut.operators.sampling import candidate_pool, diverse_batch, uniform_batch
from codecut.operators.sites import assign_sites, check_vectors, site_profile
from codecut.operators.spectral import block_subspace_iteration, code_weights, cut_value, kmeans, ncut_bisect, spectral_embed, spectral_labels
from codecut.operators.train import TrainConfig, site_step, train_encoder, train_round
from codecut.plans.pipeline import CodeGraphClustering, CodeGraphModel, Settings, assign_clusters
from codecut.session import checkpoint


@pytest.fixture(scope="module")
def vectors(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    return checkpoint(e.select(F.col("vec_id").cast("long").alias("row_id"), F.pmod("vec_id", F.lit(5)).cast("int").alias("site_id"), F.col("embedding").alias("vec"), F.col("label").alias("truth")))


@pytest.fixture(scope="module")
def orders(spark, sf):
    o = spark.read.parquet(f"{sf}/orders.parquet")
    return checkpoint(assign_sites(planted_vectors(o, "o_orderpriority", "o_orderkey"), "row_id", 5))


@pytest.mark.parametrize("spec", [dense_encoder(12, 5), conv_encoder(24, 5, (2, 3), 3, 2), linear_encoder(9, 4), dense_encoder(8, 3, (6,))])
@pytest.mark.parametrize("pairing", ["all", "consecutive"])
def test_gradient_against_differences(spec, pairing):
    rng = np.random.default_rng(1)
    x, p = rng.normal(size=(7, spec.dim)), init_params(spec, 2)
    p = p + rng.normal(0, 0.05, len(p))
    grad, (loss, pairs) = backward(spec, p, x, lambda h: loss_gradient(x, h, 0.7, 2.0, pairing))
    assert spec.n_params == len(p) == len(grad)
    assert loss == pytest.approx(pair_loss(x, forward(spec, p, x), 0.7, 2.0, pairing)) and pairs == (21 if pairing == "all" else 3)
    wrong = 0
    for i in rng.choice(len(p), 40, replace=False):
        step = np.zeros(len(p))
        step[i] = 1e-6
        num = (pair_loss(x, forward(spec, p + step, x), 0.7, 2.0, pairing) - pair_loss(x, forward(spec, p - step, x), 0.7, 2.0, pairing)) / 2e-6
        wrong += abs(num - grad[i]) > 1e-4 * max(1, abs(num))
    assert wrong <= 1  # a kink may lie between the two points


def test_loss_by_hand():
    x = np.array([[0.0, 0.0], [3.0, 4.0]])  # distance 5
    same, opposite = np.array([[1.0, 1], [1, 1]]), np.array([[1.0, 1], [-1, -1]])
    assert pair_loss(x, opposite, 4 / 5, math.inf) == 0  # 4 = 2L is met exactly
    assert pair_loss(x, same, 1, 2.5) == pytest.approx(5 * math.exp(-2))
    # opposite codes cannot be told apart further: the wish saturates at distance 2L / lambda
    assert suggest_lambda(x, 2, 1.0) == pytest.approx(4 / 5)
    assert forward(linear_encoder(2, 1), np.zeros(3), np.zeros((1, 2)), "sign")[0, 0] == 1  # the sign of 0 is +1


def test_selector_on_the_cube():
    cube = np.array([[1 if i >> b & 1 else -1 for b in range(3)] for i in range(8)], float)
    for seed in range(20):
        got = diverse_batch(cube, 8, seed)
        assert sorted(got) == list(range(8))
        assert np.array_equal(cube[got[1]], -cube[got[0]])  # the opposite vertex
    thirds = {int(diverse_batch(cube, 3, s)[2]) for s in range(200) if diverse_batch(cube, 3, s)[0] == 0}
    assert thirds == set(range(1, 7))  # any of the six unused vertices
    assert len(set(uniform_batch(50, 20, 1))) == 20


def test_selector_scores_are_pair_sums():
    rng = np.random.default_rng(5)
    codes = np.unique(rng.integers(0, 2, (40, 9)) * 2 - 1, axis=0).astype(float)
    got = diverse_batch(codes, 12, 3)
    for i in range(1, 12):
        left = np.setdiff1d(np.arange(len(codes)), got[:i])
        sums = np.array([sum((codes[j] != codes[g]).sum() for g in got[:i]) for j in left])
        assert sums[list(left).index(got[i])] == sums.max()


def test_bits_round_trip():
    rng = np.random.default_rng(0)
    for bits in (1, 8, 63, 64, 130):
        s = rng.integers(0, 2, (20, bits)).astype(bool)
        assert np.array_equal(unpack_array(pack_array(s), bits) > 0, s)


def test_cut_by_hand():
    w = np.zeros((6, 6))
    for a, b in ((0, 1), (0, 2), (1, 2), (3, 4), (3, 5), (4, 5)):
        w[a, b] = w[b, a] = 1
    w[2, 3] = w[3, 2] = 0.5
    two = np.array([0, 0, 0, 1, 1, 1])
    assert cut_value(w, two) == pytest.approx(0.5 * (0.5 / 6.5 * 2))
    assert cut_value(w, two, "vertices") == pytest.approx(0.5 * (0.5 / 3 * 2))
    assert cut_value(7 * w, two) == pytest.approx(cut_value(w, two)) and cut_value(w, np.zeros(6)) == 0
    for labels in (spectral_labels(w, 2), spectral_labels(w, 2, kind="random_walk"), spectral_labels(w, 2, kind="unnormalized"), ncut_bisect(w, 2)):
        assert len(set(labels[:3])) == 1 and len(set(labels[3:])) == 1 and labels[0] != labels[3]
    assert list(spectral_labels(w[:2, :2], 5)) == [0, 1]


def test_weights_and_matrix_free(spark):
    rng = np.random.default_rng(3)
    codes = np.unique(rng.integers(0, 1 << 12, 150))
    d = rng.integers(1, 9, len(codes)).astype(float)
    w = code_weights(codes, d, 12)
    assert np.allclose(w, w.T) and not np.diag(w).any()
    assert w[0, 1] == pytest.approx(d[0] * d[1] / bin(int(codes[0] ^ codes[1])).count("1"))
    assert np.allclose(code_weights(codes, d, 12, rows=slice(3, 9)), w[3:9])
    # three groups of codes: the wanted eigenvalues are parted from the rest
    near = np.unique([c ^ (1 << i) ^ (1 << j) for c in (0, 0b111111000000, 0b000111111111) for i in range(12) for j in range(12)])
    ones = np.ones(len(near))
    a, b = code_weights(near, ones, 12, p=1.0), block_subspace_iteration(spark, near, ones, 12, 1, iterations=60, block=40)
    dense = spectral_embed(a, 1)
    assert np.allclose(dense @ dense.T, b @ b.T, atol=1e-3)
    v = spark.createDataFrame([(int(c), int(x)) for c, x in zip(codes, d)], "code long, degree long")
    labels = codes % 3
    frame = spark.createDataFrame([(int(c), int(x)) for c, x in zip(codes, labels)], "code long, cluster int")
    for vol in ("degree", "vertices"):
        assert cut_frame(edge_weights(v), frame, vol).first()[0] == pytest.approx(cut_value(w, labels, vol))
    with pytest.raises(ValueError):
        edge_weights(v, most=10)


def test_hamming_join_is_complete(spark):
    rng = np.random.default_rng(8)
    codes = np.unique(rng.integers(0, 1 << 14, 300)).tolist()
    df = spark.createDataFrame([(c, 1) for c in codes], "code long, degree long")
    got = sorted((r["a"], r["b"]) for r in hamming_join(df, df, 3, 14).collect())
    assert got == sorted((a, b) for a in codes for b in codes if bin(a ^ b).count("1") <= 3)
    near = {r["code"]: (r["near"], r["distance"]) for r in nearest_code(df.limit(30), df.where("code % 2 = 0")).collect()}
    for c, (n, dist) in near.items():
        best = min((bin(c ^ o).count("1"), o) for o in codes if o % 2 == 0)
        assert (dist, n) == best


def test_kmeans_weights():
    x = np.array([[0.0], [1], [10], [11]])
    labels, centers, _ = kmeans(x, 2, 0, 5, np.array([3.0, 1, 1, 1]))
    assert sorted(round(float(c), 4) for c in centers[:, 0]) == [0.25, 10.5] and labels[0] == labels[1] != labels[2]


def test_averages_of_sites(spark, vectors):
    """Sites that are alike give one site's step; weights by batch give the pooled gradient."""
    spec, cfg = linear_encoder(64, 8), TrainConfig(batch=40, selector="uniform", seed=3)
    rows = [r["vec"] for r in vectors.orderBy("row_id").limit(60).collect()]
    pool = spark.createDataFrame([(s, 40, rows[:40]) for s in range(3)], "site_id int, n int, vecs array<array<float>>")
    p = init_params(spec, 1)
    got, loss = train_round(pool, spec, p, cfg, Normalizer("none"), 1, 3)
    grad, one, _ = site_step(spec, p, np.array(rows[:40]), cfg, 0)
    assert np.allclose(got, p - cfg.lr * grad, atol=1e-6) and loss == pytest.approx(one, abs=1e-6)
    uneven = spark.createDataFrame([(0, 40, rows[:40]), (1, 20, rows[40:60])], "site_id int, n int, vecs array<array<float>>")
    g2, _, _ = site_step(spec, p, np.array(rows[40:60]), cfg, 0)
    weighted, _ = train_round(uneven, spec, p, cfg, Normalizer("none"), 1, 2)
    assert np.allclose(weighted, p - cfg.lr * (40 * grad + 20 * g2) / 60, atol=1e-6)
    merged, _ = train_round(pool, spec, p, TrainConfig(batch=40, selector="uniform", seed=3, merge="parameter"), Normalizer("none"), 1, 3)
    assert np.allclose(merged, got, atol=1e-5)  # one local step from a common start


def test_two_level_sums_equal_plain(spark, vectors, monkeypatch):
    spec, cfg = dense_encoder(64, 8), TrainConfig(batch=8)
    pool = candidate_pool(vectors, 30)
    p = init_params(spec, 0)
    plain, loss = train_round(pool, spec, p, cfg, Normalizer("none"), 1, 5)
    grouped, other = train_round(pool, spec, p, cfg, Normalizer("none"), 1, 5_000_000)
    assert np.allclose(plain, grouped, atol=1e-6) and loss == pytest.approx(other)


def test_training_is_repeatable_and_stops(spark, vectors):
    spec, cfg = dense_encoder(64, 8), TrainConfig(n_rounds=6, batch=16)
    a = train_encoder(candidate_pool(vectors, 50), spec, cfg, keep=(3,))
    b = train_encoder(candidate_pool(vectors.repartition(7), 50), spec, cfg)
    assert np.array_equal(a.params, b.params) and len(a.history) == 6 and 3 in a.snapshots
    assert a.history[-1]["loss"] < a.history[0]["loss"]
    assert len(train_encoder(candidate_pool(vectors, 50), spec, TrainConfig(n_rounds=6, batch=16, tol=1e9)).history) == 2


def test_pools_are_bounded_and_whole(spark, vectors):
    pool = {r["site_id"]: r for r in candidate_pool(vectors, 20).collect()}
    assert len(pool) == 5 and all(r["n"] == 20 == len(r["vecs"]) for r in pool.values())
    assert all(r["n"] == 100 for r in candidate_pool(vectors, 1000).collect())


def test_normalizers_agree(spark, vectors):
    x = np.array([r["vec"] for r in vectors.orderBy("row_id").collect()], float)
    for kind in ("none", "l2", "minmax", "zscore", "zscore_sqrt_dim"):
        stats = fit_normalizer(vectors, kind)
        got = np.array([r["vec"] for r in normalize(vectors, stats).orderBy("row_id").collect()], float)
        assert np.allclose(got, stats.apply(x), atol=1e-6), kind
    z = fit_normalizer(vectors, "zscore").apply(x)
    assert np.allclose(z.mean(0), 0, atol=1e-6) and np.allclose(z.std(0), 1, atol=1e-4)


def test_bad_vectors(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, [1.0]), (4, [1.0, None]), (5, [float("nan"), 1.0]), (6, [])]
    df = spark.createDataFrame(rows, "row_id long, vec array<double>")
    assert [r["row_id"] for r in check_vectors(df, 2, "drop").collect()] == [1]
    assert sum(r["bad"] for r in check_vectors(df, 2, "quarantine").collect()) == 5
    with pytest.raises(Exception, match="bad vector"):
        check_vectors(df, 2).collect()


def test_measures_by_hand(spark):
    rows = [(i, c, t) for i, (c, t) in enumerate([(0, "a"), (0, "a"), (0, "b"), (1, "b"), (1, "b"), (1, "a")])]
    df = spark.createDataFrame(rows, "row_id long, cluster int, truth string")
    one = lambda d: float(d.first()[0])
    assert one(M.purity(df)) == pytest.approx(4 / 6)
    all_one, singles = df.withColumn("cluster", F.lit(0)), df.withColumn("cluster", F.col("row_id"))
    assert one(M.purity(all_one)) == 0.5 and one(M.purity(singles)) == 1  # not 1 and not the majority
    for by in M.AVERAGES:
        assert one(M.nmi(all_one, average=by)) == 0
    perfect = df.withColumn("cluster", F.when(F.col("truth") == "a", 7).otherwise(9))
    assert one(M.nmi(perfect)) == pytest.approx(1) and one(M.nmi(perfect, average="printed_product")) == pytest.approx(1 / math.log(2))
    assert one(M.nmi(df)) == pytest.approx(one(M.nmi(df, "truth", "cluster")))
    assert M.pair_scores(perfect).first()["adjusted_rand"] == pytest.approx(1)
    both = df.withColumn("cluster", F.lit(1)).withColumn("truth", F.lit("x"))
    assert one(M.nmi(both)) == 1
    h = spark.createDataFrame([("r", 1, 5.0), ("r", 2, 3.0), ("r", 3, 1.0), ("s", 1, 2.0)], "run string, round int, loss double")
    rer = {(r["run"], r["round"]): r["rer"] for r in M.relative_error_ratio(h).collect()}
    assert rer == {("r", 1): 1, ("r", 2): 0.5, ("r", 3): 0, ("s", 1): 0}
    assert {r["run"]: r["rounds"] for r in M.rounds_to(h, 0.5).collect()} == {"r": 2, "s": 1}


def test_costs():
    m, p, n, bits = 20, 10_000, 20, 64
    codes = [100, 200, 300]
    assert C.training_bits(m, p, n) == m * p * 2 * n * 32
    assert C.total_bits(m, p, n, codes, bits) == C.training_bits(m, p, n) + 32 * m * p + 600 * 96
    assert C.total_bits(3, p, n, codes, bits) <= C.bound_bits(3, p, n, bits, [100, 250, 300]) <= C.bound_bits(3, p, n, bits)
    # the printed cost of the fourth and fifth synthetic sets lies where such networks put it
    assert 30 < C.to_megabytes(C.total_bits(20, 11_000, 20, [], 64)) < 37
    assert C.label_return_bits(codes, 16, 10) == 600 * 20 and C.raw_bits(10, 3) == 960
    slope = lambda f: math.log(f(1024, 64).n_params / f(512, 64).n_params, 2)
    assert slope(conv_encoder) == pytest.approx(1, abs=0.05) and 1.8 < slope(dense_encoder) < 2.1


def test_ledger_counts_what_spark_moved(spark):
    ledger = C.Ledger(spark)
    with ledger.counted("shuffle"):
        spark.range(20_000).repartition(7, "id").agg(F.sum("id")).collect()
    assert ledger.bytes["shuffle"]["shuffle_write"] > 10_000 and ledger.seconds["shuffle"] > 0
    ledger.rounds(4, 100, 5)
    assert ledger.sent == ledger.got == 8000 and ledger.rows_per_second("shuffle", 20_000) > 0


def test_pipeline_recovers_planted_classes(spark, orders, tmp_path):
    model = CodeGraphClustering(Settings(5, 64, train=TrainConfig(n_rounds=8))).fit(orders)
    out = checkpoint(model.transform(orders))
    assert out.count() == orders.count() and out.where("cluster is null").isEmpty()
    assert float(M.purity(out).first()[0]) > 0.95 and float(M.purity(out, "code").first()[0]) > 0.97
    model.write(str(tmp_path / "m"), spark)
    back = CodeGraphModel.read(str(tmp_path / "m"), spark)
    same = back.transform(orders).select("row_id", "cluster").exceptAll(out.select("row_id", "cluster"))
    assert same.isEmpty()
    again = CodeGraphClustering(Settings(5, 64, train=TrainConfig(n_rounds=0)), init=back).fit(orders)
    assert np.array_equal(again.theta, model.theta) and again.costs["n_rounds"] == 0
    capped = CodeGraphClustering(Settings(5, 64, max_codes=40, contract=True, train=TrainConfig(n_rounds=0)), init=back).fit(orders)
    assert capped.transform(orders).where("cluster is null").isEmpty() and len(capped.codes) == 40
    assert capped.degrees.sum() == orders.count() and capped.costs["n_codes"] == model.costs["n_codes"] > 40
    with pytest.raises(ValueError, match="distinct codes"):
        CodeGraphClustering(Settings(5, 64, max_codes=40, train=TrainConfig(n_rounds=0)), init=back).fit(orders)
    plain = CodeGraphClustering(Settings(5, 64, encoder="hyperplane")).fit(orders)
    assert plain.history == [] and plain.transform(orders).count() == orders.count()


def test_plans(spark, orders):
    """Vectors are not shuffled by encoding, and labels come by broadcast."""
    model = CodeGraphClustering(Settings(5, 16, encoder="hyperplane")).fit(orders)
    plan = model.encode(orders.select("row_id", "site_id", "vec"))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan
    plan = assign_clusters(model.encode(orders), model.code_labels(spark))._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan
    plan = model.transform(orders)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") == 1 and "Exchange" not in plan and "Join" not in plan
    assert site_profile(orders).agg(F.sum("n_rows")).first()[0] == orders.count()


def test_baselines_on_planted_classes(spark, orders):
    """What each finds is at least as pure as it has to be on well-parted classes; the costs are in the known order."""
    some = checkpoint(orders.where("row_id % 3 = 0"))
    bits = {}
    for name, run, least in (
        ("central_spectral", lambda: B.central_spectral(some, 5, gamma=0.001), 0.9),
        ("central_kmeans", lambda: B.central_kmeans(some, 5, seed=3), 0.6),
        ("kmeans_parallel", lambda: B.kmeans_parallel(some, 5), 0.7),
        ("partition_merge", lambda: B.partition_merge(some, 5), 0.9),
        ("density_representatives", lambda: B.density_representatives(some, lam=0.1), 0.9),
        ("hashed_density_peaks", lambda: B.hashed_density_peaks(some, 5), 0.7),
        ("subspace_models", lambda: B.subspace_models(some, 5), 0.9),
        ("gaussian_models", lambda: B.gaussian_models(some, 5), 0.9),
    ):
        got = run()
        joined = checkpoint(got.labels.join(some.select("row_id", "truth"), "row_id"))
        assert joined.count() == some.count() and joined.select("row_id").distinct().count() == some.count(), name
        assert float(M.purity(joined).first()[0]) >= least, name
        bits[name] = got.bits
    assert bits["hashed_density_peaks"] == max(bits.values())
    with pytest.raises(ValueError):
        B.central_spectral(some, 5, most_bytes=10)


def test_grid_and_percentile(spark):
    df = spark.createDataFrame([(i, 0, [float(i % 2 * 10) + 0.01 * i, 0.0]) for i in range(20)] + [(99, 0, [500.0, 0.0])], "row_id long, site_id int, vec array<double>")
    got = {r["row_id"]: r["cluster"] for r in B.grid_cells(df, [0, 1], 1.0, 2).labels.collect()}
    assert got[99] == -1 and got[0] == got[2] != got[1] == got[3]
    assert 0 < B.second_percentile(df) < 1
    flat = spark.range(3000).select(F.col("id").alias("row_id"), F.array(F.col("id") / 3000.0).alias("vec"))
    true = 1 - math.sqrt(1 - 0.02)  # of two uniform numbers
    assert B.second_percentile(flat, within=0.005) == pytest.approx(true, abs=0.004)
    assert matrix_of(df.select("vec").toArrow().column(0)).shape == (21, 2)


def test_hashed_density_peaks_large_bucket(spark):
    """A bucket that is cut into parts gives the densities and the labels of the whole bucket."""
    from codecut.operators import baselines as B

    x = np.random.default_rng(2).normal(size=(90, 3)) + np.repeat(np.eye(3) * 6, 30, axis=0)
    df = spark.createDataFrame([(i, i % 3, v.tolist()) for i, v in enumerate(x)], "row_id long, site_id int, vec array<double>").coalesce(1)
    whole, cut = (B.hashed_density_peaks(df, 3, layouts=1, hashes=1, width=1e6, eps=1.5, most=n).labels.collect() for n in (1000, 20))
    assert {r["row_id"]: r["cluster"] for r in cut} == {r["row_id"]: r["cluster"] for r in whole}
    rows = B._split_buckets(B.lsh_buckets(df, 1, 1, 1e6, 3), 20)
    near = (np.linalg.norm(x[:, None] - x[None], axis=2) <= 1.5).sum(1) - 1
    assert {r["row_id"]: r["rho"] for r in B.bucket_densities(rows, 1.5).collect()} == dict(enumerate(near))


def _few_codes(n=90, bits=12):
    rng = np.random.default_rng(4)
    centers = rng.integers(0, 1 << bits, 3)
    codes = np.unique([int(c) ^ (1 << int(a)) ^ (1 << int(b)) for c in centers for a, b in rng.integers(0, bits, (n, 2))])
    return codes.astype(np.int64), rng.integers(1, 9, len(codes)).astype(float)


@pytest.mark.parametrize("cut", ["symmetric", "random_walk", "unnormalized", "bisect"])
def test_cuts_without_the_matrix(spark, cut):
    """On both sides of the bound on dense matrices the same cut is made, with alpha and p heeded."""
    from codecut.plans.pipeline import cut_codes

    codes, degrees = _few_codes()
    for alpha, p in ((1.0, 1.0), (0.5, 3.0)):
        dense, value = cut_codes(spark, codes, degrees, 12, 3, cut, alpha=alpha, p=p)
        free, other = cut_codes(spark, codes, degrees, 12, 3, cut, alpha=alpha, p=p, dense_up_to=10)
        assert other == pytest.approx(value, rel=0.05), (alpha, p)
        same = (dense[:, None] == dense[None, :]) == (free[:, None] == free[None, :])
        assert same.mean() > 0.9


def test_blocked_weights_equal_the_matrix(spark):
    from codecut.operators.spectral import blocked_code_weights, code_weights
    from codecut.operators.spectral import cut_value as dense_cut

    codes, degrees = _few_codes()
    w = code_weights(codes, degrees, 12, 0.5, 2.0)
    b = blocked_code_weights(spark, codes, degrees, 12, 0.5, 2.0, block=17)
    x = np.random.default_rng(0).normal(size=(len(codes), 3))
    assert np.allclose(b.times(x), w @ x) and np.allclose(b.strengths(), w.sum(1))
    labels = codes % 4
    assert b.cut_value(labels) == pytest.approx(dense_cut(w, labels))
    rank = np.random.default_rng(1).permutation(len(codes))
    assert np.allclose(b.to_earlier(rank), (w * (rank[None, :] < rank[:, None])).sum(1))


def test_nearest_code_on_both_sides_of_its_bound(spark):
    from codecut.operators.encode import nearest_labels
    from codecut.operators.graph import contract_codes, nearest_code

    rng = np.random.default_rng(8)
    v = [(int(c), int(d)) for c, d in zip(np.unique(rng.integers(0, 1 << 20, 60)), rng.integers(1, 4, 60))]
    q = [(int(c),) for c in np.unique(rng.integers(0, 1 << 20, 80))]
    vertices, codes = spark.createDataFrame(v, "code long, degree long"), spark.createDataFrame(q, "code long")
    want = {c: min((bin(c ^ x).count("1"), -d, x) for x, d in v) for (c,) in q}
    for most in (1000, 10):
        got = {r["code"]: (r["distance"], r["near"]) for r in nearest_code(codes, vertices, most, 20).collect()}
        assert got == {c: (w[0], w[2]) for c, w in want.items()}
    known, degrees = (np.array(x) for x in zip(*v))
    assert nearest_labels(np.array([c for c, in q]), known, degrees, known).tolist() == [want[c][2] for c, in q]
    merged = contract_codes(vertices, 7, 20)
    assert merged.count() == 7 and merged.agg(F.sum("degree")).first()[0] == sum(d for _, d in v)


def test_pools_are_drawn_anew(spark, vectors):
    spec, drawn = linear_encoder(64, 8), []
    redraw = lambda r: drawn.append(r) or checkpoint(candidate_pool(vectors, 20, r))
    got = train_encoder(candidate_pool(vectors, 20), spec, TrainConfig(n_rounds=7, batch=8), refresh=redraw, refresh_every=3)
    assert drawn == [4, 7] and len(got.history) == 7
    seen = {tuple(v) for s in (0, 4, 7) for r in candidate_pool(vectors, 20, s).collect() for v in r["vecs"]}
    assert len(seen) > 2 * 5 * 20


def test_many_trainings_at_once_equal_single_ones(spark, vectors):
    from codecut.operators.train import code_purities, grid_search, train_many

    spec, pool = linear_encoder(64, 8), checkpoint(candidate_pool(vectors, 40))
    configs = [TrainConfig(n_rounds=n, batch=8, lam=x) for n, x in ((3, 1.0), (5, 5.0))]
    for c, many in zip(configs, train_many(pool, spec, configs, keep=(2,))):
        one = train_encoder(pool, spec, c, keep=(2,))
        assert np.allclose(one.params, many.params) and np.allclose(one.snapshots[2], many.snapshots[2])
        assert [h["loss"] for h in one.history] == pytest.approx([h["loss"] for h in many.history])
    cells = grid_search(pool, spec, TrainConfig(batch=8), (1.0, 5.0), (0.5, 5.0), (2, 4), lambda ps: code_purities(vectors, spec, ps))
    assert len(cells) == 8
    for c in cells[::3]:
        coded = encode(vectors, spec, c["params"])
        assert c["score"] == pytest.approx(float(M.purity(coded, "code").first()[0]))


def test_no_machine_local_folder_on_a_cluster():
    from types import SimpleNamespace

    from codecut.session import shared_dir

    conf = SimpleNamespace(get=lambda k: None)
    for master in ("spark://host:7077", "local-cluster[2,1,1024]", "yarn"):
        sc = SimpleNamespace(getCheckpointDir=lambda: None, getConf=lambda: conf, master=master)
        with pytest.raises(ValueError, match="spark.checkpoint.dir"):
            shared_dir(SimpleNamespace(sparkContext=sc))


def test_subspaces_of_one_mean_are_told_apart(spark):
    """Two planes through one point: only their directions differ."""
    rng = np.random.default_rng(1)
    rows = []
    for i in range(600):
        v = rng.normal(0, 0.05, 6)
        v[2 * (i % 2) : 2 * (i % 2) + 2] += rng.normal(0, 3, 2)
        rows.append((i, i // 2 % 3, v.tolist(), i % 2))
    df = checkpoint(spark.createDataFrame(rows, "row_id long, site_id int, vec array<double>, truth int"))
    for run in (B.subspace_models, B.gaussian_models):
        got = run(df, 2, local_k=8)
        assert float(M.purity(got.labels.join(df.select("row_id", "truth"), "row_id")).first()[0]) > 0.95, run.__name__
    assert float(M.purity(B.partition_merge(df, 2).labels.join(df.select("row_id", "truth"), "row_id")).first()[0]) < 0.9
    with pytest.raises(ValueError, match="bytes of models"):
        B.gaussian_models(df, 2, most_bytes=100)


def test_divergence_and_thresholds_written_out():
    rng = np.random.default_rng(2)
    pieces = [B.fit_piece(rng.normal(size=(40, 5)) * rng.uniform(0.3, 2, 5) + rng.normal(size=5), q, 0.9) for q in (1, 2, 3, 5)]
    full = [p.basis.T @ np.diag(p.var) @ p.basis + p.rest * (np.eye(5) - p.basis.T @ p.basis) for p in pieces]
    got = B.divergence(pieces)
    for a in range(4):
        for b in range(4):
            ia, ib, gap = np.linalg.inv(full[a]), np.linalg.inv(full[b]), pieces[a].mean - pieces[b].mean
            want = (np.trace(ia @ full[b]) + np.trace(ib @ full[a]) - 10 + gap @ (ia + ib) @ gap) / 2
            assert got[a, b] == pytest.approx(want, abs=1e-8)
    x = rng.normal(size=(9, 5))
    for p, c in zip(pieces, full):
        want = [(r - p.mean) @ np.linalg.inv(c) @ (r - p.mean) + np.linalg.slogdet(c)[1] for r in x]
        assert np.allclose(B.minus_log_likelihood(x, p), want)
    at = np.array([0.0, 1.0, 1.5, 9.0, 9.5, 30.0])
    dist = np.abs(at[:, None] - at[None, :])
    steps = B.delta_candidates(dist)
    assert steps.tolist() == [0.5, 0.5, 1.0, 7.5, 20.5]
    for step in steps:
        n = len(np.unique(B.join_within(dist, step)))
        assert n == 6 - (steps <= step).sum()
    even = np.ones(6)
    assert B.merge_by_delta(dist, even, 3).tolist() == [0, 0, 0, 1, 1, 2]
    assert B.merge_by_delta(dist, even, None).tolist() == [0, 0, 0, 1, 1, 2]
    assert B.merge_by_delta(dist, even, 2, delta=0.2).max() == 1
    assert B.merge_by_delta(dist, np.array([5, 5, 5, 5, 5, 0.1]), 2).tolist() == [0, 0, 0, 1, 1, 1]


def test_seeding_and_central_methods_at_any_size(spark, orders):
    some = checkpoint(orders.where("row_id % 4 = 0"))
    taken, weights = B.oversampled_seeds(some, 5, rounds=2, factor=2.0)
    assert 5 <= len(taken) < 60 and weights.sum() == some.count()
    assert np.array_equal(taken, B.oversampled_seeds(some.repartition(5), 5, rounds=2, factor=2.0)[0])
    small, blocked = B.central_spectral(some, 5, gamma=0.001), B.central_spectral(some, 5, gamma=0.001, dense_up_to=50)
    a = {r["row_id"]: r["cluster"] for r in small.labels.collect()}
    b = {r["row_id"]: r["cluster"] for r in blocked.labels.collect()}
    assert len({(a[i], b[i]) for i in a}) == 5


def test_divergence_of_many_directions_is_made_of_matrices(monkeypatch):
    """Of pieces that keep many directions no two bases are multiplied: the work was the square of all directions."""
    from codecut.operators import baselines as B

    rng = np.random.default_rng(4)
    pieces = [B.fit_piece(rng.normal(size=(60, 24)) * rng.uniform(0.5, 2, 24) + rng.normal(size=24), 24 if i % 3 else 18, 0.9) for i in range(7)]
    cov = [p.basis.T @ np.diag(p.var - p.rest) @ p.basis + p.rest * np.eye(24) for p in pieces]
    far = lambda a, b: np.trace(np.linalg.inv(cov[a]) @ cov[b]) + (d := pieces[b].mean - pieces[a].mean) @ np.linalg.inv(cov[a]) @ d - 24
    want = np.array([[max((far(a, b) + far(b, a)) / 2, 0) for b in range(7)] for a in range(7)])
    called, traces = [], B._traces
    monkeypatch.setattr(B, "_traces", lambda p: (called.append(len(p)), traces(p, 3 * 8 * 24 * 24))[1])
    assert np.allclose(B.divergence(pieces), want, atol=1e-6) and called == [7]


def test_quantile_of_broadcast_pairs(spark):
    from codecut.operators import baselines as B

    x = np.random.default_rng(6).normal(size=(1600, 5))
    df = spark.createDataFrame([(i * 7, v.tolist()) for i, v in enumerate(x)], "row_id long, vec array<double>")
    assert B.second_percentile(df, within=0.01) == pytest.approx(B.second_percentile(df, within=0.01, broadcast_bytes=0))


def test_likelihoods_of_all_pieces():
    rng = np.random.default_rng(9)
    x = rng.normal(size=(700, 12)) + 40
    pieces = [B.fit_piece(x[i::5] * (1 + i / 3), q, 0.9) for i, q in enumerate((None, 12, 1, 5, None))]
    assert np.allclose(B.minus_log_likelihoods(x, pieces, 500), np.stack([B.minus_log_likelihood(x, p) for p in pieces], 1))


def test_methods_side_by_side_as_in_turn(spark, monkeypatch):
    """Lanes give the rows that the methods give in turn, in their order, from one distance quantile a set."""
    from codecut.plans import queries_workloads as W

    rng = np.random.default_rng(2)
    sets = []
    for name, n in (("a", 90), ("b", 60)):
        rows = [(i, i % 2, (rng.normal(size=4) * 0.2 + 5 * (i % 3)).tolist(), str(i % 3)) for i in range(n)]
        sets.append((name, spark.createDataFrame(rows, "row_id long, site_id int, vec array<double>, truth string"), 3, W.Settings(3, 8, hidden=(8,), train=W._rounds(2))))
    drawn, whole = [], W.B.second_percentile
    monkeypatch.setattr(W.B, "second_percentile", lambda *a, **kw: (drawn.append(1), whole(*a, **kw))[1])
    got = W.compare_all(sets, W.DISTRIBUTED, W.LANES)
    assert len(drawn) == 2
    want = [r for name, df, k, s in sets for r in W.compare(df, k, s, W.DISTRIBUTED, name)]
    assert [r[:2] for r in got] == [r[:2] for r in want]
    assert np.allclose([r[2:] for r in got], [r[2:] for r in want])
    some = spark.createDataFrame([("x", "p", 3), ("x", "q", 1), ("y", "q", 2)], "cluster string, truth string, n long")
    each = spark.createDataFrame([("x", "p")] * 3 + [("x", "q")] + [("y", "q")] * 2, "cluster string, truth string")
    assert W.M.purity(some, count="n").first() == W.M.purity(each).first() and np.isclose(W.M.nmi(some, count="n").first()[0], W.M.nmi(each).first()[0])
