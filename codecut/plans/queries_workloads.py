"""The experiment workloads. Data sets, sites, methods and parameters are the published ones; rows per synthetic cluster are arguments, small where registered."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import cost as C
from ..operators import metrics as M
from ..operators.encode import encode, site_degrees
from ..operators.features import char_ngram_vectors, fit_normalizer, html_features, planted_vectors
from ..operators.network import conv_encoder, dense_encoder
from ..operators.sampling import candidate_pool
from ..operators.sites import assign_sites
from ..operators.train import TrainConfig, code_purities, grid_search, train_encoder, train_many
from ..session import checkpoint, read_table
from ..sources.gaussians import subspace_dataset, waveform_dataset
from .pipeline import CodeGraphClustering, Settings
from .queries_method import LAMBDAS, ROUNDS, document_vectors, vectors
from .registry import query


def _measures(labels: DataFrame, df: DataFrame) -> tuple[float, float]:
    both = labels.select("row_id", "cluster").join(df.select("row_id", "truth"), "row_id")
    cells = checkpoint(M.contingency(both).coalesce(1))  # the rows are joined and counted once
    return tuple(float(x) for x in M.purity(cells, count="n").crossJoin(M.nmi(cells, count="n")).first())


def measured(df: DataFrame, k: int, settings: Settings, m: str, name: str, **kw) -> tuple:
    """(data, method, purity, nmi, megabytes) of one method on df(row_id, site_id, vec, truth)."""
    if m == "code_graph":
        model = CodeGraphClustering(settings).fit(df)
        labels, bits = model.transform(df), model.costs["total_bits"]
    else:
        kw |= {} if m in ("density_representatives",) else {"k": k}
        got = getattr(B, m)(df, **kw)
        labels, bits = got.labels, got.bits
    return (name, m, *_measures(labels, df), bits / 8e6)


def compare(df: DataFrame, k: int, settings: Settings, methods: tuple[str, ...], name: str) -> list[tuple]:
    """A row of ``measured`` for each method."""
    df = checkpoint(df)
    return [measured(df, k, settings, m, name) for m in methods]


def compare_all(sets: list[tuple[str, DataFrame, int, Settings]], methods: tuple[str, ...], lanes: tuple[tuple[str, ...], ...]) -> list[tuple]:
    """``compare`` of each of the sets, in this order, but with the methods in lanes side by side.

    Many methods wait for the driver, or for one task, most of their time. A lane runs one method at a time, set after set,
    so that no more than one of its results is held; those that send large models to the driver share a lane. A set is made
    once, and so is its distance quantile, for all methods that take it.
    """
    spark = sets[0][1].sparkSession
    quantiles = {"density_representatives", "hashed_density_peaks"}.intersection(methods)
    rest = tuple(m for m in methods if not any(m in lane for lane in lanes))
    lanes = [[m for m in lane if m in methods] for lane in (*lanes, rest)]

    def run(lane: list[str]) -> list[tuple]:
        out = []
        for i, (name, _, k, settings) in enumerate(sets):
            for m in lane:
                kw = {"eps": eps[i].result()} if m in quantiles else {}
                out.append(measured(made[i].result(), k, settings, m, name, **kw))
        return out

    with ThreadPoolExecutor(1) as first, ThreadPoolExecutor(1) as second, ThreadPoolExecutor(len(lanes)) as pool:
        made = [first.submit(inheritable_thread_target(spark)(checkpoint), df) for _, df, _, _ in sets]
        eps = [second.submit(inheritable_thread_target(spark)(lambda one: B.second_percentile(one.result())), one) for one in made if quantiles]
        rows = [r for f in [pool.submit(inheritable_thread_target(spark)(run), lane) for lane in lanes if lane] for r in f.result()]
    at = {r[:2]: r for r in rows}
    return [at[name, m] for name, *_ in sets for m in methods]


_SHAPE = "data string, method string, purity double, nmi double, megabytes double"
CENTRAL = ("code_graph", "central_spectral", "central_kmeans")
DISTRIBUTED = ("code_graph", "kmeans_parallel", "partition_merge", "density_representatives", "hashed_density_peaks", "subspace_models", "gaussian_models")
LANES = (("hashed_density_peaks",), ("gaussian_models", "subspace_models"), ("code_graph",), ("kmeans_parallel", "partition_merge", "density_representatives"))


def _rounds(n: int, **kw) -> TrainConfig:
    return TrainConfig(n_rounds=n, **kw)


def central_comparison(spark: SparkSession, sf_dir: str, rounds: int = 10) -> list[tuple]:
    """Against the central methods: languages and quality of documents, categories of parts, waveforms, labels of embeddings; short codes, as published."""
    parts = assign_sites(planted_vectors(read_table(spark, sf_dir, "part", "p_partkey", "p_type"), "p_type", "p_partkey"), "row_id", 10)
    waves = assign_sites(waveform_dataset(spark, 1000), "row_id", 10)
    docs = document_vectors(spark, sf_dir)
    known = read_table(spark, sf_dir, "labels", "doc_id", "quality").where("quality is not null").groupBy(F.col("doc_id").cast("long").alias("row_id")).agg(F.min("quality").alias("truth"))
    quality = docs.drop("truth").join(known, "row_id")
    out = []
    for name, df, k, bits in (("documents", docs, 4, 8), ("document quality", quality, 2, 4), ("parts", parts, 6, 12), ("waveforms", waves, 3, 4), ("embeddings", vectors(spark, sf_dir), 10, 12)):
        out += compare(df, k, Settings(k, bits, train=_rounds(rounds)), CENTRAL, name)
    return out


@query()
def w1_central_comparison(spark, d):
    return spark.createDataFrame(central_comparison(spark, d), _SHAPE)


def convergence(spark: SparkSession, sets=(1, 2, 3, 4, 5), site_counts=(20, 40, 60, 80, 100), rounds: int = 20, per_latent: int = 1, per_cluster: int = 40, bits: int = 64) -> DataFrame:
    """``run, round, loss, rer, rounds_to_tenth``: relative error of the loss by round, data set and number of sites, and the first round at which it is a tenth.

    All trainings of a set run side by side, a job a round.
    """
    history = []
    for j in sets:
        data = checkpoint(subspace_dataset(spark, j, per_latent, per_cluster))
        norm, pools = fit_normalizer(data), None
        for i, n in enumerate(site_counts):
            one = candidate_pool(assign_sites(data, "row_id", n), 512).withColumn("config", F.lit(i))
            pools = one if pools is None else pools.union(one)
        got = train_many(checkpoint(pools), conv_encoder(2 ** (j + 5), bits), [_rounds(rounds)] * len(site_counts), norm)
        history += [(f"S{j}, {n} sites", h["round"], h["loss"]) for n, g in zip(site_counts, got) for h in g.history]
    table = spark.createDataFrame(history, "run string, round int, loss double")
    return M.relative_error_ratio(table).join(M.rounds_to(table, 0.1).withColumnRenamed("rounds", "rounds_to_tenth"), "run")


@query()
def w2_convergence(spark, d):
    return convergence(spark, site_counts=(20, 60, 100), rounds=10)


def synthetic_comparison(spark: SparkSession, sets=(1, 2, 3, 4, 5), per_latent: int = 1, per_cluster: int = 128, n_sites: int = 20, rounds: int = 20, encoder: str = "conv") -> list[tuple]:
    """Five distributed baselines on the five synthetic sets; the full sizes are per_latent 20 and per_cluster 2500."""
    out = []
    for j in sets:
        df = assign_sites(subspace_dataset(spark, j, per_latent, per_cluster), "row_id", n_sites)
        k = per_latent * (j + 5)
        out += compare(df, k, Settings(k, 64, encoder=encoder, train=_rounds(rounds)), DISTRIBUTED, f"S{j}")
    return out


@query()
def w3_synthetic_comparison(spark, d):
    return spark.createDataFrame(synthetic_comparison(spark), _SHAPE)


def table_comparison(spark: SparkSession, sf_dir: str, rounds: int = 8) -> list[tuple]:
    """All distributed methods on four tables: embeddings, documents and pages (256 components), turns of conversations (128)."""
    lang = html_features(read_table(spark, sf_dir, "pages", "page_id", "url", "html")).select("row_id", F.col("lang").alias("truth"))
    pages = char_ngram_vectors(read_table(spark, sf_dir, "pages", "page_id", "html"), "page_id", "html", 1, 256).join(lang, "row_id")
    turns = read_table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text").withColumn("id", F.col("conv_id").cast("long") * 10_000 + F.col("turn").cast("long")).dropDuplicates(["id"])
    said = char_ngram_vectors(turns, "id", "text", 1, 128).join(turns.select(F.col("id").alias("row_id"), F.col("role").alias("truth")), "row_id")
    sets = (
        ("embeddings", vectors(spark, sf_dir), 10, 16),
        ("documents", document_vectors(spark, sf_dir, 256), 4, 16),
        ("pages", assign_sites(pages, "row_id", 10), 4, 8),
        ("conversations", assign_sites(said, "row_id", 10), 3, 8),
    )
    return compare_all([(name, df, k, Settings(k, bits, hidden=(64,), train=_rounds(rounds))) for name, df, k, bits in sets], DISTRIBUTED, LANES)


@query()
def w4_table_comparison(spark, d):
    return spark.createDataFrame(table_comparison(spark, d), _SHAPE)


def cost_by_dimension(spark: SparkSession, sets=(1, 2, 3, 4, 5), per_cluster: int = 60, n_sites: int = 20, rounds: int = 20, bits: int = 64) -> list[tuple]:
    """(dimension, method, megabytes) with what was measured: distinct codes a site, pieces a site and the directions they keep, candidates of the seeding, representatives."""
    rows = []
    for j in sets:
        df = checkpoint(assign_sites(subspace_dataset(spark, j, 1, per_cluster), "row_id", n_sites))
        dim, k, n = 2 ** (j + 5), j + 5, (j + 5) * per_cluster
        for kind in ("dense", "conv"):
            if kind == "conv" or j <= 2:  # codes are measured with trained convolutions; dense stacks of wide inputs share their counts
                model = CodeGraphClustering(Settings(k, bits, encoder=kind, train=_rounds(5))).fit(df)
                by_site = model.costs["codes_by_site"]
            spec = dense_encoder(dim, bits) if kind == "dense" else conv_encoder(dim, bits)
            rows.append((dim, f"code_graph_{kind}", C.total_bits(n_sites, spec.n_params, rounds, by_site, bits) / 8e6))
        for m in ("kmeans_parallel", "partition_merge", "density_representatives", "subspace_models", "gaussian_models"):
            rows.append((dim, m, getattr(B, m)(df, **({} if m == "density_representatives" else {"k": k})).bits / 8e6))
        for m in ("central", "hashed_density_peaks"):
            rows.append((dim, m, C.baseline_bits(m, n_rows=n, dim=dim, n_sites=n_sites, k=k) / 8e6))
    return rows


@query()
def w5_cost_by_dimension(spark, d):
    return spark.createDataFrame(cost_by_dimension(spark, sets=(1, 2, 3)), "dim int, method string, megabytes double")


@query()
def w6_parameter_search(spark, d):
    """Loss and purity of codes in every cell of lambda, t and rounds (6 x 6 x 4): 36 trainings side by side, all 144 encoders scored in one pass over all rows."""
    df = checkpoint(vectors(spark, d))
    norm, spec = fit_normalizer(df), dense_encoder(64, 16)
    pool = checkpoint(candidate_pool(df, 512))
    cells = grid_search(pool, spec, TrainConfig(), LAMBDAS, LAMBDAS, ROUNDS, lambda params: code_purities(df, spec, params, norm), norm)
    return spark.createDataFrame([(c["lam"], c["t"], c["n_rounds"], c["loss"], c["score"]) for c in cells], "lam double, t double, n_rounds int, loss double, code_purity double")


@query()
def w6_density_search(spark, d):
    """The density representatives' own parameter over its published values."""
    df = checkpoint(vectors(spark, d))
    eps = B.second_percentile(df)
    rows = []
    for lam in (0.01, 0.05, 0.1, 0.5, 1.0):
        got = B.density_representatives(df, eps, lam)
        rows.append((lam, *_measures(got.labels, df), got.models, got.bits / 8e6))
    return spark.createDataFrame(rows, "lam double, purity double, nmi double, n_models long, megabytes double")


@query()
def w7_code_length(spark, d):
    """Codes, purity of codes, purity of clusters and cost as the code grows."""
    df = checkpoint(assign_sites(planted_vectors(read_table(spark, d, "orders", "o_orderkey", "o_orderpriority"), "o_orderpriority", "o_orderkey"), "row_id", 10))
    rows = []
    for bits in (4, 8, 12, 16, 24, 32, 64):
        model = CodeGraphClustering(Settings(5, bits, train=_rounds(8))).fit(df)
        out = checkpoint(model.transform(df))
        rows.append((bits, model.costs["n_codes"], float(M.purity(out, "code").first()[0]), float(M.purity(out).first()[0]), model.costs["total_bits"] / 8e6))
    return spark.createDataFrame(rows, "bits int, n_codes long, code_purity double, purity double, megabytes double")


@query()
def w8_selector_ablation(spark, d):
    """Relative error by round with batches that differ and with uniform ones, on the orders and on a synthetic set."""
    orders = assign_sites(planted_vectors(read_table(spark, d, "orders", "o_orderkey", "o_orderpriority"), "o_orderpriority", "o_orderkey"), "row_id", 10)
    rows = []
    for name, df in (("orders", orders), ("S1", assign_sites(subspace_dataset(spark, 1, 2, 60), "row_id", 10))):
        pool = checkpoint(candidate_pool(df, 512))
        got = train_many(pool, dense_encoder(64, 32), [_rounds(12, selector=s) for s in ("diverse", "uniform")], fit_normalizer(df))
        rows += [(f"{name}, {s}", h["round"], h["loss"]) for s, g in zip(("diverse", "uniform"), got) for h in g.history]
    return M.relative_error_ratio(spark.createDataFrame(rows, "run string, round int, loss double"))


@query()
def w9_encoder_cost(spark, d):
    """Dense against convolutional and linear encoders: parameters, cost and purity on the orders and on a synthetic set."""
    orders = assign_sites(planted_vectors(read_table(spark, d, "orders", "o_orderkey", "o_orderpriority"), "o_orderpriority", "o_orderkey"), "row_id", 10)
    rows = []
    for name, df, k in (("orders", orders, 5), ("S2", assign_sites(subspace_dataset(spark, 2, 1, 60), "row_id", 10), 7)):
        df = checkpoint(df)
        for kind in ("dense", "conv", "linear"):
            model = CodeGraphClustering(Settings(k, 64, encoder=kind, train=_rounds(8))).fit(df)
            rows.append((name, kind, model.spec.n_params, model.costs["total_bits"] / 8e6, float(M.purity(model.transform(df)).first()[0])))
    return spark.createDataFrame(rows, "data string, encoder string, n_params long, megabytes double, purity double")


@query()
def w10_pretrained_start(spark, d):
    """An encoder of another table (pages) on the documents: no rounds, a few, and as many from a random start."""
    pages = assign_sites(char_ngram_vectors(read_table(spark, d, "pages", "page_id", "html"), "page_id", "html", 1, 64), "row_id", 10)
    df = checkpoint(document_vectors(spark, d))
    first = CodeGraphClustering(Settings(4, 64, max_codes=10_000_000, train=_rounds(10))).fit(pages)
    rows = []
    for start, n in (("pages", 0), ("pages", 5), ("random", 5)):
        m = CodeGraphClustering(Settings(4, 64, max_codes=10_000_000, train=_rounds(n)), init=first if start == "pages" else None).fit(df)
        p, q = _measures(m.transform(df), df)
        rows.append((start, n, p, q, m.costs["total_bits"] / 8e6))
    return spark.createDataFrame(rows, "start string, n_rounds int, purity double, nmi double, megabytes double")


@query()
def w12_unequal_sites(spark, d):
    """Loss by round with sites of very different sizes, averaged equally and by batch."""
    df = assign_sites(vectors(spark, d).drop("site_id"), "row_id", weights=[50, 25, 10, 5, 5, 3, 1, 1])
    pool = checkpoint(candidate_pool(df, 512))
    got = train_many(pool, dense_encoder(64, 16), [replace(_rounds(8), weighting=w) for w in ("equal", "batch")], fit_normalizer(df))
    rows = [(w, h["round"], h["loss"]) for w, g in zip(("equal", "batch"), got) for h in g.history]
    return spark.createDataFrame(rows, "run string, round int, loss double")


@query()
def code_rates(spark, d):
    """Distinct codes a site against rows, of untrained and trained encoders: what training does to the number of codes."""
    from ..operators.network import init_params

    df = vectors(spark, d)
    norm = fit_normalizer(df)
    spec = dense_encoder(64, 16)
    pool = checkpoint(candidate_pool(df, 512))
    out = None
    for name, p in (("untrained", init_params(spec, 0)), ("trained", train_encoder(pool, spec, _rounds(8), norm).params)):
        one = site_degrees(encode(df.select("site_id", "vec"), spec, p, norm)).agg(F.count("*").alias("n_codes"), F.sum("degree").alias("n_rows")).withColumn("encoder", F.lit(name))
        out = one if out is None else out.union(one)
    return out


@query()
def w11_online(spark, d):
    """One round a micro-batch, with cuts along the way."""
    from .queries_streams import stream_online_round

    return stream_online_round(spark, d)
