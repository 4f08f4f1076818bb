"""Queries of the method, its measures, its costs and its baselines, over whole tables.

Where results have to be the same in two engines, vectors are quantised to integers and codes come
from a closed-form integer encoder; after that everything is exact.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..functions.bits import code_l1, hamming, pack_bits, unpack_bits
from ..operators import baselines as B
from ..operators import cost as C
from ..operators import metrics as M
from ..operators.encode import code_usage as usage
from ..operators.encode import encode, encode_fixed, merge_degrees
from ..operators.encode import site_degrees as degrees_by_site
from ..operators.features import Normalizer, char_ngram_vectors, fit_normalizer, html_features, normalize, planted_vectors, profile, text_shape
from ..operators.graph import cap_codes, canonical_labels, cut_value, graph_components, hamming_join, knn_codes
from ..operators.graph import edge_weights as weights
from ..operators.graph import nearest_code as nearest
from ..operators.graph import vertex_strength as strength
from ..operators.loss import loss_gradient, pair_loss
from ..operators.network import conv_encoder, dense_encoder, forward, linear_encoder
from ..operators.sampling import candidate_pool
from ..operators.sites import assign_sites, check_vectors
from ..operators.sites import site_profile as sites_of
from ..operators.train import TrainConfig, history_frame
from ..session import checkpoint, read_table
from .pipeline import CodeGraphClustering, Settings
from .registry import query

DIM, SITES = 64, 10


def vectors(spark, d) -> DataFrame:
    e = read_table(spark, d, "embeddings", "vec_id", "embedding", "label")
    return e.select(F.col("vec_id").cast("long").alias("row_id"), F.pmod("vec_id", F.lit(SITES)).cast("int").alias("site_id"), F.col("embedding").alias("vec"), F.col("label").alias("truth"))


def quantised(spark, d) -> DataFrame:
    return vectors(spark, d).select("row_id", "site_id", "truth", V.quantize(F.col("vec")).alias("q"))


def coded(spark, d, bits: int) -> DataFrame:
    return quantised(spark, d).select("row_id", "site_id", "truth", encode_fixed(F.col("q"), DIM, bits).alias("code"))


Q_SQL = f"""q AS (SELECT CAST(vec_id AS BIGINT) AS row_id, CAST(vec_id % {SITES} AS INTEGER) AS site_id, label AS truth,
  list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 4096) AS BIGINT)) AS v FROM embeddings)"""
L_SQL = Q_SQL + ", l AS (SELECT row_id, site_id, truth, unnest(v) AS x, generate_subscripts(v, 1) - 1 AS i FROM q)"


def code_sql(bits: int) -> str:
    return (
        L_SQL
        + f""", s AS (SELECT row_id, site_id, truth, b, sum(x * ((((i + 1) * (b * b + 3 * b + 7) + i * i * (b + 5)) % 23) - 11)) AS s
  FROM l, range(0, {bits}) AS t(b) GROUP BY ALL),
 c AS (SELECT row_id, site_id, truth, CAST(sum(CASE WHEN s < 0 THEN 0::HUGEINT WHEN b = 63 THEN -9223372036854775808::HUGEINT
  ELSE (1::HUGEINT << CAST(b AS INTEGER)) END) AS BIGINT) AS code FROM s GROUP BY ALL)"""
    )


DEG_SQL = ", d AS (SELECT site_id, code, count(*) AS degree FROM c GROUP BY ALL), v AS (SELECT code, CAST(sum(degree) AS BIGINT) AS degree FROM d GROUP BY ALL)"
EDGE_SQL = ", e AS (SELECT a.code AS src, b.code AS dst, CAST(a.degree AS DOUBLE) * b.degree / bit_count(xor(a.code, b.code)) AS weight FROM v a JOIN v b ON a.code < b.code)"
BOTH_SQL = ", w AS (SELECT src, dst, weight FROM e UNION ALL SELECT dst, src, weight FROM e)"

# sites and vectors


@query(f"SELECT CAST(vec_id AS BIGINT) AS row_id, CAST(vec_id % {SITES} AS INTEGER) AS site_id FROM embeddings")
def site_assign_mod(spark, d):
    u = (F.pmod(F.col("row_id"), F.lit(SITES)) + 0.5) / float(SITES)
    return assign_sites(vectors(spark, d).drop("site_id"), "row_id", weights=[1.0] * SITES, uniform=u).select("row_id", "site_id")


@query(f"SELECT CAST(vec_id % {SITES} AS INTEGER) AS site_id, count(*) AS n_rows, CAST(sum(4 * len(embedding)) AS BIGINT) AS vector_bytes FROM embeddings GROUP BY 1")
def site_profile(spark, d):
    return sites_of(vectors(spark, d))


@query("""SELECT CAST(vec_id AS BIGINT) AS row_id, CASE WHEN u < 0.5 THEN 0 WHEN u < 0.75 THEN 1 WHEN u < 0.9 THEN 2 ELSE 3 END AS site_id
  FROM (SELECT vec_id, (vec_id * 7919 % 1000) / 1000.0::DOUBLE AS u FROM embeddings)""")
def site_unequal(spark, d):
    u = F.pmod(F.col("row_id") * 7919, F.lit(1000)) / 1000.0
    return assign_sites(vectors(spark, d).drop("site_id"), "row_id", weights=[50, 25, 15, 10], uniform=u).select("row_id", "site_id")


@query(f"""SELECT CAST(dense_rank() OVER (ORDER BY source) - 1 AS INTEGER) AS site_id, source, count(*) AS n_rows FROM documents GROUP BY source""")
def site_by_column(spark, d):
    docs = read_table(spark, d, "documents", "doc_id", "source")
    return assign_sites(docs, by="source").groupBy("site_id", "source").agg(F.count("*").alias("n_rows"))


def _as_vec(spark, d) -> DataFrame:
    return quantised(spark, d).select("row_id", F.col("q").cast("array<double>").alias("vec"))


@query(f"WITH {L_SQL} SELECT CAST(i AS INTEGER) AS i, round(avg(x), 6) AS mean, round(stddev_pop(x), 6) AS sd, CAST(min(x) AS DOUBLE) AS low, CAST(max(x) AS DOUBLE) AS high FROM l GROUP BY i")
def vec_stats(spark, d):
    n = fit_normalizer(_as_vec(spark, d), "zscore")
    return spark.createDataFrame([(i, round(m, 6), round(x, 6), lo, hi) for i, (m, x, lo, hi) in enumerate(zip(n.mean, n.sd, n.low, n.high))], "i int, mean double, sd double, low double, high double")


def _normalized(spark, d, kind: str) -> DataFrame:
    v = _as_vec(spark, d)
    return normalize(v, fit_normalizer(v, kind)).select("row_id", F.posexplode("vec").alias("i", "x")).select("row_id", "i", F.round("x", 6).alias("x"))


@query(f"WITH {L_SQL} SELECT row_id, CAST(i AS INTEGER) AS i, round(x / sqrt(CAST(sum(x * x) OVER (PARTITION BY row_id) AS DOUBLE)), 6) AS x FROM l")
def vec_l2norm(spark, d):
    return _normalized(spark, d, "l2")


_STATS = ", m AS (SELECT i, CAST(sum(x) AS DOUBLE) / count(*) AS mean, CAST(sum(x * x) AS DOUBLE) / count(*) AS sq, min(x) AS lo, max(x) AS hi FROM l GROUP BY i)"


@query(f"WITH {L_SQL}{_STATS} SELECT row_id, CAST(i AS INTEGER) AS i, round((x - mean) / sqrt(sq - mean * mean), 6) AS x FROM l JOIN m USING (i)")
def vec_zscore(spark, d):
    return _normalized(spark, d, "zscore")


@query(f"WITH {L_SQL}{_STATS} SELECT row_id, CAST(i AS INTEGER) AS i, round((x - mean) / sqrt(sq - mean * mean) / 8, 6) AS x FROM l JOIN m USING (i)")
def vec_zscore_sqrt_dim(spark, d):
    return _normalized(spark, d, "zscore_sqrt_dim")


@query(f"WITH {L_SQL}{_STATS} SELECT row_id, CAST(i AS INTEGER) AS i, round(CAST(x - lo AS DOUBLE) / (hi - lo), 6) AS x FROM l JOIN m USING (i)")
def vec_minmax(spark, d):
    return _normalized(spark, d, "minmax")


@query("SELECT CAST(vec_id AS BIGINT) AS row_id, len(embedding) <> 64 OR list_bool_or(list_transform(embedding, lambda x: x IS NULL OR isnan(x))) OR vec_id % 7 = 0 AS bad FROM embeddings")
def checked_vectors(spark, d):
    """Every seventh vector is cut short, and has to be found."""
    v = vectors(spark, d).withColumn("vec", F.when(F.col("row_id") % 7 == 0, F.slice("vec", 1, 5)).otherwise(F.col("vec")))
    return check_vectors(v, DIM, "quarantine").select("row_id", "bad")


@query(f"WITH {L_SQL} SELECT row_id, CAST(i AS INTEGER) AS i, x AS q FROM l")
def vec_quantize(spark, d):
    return quantised(spark, d).select("row_id", F.posexplode("q").alias("i", "q"))


_PAIR = ", p AS (SELECT row_id, v, lead(row_id) OVER (PARTITION BY site_id ORDER BY row_id) AS other, lead(v) OVER (PARTITION BY site_id ORDER BY row_id) AS u FROM q)"


def _consecutive(df: DataFrame, *columns: str) -> DataFrame:
    """Each row with the next one of its site."""
    w = Window.partitionBy("site_id").orderBy("row_id")
    return df.select("row_id", *columns, F.lead("row_id").over(w).alias("other"), *[F.lead(c).over(w).alias(f"next_{c}") for c in columns]).where("other is not null")


@query(f"WITH {Q_SQL}{_PAIR} SELECT row_id, other, round(sqrt(CAST(list_sum(list_transform(list_zip(v, u), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS DOUBLE)) / 4096, 6) AS distance FROM p WHERE other IS NOT NULL")
def vec_pair_distance(spark, d):
    p = _consecutive(quantised(spark, d), "q")
    diff = F.zip_with("q", "next_q", lambda a, b: a - b)
    return p.select("row_id", "other", F.round(F.sqrt(V.int_dot(diff, diff).cast("double")) / 4096, 6).alias("distance"))


@query(f"WITH {Q_SQL}{_PAIR} SELECT row_id, other, CAST(list_sum(list_transform(list_zip(v, u), lambda z: z[1] * z[2])) AS BIGINT) AS dot, CAST(list_sum(list_transform(list_zip(v, u), lambda z: abs(z[1] - z[2]))) AS BIGINT) AS l1 FROM p WHERE other IS NOT NULL")
def vec_algebra(spark, d):
    p = _consecutive(quantised(spark, d), "q")
    return p.select("row_id", "other", V.int_dot(F.col("q"), F.col("next_q")).alias("dot"), V.l1(F.col("q"), F.col("next_q")).cast("long").alias("l1"))


# codes


@query(f"WITH {code_sql(16)} SELECT row_id, site_id, code FROM c")
def fixed_codes_16(spark, d):
    return coded(spark, d, 16).select("row_id", "site_id", "code")


@query(f"WITH {code_sql(64)} SELECT row_id, site_id, code FROM c")
def fixed_codes_64(spark, d):
    return coded(spark, d, 64).select("row_id", "site_id", "code")


def _linear_map(bits: int) -> np.ndarray:
    """The closed-form integer directions as parameters of a linear encoder."""
    b, i = np.meshgrid(np.arange(bits), np.arange(DIM))
    return np.concatenate([(((i + 1) * (b * b + 3 * b + 7) + i * i * (b + 5)) % 23 - 11).astype(float).ravel(), np.zeros(bits)])


@query(f"WITH {code_sql(64)} SELECT row_id, site_id, code FROM c")
def encoder_codes(spark, d):
    """Codes by the numpy encoder in the scan's stage."""
    v = quantised(spark, d).select("row_id", "site_id", F.col("q").cast("array<double>").alias("vec"))
    return encode(v, linear_encoder(DIM, 64), _linear_map(64))


@query(f"WITH {code_sql(16)} SELECT row_id, code, code AS packed, CAST(bit_count(code) AS INTEGER) AS ones FROM c")
def pack_unpack(spark, d):
    bits = coded(spark, d, 16).select("row_id", "code", unpack_bits(F.col("code"), 16).alias("bits"))
    return bits.select("row_id", "code", pack_bits(F.col("bits")).alias("packed"), F.aggregate("bits", F.lit(0), lambda a, b: a + b).alias("ones"))


@query(f"WITH {code_sql(64)}, p AS (SELECT row_id, code, lead(row_id) OVER w AS other, lead(code) OVER w AS next FROM c WINDOW w AS (PARTITION BY site_id ORDER BY row_id)) SELECT row_id, other, CAST(bit_count(xor(code, next)) AS INTEGER) AS hamming, CAST(2 * bit_count(xor(code, next)) AS INTEGER) AS l1 FROM p WHERE other IS NOT NULL")
def hamming_pairs(spark, d):
    p = _consecutive(coded(spark, d, 64), "code")
    return p.select("row_id", "other", hamming(F.col("code"), F.col("next_code")).alias("hamming"), code_l1(F.col("code"), F.col("next_code")).alias("l1"))


@query(f"WITH {code_sql(16)}{DEG_SQL} SELECT * FROM d")
def site_degrees(spark, d):
    return degrees_by_site(coded(spark, d, 16))


@query(f"WITH {code_sql(16)}{DEG_SQL} SELECT * FROM v")
def merged_degrees(spark, d):
    return merge_degrees(site_degrees(spark, d))


@query(f"WITH {code_sql(16)}{DEG_SQL} SELECT count(*) AS n_codes, count(*) / 65536.0::DOUBLE AS share_of_codes, round(sum(-(degree / n) * ln(degree / n)), 6) AS entropy FROM (SELECT degree, CAST(sum(degree) OVER () AS DOUBLE) AS n FROM v)")
def code_usage(spark, d):
    return usage(merged_degrees(spark, d), 16).withColumn("entropy", F.round("entropy", 6))


@query(f"WITH {code_sql(16)}, k AS (SELECT code, truth, count(*) AS n FROM c GROUP BY ALL) SELECT round(CAST(sum(top) AS DOUBLE) / sum(n), 6) AS purity FROM (SELECT max(n) AS top, sum(n) AS n FROM k GROUP BY code)")
def code_purity(spark, d):
    return M.purity(coded(spark, d, 16), "code").select(F.round("purity", 6).alias("purity"))


_TOP = ", top AS (SELECT code, degree FROM v ORDER BY degree DESC, code LIMIT 64)"


@query(f"WITH {code_sql(16)}{DEG_SQL}{_TOP} SELECT * FROM top")
def cap_codes_topk(spark, d):
    return cap_codes(merged_degrees(spark, d), 64)


_NEAR = "SELECT a.code, b.code AS near, CAST(bit_count(xor(a.code, b.code)) AS INTEGER) AS distance FROM {0} a, top b QUALIFY row_number() OVER (PARTITION BY a.code ORDER BY bit_count(xor(a.code, b.code)), b.degree DESC, b.code) = 1"


@query(f"WITH {code_sql(16)}{DEG_SQL}{_TOP} " + _NEAR.format("v"))
def nearest_code(spark, d):
    all_ = merged_degrees(spark, d)
    return nearest(all_, cap_codes(all_, 64))


@query(f"WITH {code_sql(16)}{DEG_SQL}{_TOP}, rest AS (SELECT code FROM v WHERE code NOT IN (SELECT code FROM top)) " + _NEAR.format("rest"))
def assign_unseen(spark, d):
    all_ = merged_degrees(spark, d)
    top = cap_codes(all_, 64)
    return nearest(all_.join(top, "code", "left_anti"), top)


@query(f"WITH {code_sql(16)}{DEG_SQL} SELECT a.code AS a, b.code AS b, CAST(bit_count(xor(a.code, b.code)) AS INTEGER) AS distance FROM v a, v b WHERE bit_count(xor(a.code, b.code)) <= 2")
def hamming_join_banded(spark, d):
    v = merged_degrees(spark, d)
    return hamming_join(v, v, 2, 16)


@query(f"WITH {code_sql(8)}{DEG_SQL} SELECT a.code AS src, b.code AS dst, CAST(bit_count(xor(a.code, b.code)) AS INTEGER) AS distance, CAST(row_number() OVER (PARTITION BY a.code ORDER BY bit_count(xor(a.code, b.code)), b.code) AS INTEGER) AS rank FROM v a, v b WHERE a.code <> b.code QUALIFY rank <= 3")
def graph_knn_codes(spark, d):
    return knn_codes(vertices8(spark, d), 3)


@query(f"WITH {code_sql(24)} SELECT row_id, code FROM c")
def hyperplane_codes(spark, d):
    """Data-independent codes (one shot of hyperplanes), here with the closed-form directions."""
    return coded(spark, d, 24).select("row_id", "code")


# training


def _batch_losses(spark, d, lam: float, t: float, head: str, pairing: str = "all", size: int = 16) -> DataFrame:
    """Loss of each site's first rows as one batch."""
    import pandas as pd

    spec, theta = linear_encoder(DIM, 8), _linear_map(8)

    def run(key, frame):
        q = np.stack(frame.sort_values("row_id")["q"].head(size).to_numpy()).astype(float)
        codes = forward(spec, theta / 65536, q, head)
        value = pair_loss(q / 4096, codes, lam, t, pairing)
        slope, (again, n) = loss_gradient(q / 4096, codes, lam, t, pairing)
        assert abs(value - again) < 1e-9
        return pd.DataFrame({"site_id": [int(key[0])], "n_pairs": [n], "loss": [round(value, 5)]})

    return quantised(spark, d).groupBy("site_id").applyInPandas(run, "site_id int, n_pairs long, loss double")


def _loss_sql(code: str, lam: float, t: str, pairs: str = "a.r < b.r") -> str:
    return (
        f"WITH {L_SQL}, r AS (SELECT row_id, site_id, v, row_number() OVER (PARTITION BY site_id ORDER BY row_id) AS r FROM q QUALIFY r <= 16),"
        f" s AS (SELECT row_id, b, {code} AS h FROM l JOIN r USING (row_id), range(0, 8) AS t(b) GROUP BY row_id, b),"
        " k AS (SELECT row_id, list(h ORDER BY b) AS h FROM s GROUP BY 1), x AS (SELECT r.*, k.h FROM r JOIN k USING (row_id)),"
        " p AS (SELECT a.site_id, sqrt(CAST(list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS DOUBLE)) / 4096 AS d,"
        f" list_sum(list_transform(list_zip(a.h, b.h), lambda z: abs(z[1] - z[2]))) AS l1 FROM x a JOIN x b ON a.site_id = b.site_id AND {pairs})"
        f" SELECT site_id, count(*) AS n_pairs, round(avg(abs({lam} * d - l1) * {t}), 5) AS loss FROM p GROUP BY site_id"
    )


_DOT = "CAST(sum(x * ((((i + 1) * (b * b + 3 * b + 7) + i * i * (b + 5)) % 23) - 11)) AS DOUBLE)"


@query(_loss_sql(f"CASE WHEN {_DOT} >= 0 THEN 1.0 ELSE -1.0 END", 5, "exp(-d / 5)"))
def pair_loss_hard(spark, d):
    return _batch_losses(spark, d, 5.0, 5.0, "sign")


@query(_loss_sql(f"tanh({_DOT} / 65536)", 5, "exp(-d / 5)"))
def pair_loss_surrogate(spark, d):
    return _batch_losses(spark, d, 5.0, 5.0, "tanh")


@query(_loss_sql(f"tanh({_DOT} / 65536)", 2, "1.0"))
def pair_loss_unweighted(spark, d):
    """t without bound: all pairs weigh alike."""
    return _batch_losses(spark, d, 2.0, float("inf"), "tanh")


@query(_loss_sql(f"tanh({_DOT} / 65536)", 5, "exp(-d / 5)", "b.r = a.r + 1 AND a.r % 2 = 1"))
def pair_loss_consecutive(spark, d):
    return _batch_losses(spark, d, 5.0, 5.0, "tanh", "consecutive")


@query(f"WITH {code_sql(16)}, b AS (SELECT site_id, code FROM c QUALIFY row_number() OVER (PARTITION BY site_id ORDER BY row_id) <= 8), k AS (SELECT DISTINCT site_id, code FROM c) SELECT k.site_id, k.code, CAST(sum(bit_count(xor(k.code, b.code))) AS BIGINT) AS score FROM k JOIN b USING (site_id) GROUP BY ALL")
def diverse_scores(spark, d):
    """Each code's sum of differing bits to the first batch of its site, from the batch's sums of signs alone."""
    import pandas as pd

    from ..functions.bits import unpack_array
    from ..operators.sampling import code_scores

    def run(key, frame):
        codes = frame.sort_values("row_id")["code"].to_numpy()
        kinds, batch = np.unique(codes), unpack_array(codes[:8], 16)
        score = code_scores(unpack_array(kinds, 16), batch.sum(0), len(batch))
        return pd.DataFrame({"site_id": int(key[0]), "code": kinds, "score": np.rint(score).astype(np.int64)})

    return coded(spark, d, 16).groupBy("site_id").applyInPandas(run, "site_id int, code long, score long")


@query()
def diverse_batch(spark, d):
    """The rows of one round's batch at each site (32 of the pool's codes), with seeded ties."""
    import pandas as pd

    from ..functions.bits import unpack_array
    from ..operators.sampling import diverse_batch as pick

    def run(key, frame):
        frame = frame.sort_values("row_id")
        at = pick(unpack_array(frame["code"].to_numpy(), 16), 32, int(key[0]))
        return pd.DataFrame({"site_id": int(key[0]), "place": np.arange(len(at)), "row_id": frame["row_id"].to_numpy()[at], "code": frame["code"].to_numpy()[at]})

    return coded(spark, d, 16).groupBy("site_id").applyInPandas(run, "site_id int, place long, row_id long, code long")


_GRAD = f"WITH {L_SQL}, g AS (SELECT site_id, i, CAST(sum(x) AS DOUBLE) / count(*) AS g, count(*) AS n FROM l GROUP BY ALL) "


def _averaged(spark, d, weighting: str) -> DataFrame:
    """What the rounds' own sums make of one vector a site (its mean, with its number of rows)."""
    import pandas as pd

    from ..operators.train import _add

    def one(key, frame):
        x = np.stack(frame["q"].to_numpy()).astype(float)
        return pd.DataFrame({"group": [0], "site_id": [int(key[0])], "used": [len(x)], "loss": [0.0], "data": [x.mean(0).astype("<f4").tobytes()]})

    def split(frames):
        for f in frames:
            for w, data in zip(f["w"], f["data"]):
                g = np.frombuffer(data) / w
                yield pd.DataFrame({"i": np.arange(len(g), dtype=np.int32), "g": np.round(g, 2)})

    sites = quantised(spark, d).groupBy("site_id").applyInPandas(one, "group int, site_id int, used int, loss double, data binary")
    return sites.groupBy("group").applyInPandas(_add(weighting), "group int, w double, loss double, data binary").mapInPandas(split, "i int, g double")


@query(_GRAD + "SELECT CAST(i AS INTEGER) AS i, round(avg(g), 2) AS g FROM g GROUP BY i")
def gradient_average_equal(spark, d):
    return _averaged(spark, d, "equal")


@query(_GRAD + "SELECT CAST(i AS INTEGER) AS i, round(sum(g * n) / sum(n), 2) AS g FROM g GROUP BY i")
def gradient_average_weighted(spark, d):
    return _averaged(spark, d, "batch")


@query(f"SELECT CAST(vec_id % {SITES} AS INTEGER) AS site_id, CAST(least(count(*), 32) AS INTEGER) AS n, true AS own FROM embeddings GROUP BY 1")
def candidate_pools(spark, d):
    """Size of each site's pool, and whether all its vectors are the site's."""
    v = vectors(spark, d)
    pool = candidate_pool(v, 32).select("site_id", "n", F.explode("vecs").alias("vec"))
    return pool.join(v.select("site_id", "vec").distinct().withColumn("is", F.lit(True)), ["site_id", "vec"], "left").groupBy("site_id", "n").agg(((F.count("is") == F.col("n")) & (F.count("*") == F.col("n"))).alias("own"))


@query()
def train_history(spark, d):
    model = CodeGraphClustering(Settings(10, 16, train=TrainConfig(n_rounds=8))).fit(vectors(spark, d))
    return history_frame(spark, model.history)


@query("""WITH h AS (SELECT event_type AS run, CAST(date_diff('day', TIMESTAMP '2024-01-01', ts) AS INTEGER) AS round, CAST(count(*) AS DOUBLE) AS loss FROM events GROUP BY ALL)
  SELECT run, round, loss, round(CASE WHEN max(loss) OVER w = min(loss) OVER w THEN 0.0 ELSE (loss - min(loss) OVER w) / (max(loss) OVER w - min(loss) OVER w) END, 6) AS rer FROM h WINDOW w AS (PARTITION BY run)""")
def rer_curve(spark, d):
    e = read_table(spark, d, "events", "event_type", "ts")
    h = e.groupBy(F.col("event_type").alias("run"), F.datediff("ts", F.lit("2024-01-01")).alias("round")).agg(F.count("*").cast("double").alias("loss"))
    return M.relative_error_ratio(h).withColumn("rer", F.round("rer", 6))


LAMBDAS, ROUNDS = (0.1, 0.2, 0.5, 1.0, 2.0, 5.0), (5, 10, 15, 20)


@query(f"""WITH {code_sql(16)}, p AS (SELECT c.row_id, code, v, lead(code) OVER w AS next, lead(v) OVER w AS u FROM c JOIN q USING (row_id) WINDOW w AS (PARTITION BY c.site_id ORDER BY c.row_id)),
  x AS (SELECT sqrt(CAST(list_sum(list_transform(list_zip(v, u), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS DOUBLE)) / 4096 AS d, 2 * bit_count(xor(code, next)) AS l1 FROM p WHERE next IS NOT NULL)
  SELECT lam::DOUBLE AS lam, t::DOUBLE AS t, n_rounds, round(avg(abs(lam::DOUBLE * d - l1) * exp(-d / t::DOUBLE)), 5) AS loss FROM x, unnest([0.1, 0.2, 0.5, 1, 2, 5]) a(lam), unnest([0.1, 0.2, 0.5, 1, 2, 5]) b(t), unnest([5, 10, 15, 20]) c(n_rounds) GROUP BY ALL""")
def grid_cells(spark, d):
    """The cells of the search, each with the loss of the table's fixed codes over every row and the next one of its site."""
    q = quantised(spark, d).select("row_id", "site_id", "q", encode_fixed(F.col("q"), DIM, 16).alias("code"))
    p = _consecutive(q, "q", "code")
    diff = F.zip_with("q", "next_q", lambda a, b: a - b)
    x = p.select((F.sqrt(V.int_dot(diff, diff).cast("double")) / 4096).alias("d"), code_l1(F.col("code"), F.col("next_code")).alias("l1"))
    losses = [F.struct(F.lit(a).alias("lam"), F.lit(b).alias("t"), F.avg(F.abs(a * F.col("d") - F.col("l1")) * F.exp(-F.col("d") / b)).alias("loss")) for a in LAMBDAS for b in LAMBDAS]
    cells = x.agg(F.array(*losses).alias("cells")).select(F.inline("cells"))
    return cells.where("loss is not null").select("lam", "t", F.explode(F.array(*[F.lit(n) for n in ROUNDS])).alias("n_rounds"), F.round("loss", 5).alias("loss"))


_SHAPE_SQL = f"n AS (SELECT count(*) AS n, CAST(max(len(embedding)) AS BIGINT) AS width, count(DISTINCT vec_id % {SITES}) AS sites, count(DISTINCT label) AS k FROM embeddings)"
_WIDTHS = (1, 2, 4, 8, 16)
_WIDTHS_SQL = _SHAPE_SQL + ", w AS (SELECT n.*, width * m AS dim FROM n, unnest([1, 2, 4, 8, 16]::BIGINT[]) t(m))"


def _table_shape(spark, d):
    """One row ``n, width, sites, k`` of the vectors: what costs and budgets depend on."""
    v = vectors(spark, d)
    return v.agg(F.count("*").alias("n"), F.max(F.size("vec")).alias("width"), F.countDistinct("site_id").alias("sites"), F.countDistinct("truth").alias("k")).first()


@query(f"""WITH {_WIDTHS_SQL} SELECT dim, kind, CAST(CASE kind WHEN 'dense' THEN 2 * (dim * dim + dim) + dim * 64 + 64 WHEN 'linear' THEN dim * 64 + 64
  ELSE (4 * 5 + 4) + (4 * 4 * 5 + 4) + ((((dim - 4) // 2) - 4) // 2) * 4 * 64 + 64 END AS BIGINT) AS n_params FROM w, unnest(['dense', 'conv', 'linear']) b(kind)""")
def encoder_params_budget(spark, d):
    """Parameters of each kind of encoder for the table's vectors, and for ones 2 to 16 times as wide."""
    kinds, width = {"dense": dense_encoder, "conv": conv_encoder, "linear": linear_encoder}, _table_shape(spark, d)["width"]
    return spark.createDataFrame([(m * width, k, f(m * width, 64).n_params) for m in _WIDTHS for k, f in kinds.items()], "dim long, kind string, n_params long")


# graph


def vertices8(spark, d):
    return merge_degrees(degrees_by_site(coded(spark, d, 8)))


@query(f"WITH {code_sql(8)}{DEG_SQL}{EDGE_SQL} SELECT src, dst, round(weight, 6) AS weight FROM e")
def edge_weights(spark, d):
    return weights(vertices8(spark, d)).withColumn("weight", F.round("weight", 6))


@query(f"WITH {code_sql(8)}{DEG_SQL}{EDGE_SQL} SELECT src, dst, round(1.0::DOUBLE / bit_count(xor(src, dst)), 6) AS weight FROM e")
def edge_weights_no_degree(spark, d):
    return weights(vertices8(spark, d), alpha=0).withColumn("weight", F.round("weight", 6))


@query(f"WITH {code_sql(8)}{DEG_SQL} SELECT a.code AS src, b.code AS dst, round(sqrt(CAST(a.degree * b.degree AS DOUBLE)) / pow(bit_count(xor(a.code, b.code)), 2), 6) AS weight FROM v a JOIN v b ON a.code < b.code WHERE bit_count(xor(a.code, b.code)) <= 4")
def edge_weights_power(spark, d):
    return weights(vertices8(spark, d), alpha=0.5, p=2, max_hamming=4).withColumn("weight", F.round("weight", 6))


@query(f"WITH {code_sql(8)}{DEG_SQL}{EDGE_SQL}{BOTH_SQL} SELECT src AS code, round(sum(weight), 4) AS strength FROM w GROUP BY src")
def vertex_strength(spark, d):
    return strength(weights(vertices8(spark, d))).withColumn("strength", F.round("strength", 4))


_CUT = ", k AS (SELECT code, code % 5 AS cluster FROM v), o AS (SELECT a.cluster, sum(CASE WHEN a.cluster <> b.cluster THEN weight ELSE 0 END) AS out, sum(weight) AS vol FROM w JOIN k a ON a.code = w.src JOIN k b ON b.code = w.dst GROUP BY 1) "


@query(f"WITH {code_sql(8)}{DEG_SQL}{EDGE_SQL}{BOTH_SQL}{_CUT} SELECT round(0.5 * sum(out / vol), 6) AS cut_value FROM o")
def cut_value_degree(spark, d):
    v = vertices8(spark, d)
    return cut_value(weights(v), v.select("code", (F.col("code") % 5).alias("cluster"))).select(F.round("cut_value", 6).alias("cut_value"))


@query(f"WITH {code_sql(8)}{DEG_SQL}{EDGE_SQL}{BOTH_SQL}{_CUT} SELECT round(0.5 * sum(out / n), 4) AS cut_value FROM o JOIN (SELECT cluster, count(*) AS n FROM k GROUP BY 1) USING (cluster)")
def cut_value_vertices(spark, d):
    v = vertices8(spark, d)
    return cut_value(weights(v), v.select("code", (F.col("code") % 5).alias("cluster")), "vertices").select(F.round("cut_value", 4).alias("cut_value"))


@query(f"WITH RECURSIVE {code_sql(16)}{DEG_SQL}, n AS (SELECT a.code AS x, b.code AS y FROM v a JOIN v b ON bit_count(xor(a.code, b.code)) = 1), r(node, low) AS (SELECT x, least(x, y) FROM n UNION SELECT n.y, r.low FROM r JOIN n ON n.x = r.node) SELECT node, min(low) AS component FROM r GROUP BY node")
def components(spark, d):
    v = merged_degrees(spark, d)
    return graph_components(hamming_join(v, v, 1, 16).select(F.col("a").alias("src"), F.col("b").alias("dst")))


@query(f"WITH {code_sql(8)}{DEG_SQL}{EDGE_SQL}{BOTH_SQL} SELECT src AS code, count(*) AS n_neighbors FROM w GROUP BY src")
def graph_degree(spark, d):
    from ..operators.graph import both_ways

    return both_ways(weights(vertices8(spark, d))).groupBy(F.col("src").alias("code")).agg(F.count("*").alias("n_neighbors"))


def _cut_codes(spark, d, cut):
    from .pipeline import cut_codes

    v = vertices8(spark, d).orderBy("code").collect()
    codes = np.array([r["code"] for r in v], np.int64)
    labels, value = cut_codes(spark, codes, np.array([r["degree"] for r in v], float), 8, 5, cut)
    return spark.createDataFrame([(int(c), int(x), value) for c, x in zip(codes, labels)], "code long, cluster int, cut_value double")


@query()
def spectral_bisect(spark, d):
    return _cut_codes(spark, d, "bisect")


@query()
def code_graph_labels(spark, d):
    return _cut_codes(spark, d, "symmetric")


@query()
def power_iteration(spark, d):
    from ..operators.spectral import power_iteration_labels

    return power_iteration_labels(weights(vertices8(spark, d)), 5)


# the whole method


def planted_orders(spark, d):
    o = read_table(spark, d, "orders", "o_orderkey", "o_orderpriority")
    return assign_sites(planted_vectors(o, "o_orderpriority", "o_orderkey"), "row_id", 10)


@query("SELECT o_orderkey AS row_id, min(o_orderkey) OVER (PARTITION BY o_orderpriority) AS label FROM orders")
def pipeline_planted_orders(spark, d):
    df = planted_orders(spark, d)
    model = CodeGraphClustering(Settings(5, 64, train=TrainConfig(n_rounds=10))).fit(df)
    return canonical_labels(model.transform(df.select("row_id", "site_id", "vec")))


def document_vectors(spark, d, dim: int = 64):
    docs = read_table(spark, d, "documents", "doc_id", "text", "lang")
    v = char_ngram_vectors(docs, "doc_id", "text", 1, dim)
    return assign_sites(v, "row_id", 10).join(docs.select(F.col("doc_id").alias("row_id"), F.col("lang").alias("truth")), "row_id")


def scores(labelled: DataFrame, extra: dict | None = None) -> DataFrame:
    out = M.purity(labelled).crossJoin(M.nmi(labelled))
    for k, v in (extra or {}).items():
        out = out.withColumn(k, F.lit(v))
    return out


@query()
def pipeline_documents(spark, d):
    df = checkpoint(document_vectors(spark, d))
    # texts have nearly as many codes as rows: all of them are cut, none refused or merged
    model = CodeGraphClustering(Settings(4, 64, max_codes=10_000_000, train=TrainConfig(n_rounds=10))).fit(df)
    return scores(model.transform(df), {"n_codes": len(model.codes), "megabytes": model.costs["total_bits"] / 8e6})


@query()
def pipeline_embeddings(spark, d):
    df = vectors(spark, d)
    model = CodeGraphClustering(Settings(10, 16, train=TrainConfig(n_rounds=10))).fit(df)
    return model.transform(df).groupBy("cluster").agg(F.count("*").alias("n_rows"), F.countDistinct("code").alias("n_codes"))


@query()
def entry_code_graph(spark, d):
    return pipeline_embeddings(spark, d)


@query()
def pipeline_pretrained(spark, d):
    df = vectors(spark, d)
    first = CodeGraphClustering(Settings(10, 16, train=TrainConfig(n_rounds=5))).fit(df)
    again = CodeGraphClustering(Settings(10, 16, train=TrainConfig(n_rounds=0)), init=first).fit(df)
    return again.transform(df).select("row_id", "code", "cluster")


# costs


_BY_SITE = f"WITH {code_sql(16)}{DEG_SQL}, n AS (SELECT site_id, count(*) AS num FROM d GROUP BY 1) "


@query(f"WITH {_SHAPE_SQL} SELECT CAST(sites * (2 * (width * width + width) + width * 16 + 16) AS BIGINT) * 2 * n_rounds * 32 AS bits, n_rounds FROM n, unnest([5, 10, 15, 20]) t(n_rounds)")
def cost_training(spark, d):
    """For the table's sites and the width of its vectors."""
    n = _table_shape(spark, d)
    p = dense_encoder(n["width"], 16).n_params
    return spark.createDataFrame([(C.training_bits(n["sites"], p, r), r) for r in ROUNDS], "bits long, n_rounds int")


@query(_BY_SITE + "SELECT CAST(sum(num * 48) AS BIGINT) AS code_bits FROM n")
def cost_codes(spark, d):
    return C.code_bits(site_degrees(spark, d), 16)


def _sizes(spark, d) -> DataFrame:
    return site_degrees(spark, d).groupBy("site_id").agg(F.count("*").alias("num"))


def _params_word(n_rounds: int) -> int:
    return 32 * (2 * n_rounds + 1) * dense_encoder(64, 16).n_params


@query(_BY_SITE + "SELECT CAST(sum(32 * 41 * (2 * (64 * 64 + 64) + 64 * 16 + 16) + num * 48) AS BIGINT) AS total_bits, round(sum(32 * 41 * (2 * (64 * 64 + 64) + 64 * 16 + 16) + num * 48) / 8e6, 6) AS megabytes FROM n")
def cost_total(spark, d):
    total = F.sum(F.lit(_params_word(20)) + F.col("num") * 48)
    return _sizes(spark, d).agg(total.alias("total_bits"), F.round(C.megabytes(total), 6).alias("megabytes"))


@query(f"WITH {_SHAPE_SQL} SELECT bits, CAST(CAST(32 * 41 AS HUGEINT) * sites * (2 * (width * width + width) + width * 16 + 16) + CAST(sites AS HUGEINT) * (32 + bits) * (1::HUGEINT << CAST(bits AS INTEGER)) AS DECIMAL(38, 0)) AS bound FROM n, unnest([4, 8, 16, 32, 64]) t(bits)")
def cost_bound(spark, d):
    """For the table's sites and the width of its vectors."""
    from decimal import Decimal

    n = _table_shape(spark, d)
    p = dense_encoder(n["width"], 16).n_params
    return spark.createDataFrame([(b, Decimal(C.bound_bits(n["sites"], p, 20, b))) for b in (4, 8, 16, 32, 64)], "bits int, bound decimal(38,0)")


@query(_BY_SITE + ", r AS (SELECT site_id, count(*) AS rows FROM c GROUP BY 1) SELECT CAST(sum(32 * 41 * (2 * (64 * 64 + 64) + 64 * 16 + 16) + 48 * least(65536, rows)) AS BIGINT) AS bound FROM r")
def cost_tight_bound(spark, d):
    sizes = coded(spark, d, 16).groupBy("site_id").agg(F.count("*").alias("rows"))
    return sizes.agg(F.sum(F.lit(_params_word(20)) + 48 * F.least(F.lit(65536), F.col("rows"))).alias("bound"))


@query(_BY_SITE + "SELECT CAST(sum(num * (16 + 4)) AS BIGINT) AS bits FROM n")
def cost_label_return(spark, d):
    return _sizes(spark, d).agg(F.sum(F.col("num") * (16 + 4)).alias("bits"))


@query("SELECT CAST(sum(len(embedding) * 32) AS BIGINT) AS bits FROM embeddings")
def cost_raw(spark, d):
    return vectors(spark, d).agg(F.sum(F.size("vec") * 32).alias("bits"))


@query(f"""WITH {_WIDTHS_SQL}, b AS (SELECT dim, kind, CAST(32 * 41 * sites * CASE kind WHEN 'dense' THEN 2 * (dim * dim + dim) + dim * 64 + 64
  ELSE (4 * 5 + 4) + (4 * 4 * 5 + 4) + ((((dim - 4) // 2) - 4) // 2) * 4 * 64 + 64 END AS DOUBLE) AS bits FROM w, unnest(['dense', 'conv']) k(kind))
  SELECT kind, round(regr_slope(ln(bits), ln(dim::DOUBLE)), 6) AS slope, round(sum(bits) FILTER (WHERE dim = (SELECT width FROM n)) / 8e6, 6) AS megabytes FROM b GROUP BY kind""")
def cost_by_dim(spark, d):
    """Training cost on the table's sites, and its growth with the width of its vectors, on logarithms: linear for convolutions, quadratic for dense stacks."""
    n = _table_shape(spark, d)
    rows = [(k, m * n["width"], float(C.total_bits(n["sites"], f(m * n["width"], 64).n_params, 20, [], 64))) for k, f in (("dense", dense_encoder), ("conv", conv_encoder)) for m in _WIDTHS]
    df = spark.createDataFrame(rows, "kind string, dim int, bits double")
    mine = {(k, x): bits for k, x, bits in rows}
    parts = [C.cost_growth(df.where(F.col("kind") == k)).select(F.lit(k).alias("kind"), F.round("slope", 6).alias("slope"), F.round(C.megabytes(F.lit(mine[k, n["width"]])), 6).alias("megabytes")) for k in ("dense", "conv")]
    return parts[0].union(parts[1])


@query(f"""WITH {_WIDTHS_SQL} SELECT dim, method, CAST(32 * CASE method WHEN 'central' THEN n * dim WHEN 'kmeans_parallel' THEN 10 * 2 * sites * k * dim WHEN 'partition_merge' THEN sites * k * (dim + 1) + sites * k * dim
  WHEN 'hashed_density_peaks' THEN 20 * n * dim WHEN 'subspace_models' THEN 3000 * (1 + dim + dim * 24 + 24) WHEN 'gaussian_models' THEN 3000 * (1 + dim + dim * (dim + 1) // 2)
  WHEN 'density_representatives' THEN 2 * 200 * (dim + 1) ELSE 200 * (dim + 1) END AS BIGINT) AS bits
  FROM w, unnest(['central', 'kmeans_parallel', 'partition_merge', 'hashed_density_peaks', 'subspace_models', 'gaussian_models', 'density_representatives', 'grid']) m(method)""")
def cost_models_baselines(spark, d):
    """Modelled cost of each baseline for the table's rows, sites and labels, at the width of its vectors and up to 16 times that."""
    n = _table_shape(spark, d)
    names = ("central", "kmeans_parallel", "partition_merge", "hashed_density_peaks", "subspace_models", "gaussian_models", "density_representatives", "grid")
    rows = [(w * n["width"], m, C.baseline_bits(m, n_rows=n["n"], dim=w * n["width"], n_sites=n["sites"], k=n["k"], models=3000, latent=24, reps=200)) for w in _WIDTHS for m in names]
    return spark.createDataFrame(rows, "dim long, method string, bits long")


# accuracy, of the 4-bit code as cluster against the label


def _labelled(spark, d):
    return coded(spark, d, 4).select("row_id", F.col("code").alias("cluster"), "truth")


_CELLS = f"WITH {code_sql(4)}, n AS (SELECT code AS cluster, truth, count(*) AS n FROM c GROUP BY ALL), a AS (SELECT cluster, sum(n) AS na FROM n GROUP BY 1), b AS (SELECT truth, sum(n) AS nb FROM n GROUP BY 1), t AS (SELECT CAST(sum(n) AS DOUBLE) AS t FROM n) "
_ENT = _CELLS + ", h AS (SELECT (SELECT sum(-(na / t) * ln(na / t)) FROM a, t) AS ha, (SELECT sum(-(nb / t) * ln(nb / t)) FROM b, t) AS hb, (SELECT sum(n / t * ln(n * t / (na * nb))) FROM n JOIN a USING (cluster) JOIN b USING (truth), t) AS mi) "


@query(_CELLS + "SELECT cluster, truth, n FROM n")
def contingency(spark, d):
    return M.contingency(_labelled(spark, d))


@query(_CELLS + "SELECT round(CAST(sum(top) AS DOUBLE) / sum(n), 6) AS purity FROM (SELECT max(n) AS top, sum(n) AS n FROM n GROUP BY cluster)")
def purity(spark, d):
    return M.purity(_labelled(spark, d)).select(F.round("purity", 6).alias("purity"))


@query(_ENT + "SELECT (SELECT CAST(t AS BIGINT) FROM t) AS n, round(ha, 6) AS h_cluster, round(hb, 6) AS h_truth, round(mi, 6) AS mutual FROM h")
def entropy_terms(spark, d):
    e = M.entropy_terms(_labelled(spark, d))
    return e.select("n", *[F.round(c, 6).alias(c) for c in ("h_cluster", "h_truth", "mutual")])


for _name, _by in {"geometric": "sqrt(ha * hb)", "arithmetic": "(ha + hb) / 2", "max": "greatest(ha, hb)", "min": "least(ha, hb)", "printed_product": "ha * hb"}.items():
    query(_ENT + f"SELECT round(mi / ({_by}), 6) AS nmi FROM h", name="nmi_printed" if _name == "printed_product" else f"nmi_{_name}")(lambda spark, d, a=_name: M.nmi(_labelled(spark, d), average=a).select(F.round("nmi", 6).alias("nmi")))

_PAIRS = _CELLS + ", p AS (SELECT (SELECT sum(n * (n - 1) / 2) FROM n) AS s, (SELECT sum(na * (na - 1) / 2) FROM a) AS sc, (SELECT sum(nb * (nb - 1) / 2) FROM b) AS st, (SELECT t * (t - 1) / 2 FROM t) AS every) "


@query(_PAIRS + "SELECT CAST(s AS DOUBLE) AS both, CAST(sc AS DOUBLE) AS same_cluster, CAST(st AS DOUBLE) AS same_truth, round(2 * s / (sc + st), 6) AS pair_f1 FROM p")
def pair_counts(spark, d):
    return M.pair_scores(_labelled(spark, d)).select("both", "same_cluster", "same_truth", F.round("pair_f1", 6).alias("pair_f1"))


@query(_PAIRS + "SELECT round((s - sc * st / every) / ((sc + st) / 2 - sc * st / every), 6) AS adjusted_rand FROM p")
def adjusted_rand(spark, d):
    return M.pair_scores(_labelled(spark, d)).select(F.round("adjusted_rand", 6).alias("adjusted_rand"))


# baselines


def _scored(spark, d, run):
    df = checkpoint(vectors(spark, d))
    got = run(df)
    return scores(got.labels.join(df.select("row_id", "truth"), "row_id"), {"megabytes": got.bits / 8e6})


query(name="central_kmeans")(lambda s, d: _scored(s, d, lambda df: B.central_kmeans(df, 10)))
query(name="central_spectral")(lambda s, d: _scored(s, d, lambda df: B.central_spectral(df, 10)))
query(name="kmeans_parallel")(lambda s, d: _scored(s, d, lambda df: B.kmeans_parallel(df, 10)))
query(name="partition_merge")(lambda s, d: _scored(s, d, lambda df: B.partition_merge(df, 10)))
query(name="density_representatives")(lambda s, d: _scored(s, d, B.density_representatives))
query(name="density_peaks_labels")(lambda s, d: _scored(s, d, lambda df: B.hashed_density_peaks(df, 10)))
query(name="subspace_models")(lambda s, d: _scored(s, d, lambda df: B.subspace_models(df, 10)))
query(name="gaussian_models")(lambda s, d: _scored(s, d, lambda df: B.gaussian_models(df, 10)))
query(name="random_codes")(lambda s, d: scores(CodeGraphClustering(Settings(10, 16, encoder="hyperplane")).fit(vectors(s, d)).transform(vectors(s, d))))


@query(f"WITH {L_SQL}, k AS (SELECT row_id % 5 AS cluster, i, CAST(sum(x * (1 + row_id % 3)) AS DOUBLE) / sum(1 + row_id % 3) AS center FROM l GROUP BY ALL) SELECT CAST(cluster AS BIGINT) AS cluster, CAST(i AS INTEGER) AS i, round(center, 4) AS center FROM k")
def weighted_lloyd_step(spark, d):
    """New weighted centers of a given assignment (by id), weights 1 to 3."""
    x = quantised(spark, d).select((F.col("row_id") % 5).alias("cluster"), (F.col("row_id") % 3 + 1).alias("w"), F.posexplode("q").alias("i", "x"))
    return x.groupBy("cluster", "i").agg(F.round(F.sum(F.col("x") * F.col("w")).cast("double") / F.sum("w"), 4).alias("center"))


@query(f"WITH {Q_SQL}, x AS (SELECT sqrt(CAST(list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS DOUBLE)) AS d FROM q a JOIN q b ON a.row_id < b.row_id) SELECT round(quantile_cont(d, 0.02), 4) AS eps FROM x")
def eps_second_percentile(spark, d):
    """Of all pairs of rows."""
    return spark.createDataFrame([(round(B.second_percentile(_as_vec(spark, d)), 4),)], "eps double")


EPS = 4800  # in steps of 1/4096: about 1.17
_LAYOUTS, _HASHES, _WIDTH = 10, 3, 200_000


def _int_maps():
    b, i = np.meshgrid(np.arange(_LAYOUTS * _HASHES), np.arange(DIM))
    return (((i + 1) * (b * b + 3 * b + 7) + i * i * (b + 5)) % 23 - 11).astype(float), np.arange(_LAYOUTS * _HASHES) * 1000.0


def _int_buckets(spark, d):
    q = quantised(spark, d).select("row_id", F.col("q").cast("array<double>").alias("vec"))
    return B.lsh_buckets(q, _LAYOUTS, _HASHES, _WIDTH, DIM, maps=_int_maps())


_BUCKETS = f"""WITH {L_SQL}, h AS (SELECT row_id, b, CAST(floor(CAST(sum(x * ((((i + 1) * (b * b + 3 * b + 7) + i * i * (b + 5)) % 23) - 11)) + b * 1000 AS DOUBLE) / {_WIDTH}) AS BIGINT) AS h FROM l, range(0, {_LAYOUTS * _HASHES}) t(b) GROUP BY row_id, b),
 k AS (SELECT row_id, CAST(b // {_HASHES} AS INTEGER) AS layout, string_agg(CAST(h AS VARCHAR), ',' ORDER BY b) AS bucket FROM h GROUP BY row_id, b // {_HASHES})"""
_RHO = _BUCKETS + f""", kv AS (SELECT k.*, q.v FROM k JOIN q USING (row_id)),
 pr AS (SELECT a.layout, a.row_id AS x, b.row_id AS y, list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) AS sq FROM kv a JOIN kv b ON a.layout = b.layout AND a.bucket = b.bucket AND a.row_id <> b.row_id),
 lr AS (SELECT k.layout, k.row_id, count(pr.y) FILTER (WHERE sq <= {EPS}::BIGINT * {EPS}) AS rho FROM k LEFT JOIN pr ON pr.layout = k.layout AND pr.x = k.row_id GROUP BY ALL),
 rho AS (SELECT row_id, max(rho) AS rho FROM lr GROUP BY 1)"""
_DELTA = _RHO + ", dl AS (SELECT pr.x AS row_id, min(sq) AS sq FROM pr JOIN rho a ON a.row_id = pr.x JOIN rho b ON b.row_id = pr.y WHERE b.rho > a.rho OR (b.rho = a.rho AND pr.y < pr.x) GROUP BY 1)"


@query(_BUCKETS + " SELECT row_id, layout, bucket FROM k")
def lsh_buckets(spark, d):
    return _int_buckets(spark, d).select("row_id", "layout", "bucket")


def _int_codes(spark, d):
    q = quantised(spark, d).select("row_id", F.col("q").cast("array<double>").alias("vec"))
    return B.lsh_codes(q, _LAYOUTS, _HASHES, _WIDTH, DIM, maps=_int_maps())


@query(_RHO + " SELECT * FROM rho")
def lsh_rho_max(spark, d):
    return B.layout_densities(_int_codes(spark, d), float(EPS), _LAYOUTS)


def _delta(spark, d):
    kinds = B.kinds_of(_int_codes(spark, d), vectors(spark, d).count())
    rho, delta = B.kind_peaks(kinds, float(EPS), _LAYOUTS)
    every = kinds.select("row_id", "ids").join(rho, "row_id").select(F.explode("ids").alias("row_id"), "rho")
    return every, B.of_copies(kinds, delta).select("row_id", "delta")


@query(_DELTA + " SELECT row_id, round(sqrt(CAST(sq AS DOUBLE)), 4) AS delta FROM dl")
def lsh_delta_min(spark, d):
    return _delta(spark, d)[1].withColumn("delta", F.round("delta", 4))


@query(_DELTA + " SELECT row_id, rho, round(rho * sqrt(CAST(coalesce(sq, (SELECT max(sq) FROM dl)) AS DOUBLE)), 3) AS gamma FROM rho LEFT JOIN dl USING (row_id) ORDER BY gamma DESC, row_id LIMIT 10")
def gamma_topk(spark, d):
    rho, delta = _delta(spark, d)
    top = delta.agg(F.max("delta")).first()[0]
    gamma = F.round(F.col("rho") * F.coalesce("delta", F.lit(top)), 3)
    return rho.join(delta, "row_id", "left").select("row_id", "rho", gamma.alias("gamma")).orderBy(F.desc("gamma"), "row_id").limit(10)


@query(f"WITH {Q_SQL}, y AS (SELECT a.row_id, count(*) FILTER (WHERE list_sum(list_transform(list_zip(a.v, b.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) <= {EPS}::BIGINT * {EPS}) - 1 AS rho FROM q a JOIN q b USING (site_id) GROUP BY 1) SELECT row_id, rho FROM y")
def cutoff_density(spark, d):
    q = quantised(spark, d).select("site_id", "row_id", F.col("q").cast("array<double>").alias("vec"))
    return q.groupBy("site_id").applyInPandas(B._density(float(EPS)), "row_id long, rho long")


@query("WITH k AS (SELECT CAST(floor(l_quantity / 5) AS BIGINT) AS a, CAST(floor(l_discount / 0.02 + 1e-9) AS BIGINT) AS b FROM lineitem) SELECT a, b, count(*) AS n FROM k GROUP BY ALL HAVING count(*) >= 50")
def grid_cells_dense(spark, d):
    li = read_table(spark, d, "lineitem", "l_quantity", "l_discount")
    a, b = F.floor(F.col("l_quantity") / 5).cast("long"), F.floor(F.col("l_discount") / 0.02 + 1e-9).cast("long")
    return li.groupBy(a.alias("a"), b.alias("b")).agg(F.count("*").alias("n")).where("n >= 50")


@query("""WITH RECURSIVE c AS (SELECT CAST(vec_id AS BIGINT) AS row_id, CAST(floor(CAST(embedding[1] AS DOUBLE) / 0.0625) AS BIGINT) AS a, CAST(floor(CAST(embedding[2] AS DOUBLE) / 0.0625) AS BIGINT) AS b FROM embeddings),
  g AS (SELECT a, b, min(row_id) AS low FROM c GROUP BY ALL HAVING count(*) >= 3),
  n AS (SELECT x.a, x.b, y.a AS c, y.b AS d FROM g x JOIN g y ON abs(x.a - y.a) <= 1 AND abs(x.b - y.b) <= 1),
  r(a, b, low) AS (SELECT a, b, low FROM g UNION SELECT n.c, n.d, r.low FROM r JOIN n ON n.a = r.a AND n.b = r.b),
  m AS (SELECT a, b, min(low) AS label FROM r GROUP BY ALL) SELECT row_id, coalesce(label, -1) AS label FROM c LEFT JOIN m USING (a, b)""")
def grid_clusters(spark, d):
    """Clusters of dense cells, named by their smallest row; -1 elsewhere."""
    got = B.grid_cells(vectors(spark, d), [0, 1], 0.0625, 3).labels
    low = got.where("cluster >= 0").groupBy("cluster").agg(F.min("row_id").alias("label"))
    return got.join(low, "cluster", "left").select("row_id", F.coalesce("label", F.lit(-1)).alias("label"))


# features


@query("SELECT CAST(doc_id AS BIGINT) AS row_id, CAST(length(text) AS INTEGER) AS n_chars, CAST(len(string_split(text, chr(10))) AS INTEGER) AS n_lines, CAST(len(list_distinct(string_split(text, chr(10)))) AS INTEGER) AS n_distinct_lines, CAST(len(regexp_extract_all(text, '[0-9]')) AS INTEGER) AS n_digits, CAST(len(regexp_extract_all(text, '[.,;:!?]')) AS INTEGER) AS n_marks FROM documents")
def feature_text_shape(spark, d):
    return text_shape(read_table(spark, d, "documents", "doc_id", "text"), "doc_id", "text").drop("n_words")


@query("SELECT CAST(page_id AS BIGINT) AS row_id, CAST(len(regexp_extract_all(html, '<[a-z]')) AS INTEGER) AS n_tags, CAST(len(regexp_extract_all(html, '<a ')) AS INTEGER) AS n_links, CAST(length(regexp_replace(html, '<[^>]*>', '', 'g')) AS INTEGER) AS text_chars, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host, regexp_extract(html, 'lang=\"([a-z]+)\"', 1) AS lang FROM pages")
def feature_html(spark, d):
    return html_features(read_table(spark, d, "pages", "page_id", "url", "html"))



@query("SELECT CAST(user_id AS BIGINT) AS row_id, event_type, count(*) AS n, round(avg(value), 7) AS mean FROM events GROUP BY ALL")
def feature_user_profile(spark, d):
    e = read_table(spark, d, "events", "user_id", "event_type", "value")
    kinds = [r[0] for r in e.select("event_type").distinct().orderBy("event_type").limit(4097).collect()]
    if len(kinds) > 4096:
        raise ValueError("profiles have a place for each event type; more than 4096 are too many")
    p = profile(e, "user_id", "event_type", "value", kinds)
    each = p.select("row_id", F.explode(F.array(*[F.struct(F.lit(k).alias("event_type"), F.get("vec", 3 * i).cast("long").alias("n"), F.round(F.get("vec", 3 * i + 1), 7).alias("mean")) for i, k in enumerate(kinds)])).alias("x"))
    return each.select("row_id", "x.*").where("n > 0")


# more of the shipped operators against SQL


@query(f"WITH {code_sql(16)}{DEG_SQL}{_TOP}, near AS (" + _NEAR.format("v") + ") SELECT row_id, code, CAST(near.near % 5 AS INTEGER) AS cluster FROM c JOIN near USING (code)")
def encode_and_label(spark, d):
    """Codes and clusters in one pass: 64 codes have a label, the others that of their nearest."""
    from ..operators.encode import encode_and_label as run

    top = cap_codes(merged_degrees(spark, d), 64).orderBy(F.desc("degree"), "code").collect()
    codes = np.array([r["code"] for r in top], np.int64)
    v = quantised(spark, d).select("row_id", F.col("q").cast("array<double>").alias("vec"))
    return run(v, linear_encoder(DIM, 16), _linear_map(16), Normalizer("none"), codes, np.array([r["degree"] for r in top], float), codes % 5)


@query(f"WITH {code_sql(16)}{DEG_SQL}{_TOP}, near AS (" + _NEAR.format("v") + ") SELECT near.near AS code, CAST(sum(v.degree) AS BIGINT) AS degree FROM v JOIN near USING (code) GROUP BY 1")
def contracted_codes(spark, d):
    from ..operators.graph import contract_codes

    return contract_codes(merged_degrees(spark, d), 64, 16)


@query("""WITH h AS (SELECT event_type AS run, CAST(date_diff('day', TIMESTAMP '2024-01-01', ts) AS INTEGER) AS round, CAST(count(*) AS DOUBLE) AS loss FROM events GROUP BY ALL),
  x AS (SELECT run, round, CASE WHEN max(loss) OVER w = min(loss) OVER w THEN 0.0 ELSE (loss - min(loss) OVER w) / (max(loss) OVER w - min(loss) OVER w) END AS rer FROM h WINDOW w AS (PARTITION BY run))
  SELECT run, min(round) AS rounds FROM x WHERE rer <= 0.4 GROUP BY run""")
def rounds_to(spark, d):
    e = read_table(spark, d, "events", "event_type", "ts")
    return M.rounds_to(e.groupBy(F.col("event_type").alias("run"), F.datediff("ts", F.lit("2024-01-01")).alias("round")).agg(F.count("*").cast("double").alias("loss")), 0.4)


@query("SELECT CAST(c AS INTEGER) AS truth, CAST(1 << CAST(c // 2 + 1 AS INTEGER) AS INTEGER) AS latent_dim, 30 AS n, 64 AS dim, true AS near FROM range(0, 12) t(c)")
def synthetic_clusters(spark, d):
    """The generator's clusters: latent dimensions, sizes, and that means lie within the published reach."""
    from ..sources.gaussians import subspace_dataset

    x = subspace_dataset(spark, 1, 2, 30)
    far = F.array_max(F.transform("vec", lambda v: F.abs(v)))
    return x.groupBy("truth", "latent_dim").agg(F.count("*").cast("int").alias("n"), F.max(F.size("vec")).alias("dim"), (F.max(far) < 20 / 6 + 8).alias("near"))


for _fmt in ("parquet", "csv", "json", "orc"):

    def _round_trip(spark, d, fmt=_fmt):
        import uuid

        from ..session import shared_dir
        from ..sources import io

        df, path = io.load(spark, d, "customer"), f"{shared_dir(spark)}/{fmt}-{uuid.uuid4().hex}"
        io.save(df, path, fmt)
        return io.read_as(spark, path, fmt, df.schema)

    query("SELECT * FROM customer", name=f"written_{_fmt}")(_round_trip)


@query(f"WITH {code_sql(16)} SELECT row_id, CAST(bit_count(xor(code, 21845)) AS INTEGER) AS hamming, CAST(2 * bit_count(xor(code, 21845)) AS INTEGER) AS l1 FROM c")
def sql_functions(spark, d):
    from ..functions import udfs

    udfs.register(spark)
    coded(spark, d, 16).select("row_id", "code").createOrReplaceTempView("codes_of_rows")
    return spark.sql("SELECT row_id, hamming(code, 21845) AS hamming, code_l1(code, 21845) AS l1 FROM codes_of_rows")


_PLANTED = "SELECT c_custkey AS row_id, min(c_custkey) OVER (PARTITION BY c_mktsegment) AS label FROM customer"


def planted_customers(spark, d) -> DataFrame:
    c = read_table(spark, d, "customer", "c_custkey", "c_mktsegment")
    return assign_sites(planted_vectors(c, "c_mktsegment", "c_custkey"), "row_id", 5)


def _planted(run):
    return lambda spark, d: canonical_labels(run(checkpoint(planted_customers(spark, d))).labels.select("row_id", "cluster"))


for _name, _run in {
    "central_spectral": lambda df: B.central_spectral(df, 5, gamma=0.001),
    "kmeans_parallel": lambda df: B.kmeans_parallel(df, 5),
    "partition_merge": lambda df: B.partition_merge(df, 5),
    "density_representatives": lambda df: B.density_representatives(df, lam=0.01),
    "density_peaks": lambda df: B.hashed_density_peaks(df, 5, eps=6.5, width=200.0),
    "gaussian_models": lambda df: B.gaussian_models(df, 5),
}.items():
    query(_PLANTED, name=f"planted_{_name}")(_planted(_run))


def _planted_cut(cut):
    def run(spark, d):
        df = checkpoint(planted_customers(spark, d))
        model = CodeGraphClustering(Settings(5, 64, encoder="hyperplane", cut=cut)).fit(df)
        return canonical_labels(model.transform(df.select("row_id", "site_id", "vec")).select("row_id", "cluster"))

    return run


for _cut in ("symmetric", "random_walk", "bisect"):
    query(_PLANTED, name=f"planted_cut_{_cut}")(_planted_cut(_cut))


@query(_PLANTED)
def planted_saved_model(spark, d):
    """Fitted, written, read back, applied."""
    import uuid

    from ..session import shared_dir
    from .pipeline import CodeGraphModel

    df, path = checkpoint(planted_customers(spark, d)), f"{shared_dir(spark)}/model-{uuid.uuid4().hex}"
    CodeGraphClustering(Settings(5, 64, train=TrainConfig(n_rounds=10))).fit(df).write(path, spark)
    return canonical_labels(CodeGraphModel.read(path, spark).transform(df.select("row_id", "site_id", "vec")).select("row_id", "cluster"))
