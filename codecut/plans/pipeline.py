"""The whole method as an estimator and a model."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

import numpy as np
from pyspark.ml import Estimator, Model
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cost
from ..operators.encode import encode, encode_and_label, merge_degrees, random_hyperplane_params, site_degrees
from ..operators.features import Normalizer, fit_normalizer
from ..operators.graph import contract_codes, nearest_code
from ..operators.network import EncoderSpec, conv_encoder, dense_encoder, linear_encoder
from ..operators.sampling import candidate_pool
from ..operators.spectral import blocked_bisect, blocked_code_weights, code_weights, cut_value, kmeans, ncut_bisect, spectral_labels
from ..operators.train import TrainConfig, Trained, train_encoder
from ..session import checkpoint


@dataclass(frozen=True)
class Settings:
    k: int
    bits: int = 64
    encoder: str = "dense"  # dense, conv, linear, or hyperplane (no training)
    hidden: tuple[int, ...] | None = None
    normalize: str = "zscore_sqrt_dim"
    per_site: int = 512
    refresh_every: int = 10  # rounds after which the pools are drawn anew; 0: never
    max_codes: int = 100_000
    contract: bool = False  # with more codes than max_codes, merge the rest into their nearest ones; else refuse
    alpha: float = 1.0
    p: float = 1.0
    cut: str = "symmetric"  # random_walk, unnormalized, or bisect
    kmeans_restarts: int = 20
    encoder_restarts: int = 1
    train: TrainConfig = field(default_factory=TrainConfig)


def spec_for(s: Settings, dim: int) -> EncoderSpec:
    if s.encoder == "dense":
        return dense_encoder(dim, s.bits, s.hidden)
    return conv_encoder(dim, s.bits) if s.encoder == "conv" else linear_encoder(dim, s.bits)


def cut_codes(spark: SparkSession, codes: np.ndarray, degrees: np.ndarray, bits: int, k: int, cut: str = "symmetric", restarts: int = 20, seed: int = 0, alpha: float = 1.0, p: float = 1.0, dense_up_to: int = 4096) -> tuple[np.ndarray, float]:
    """(cluster of each code, cut value). Above ``dense_up_to`` codes the matrix is never made; the cuts are the same."""
    if len(codes) <= dense_up_to:
        w = code_weights(codes, degrees, bits, alpha, p)
        labels = ncut_bisect(w, k) if cut == "bisect" else spectral_labels(w, k, seed, restarts, cut)
        return labels, cut_value(w, labels)
    part = lambda at: blocked_code_weights(spark, codes[at], degrees[at], bits, alpha, p)
    w = part(np.arange(len(codes)))
    labels = blocked_bisect(part, len(codes), k, seed) if cut == "bisect" else kmeans(w.embed(k, cut, seed=seed), k, seed, restarts)[0]
    return labels, w.cut_value(labels)


def graph_vertices(degrees: DataFrame, s: Settings) -> tuple[np.ndarray, np.ndarray]:
    """Codes and degrees of the graph, by falling degree."""
    merged = checkpoint(merge_degrees(degrees))
    n = merged.limit(s.max_codes + 1).count()
    if n > s.max_codes:
        if not s.contract:
            raise ValueError(f"more than {s.max_codes} distinct codes: use fewer bits, raise max_codes, or set contract")
        merged = contract_codes(merged, s.max_codes, s.bits)
    rows = merged.orderBy(F.desc("degree"), "code").select("code", "degree").toArrow()  # packed: as objects they would be many times their bytes
    return np.array(rows.column(0).to_pylist(), np.int64), rows.column(1).to_numpy().astype(float)


class CodeGraphClustering(Estimator):
    """Train an encoder by rounds over sites, count codes, cut their graph.

    Input rows: ``row_id, site_id, vec``. ``init`` starts from another model's encoder; with
    n_rounds=0 it is used as it is. Memory of the driver: parameters, one gradient
    a site (or a group of sites), and at most ``max_codes`` codes (more are refused, or merged
    into their nearest ones where ``contract`` is set).
    """

    def __init__(self, settings: Settings, init: "CodeGraphModel | None" = None):
        super().__init__()
        self.settings, self.init = settings, init

    def _fit(self, dataset: DataFrame) -> "CodeGraphModel":
        s, spark = self.settings, dataset.sparkSession
        ledger = cost.Ledger(spark)
        if self.init is not None:
            normalizer, spec = self.init.normalizer, self.init.spec
        else:
            with ledger.timed("normalizer"):
                normalizer = fit_normalizer(dataset, s.normalize)
            first = dataset.select(F.size("vec").alias("d")).first()
            if first is None:
                raise ValueError("no rows to cluster")
            spec = spec_for(s, first["d"])
        trained_here = s.encoder != "hyperplane" and s.train.n_rounds > 0
        pool = n_sites = None
        if trained_here:
            with ledger.timed("pool"):
                pool = checkpoint(candidate_pool(dataset, s.per_site, s.train.seed))
                redraw = lambda r: checkpoint(candidate_pool(dataset, s.per_site, s.train.seed + 7919 * r))
        best = None
        for r in range(max(1, s.encoder_restarts) if trained_here else 1):
            seed = s.train.seed + r
            with ledger.timed("training"):
                if s.encoder == "hyperplane" and self.init is None:
                    got = Trained(spec, random_hyperplane_params(spec, seed))
                elif trained_here:
                    got = train_encoder(pool, spec, replace(s.train, seed=seed), normalizer, None if self.init is None else self.init.theta, refresh=redraw, refresh_every=s.refresh_every)
                else:
                    got = Trained(spec, self.init.theta)
            with ledger.timed("encoding"):
                degrees = checkpoint(site_degrees(encode(dataset.select("site_id", "vec"), spec, got.params, normalizer)))
            with ledger.timed("cut"):
                codes, counts = graph_vertices(degrees, s)
                labels, value = cut_codes(spark, codes, counts, s.bits, s.k, s.cut, s.kmeans_restarts, seed, s.alpha, s.p)
            if best is None or value < best[0]:
                best = (value, got, degrees, codes, counts, labels)
        value, got, degrees, codes, counts, labels = best
        by_site = [r["n"] for r in degrees.groupBy("site_id").agg(F.count("*").alias("n")).orderBy("site_id").collect()]
        n_sites = len(by_site)
        if trained_here:
            ledger.rounds(n_sites, spec.n_params, len(got.history))
        costs = {
            "n_sites": n_sites,
            "n_params": spec.n_params,
            "n_rounds": len(got.history),
            "codes_by_site": by_site,
            "n_codes": merge_degrees(degrees).count(),
            "total_bits": cost.total_bits(n_sites, spec.n_params, len(got.history), by_site, s.bits),
            "label_return_bits": cost.label_return_bits(by_site, s.bits, s.k),
            "cut_value": value,
            "seconds": ledger.seconds,
        }
        return CodeGraphModel(s, spec, got.params, normalizer, codes, counts, labels, got.history, costs)


class CodeGraphModel(Model):
    def __init__(self, settings: Settings, spec: EncoderSpec, params: np.ndarray, normalizer: Normalizer, codes: np.ndarray, degrees: np.ndarray, labels: np.ndarray, history: list[dict], costs: dict):
        super().__init__()
        self.settings, self.spec, self.theta, self.normalizer = settings, spec, params, normalizer
        self.codes, self.degrees, self.labels, self.history, self.costs = codes, degrees, labels, history, costs

    def code_labels(self, spark: SparkSession) -> DataFrame:
        rows = [(int(c), int(d), int(x)) for c, d, x in zip(self.codes, self.degrees, self.labels)]
        return spark.createDataFrame(rows, "code long, degree long, cluster int")

    def encode(self, df: DataFrame) -> DataFrame:
        return encode(df, self.spec, self.theta, self.normalizer)

    def _transform(self, dataset: DataFrame) -> DataFrame:
        if self.spec.bits > 64:
            return assign_clusters(self.encode(dataset), self.code_labels(dataset.sparkSession))
        return encode_and_label(dataset, self.spec, self.theta, self.normalizer, self.codes, self.degrees, self.labels)

    def write(self, path: str, spark: SparkSession) -> None:
        """Two Parquet tables: one row with the encoder, and the labelled codes."""
        meta = json.dumps({"settings": asdict(self.settings), "normalizer": asdict(self.normalizer), "history": self.history, "costs": self.costs})
        row = [(self.spec.to_json(), meta, [float(x) for x in self.theta])]
        spark.createDataFrame(row, "spec string, meta string, params array<double>").coalesce(1).write.mode("overwrite").parquet(f"{path}/encoder")
        self.code_labels(spark).coalesce(1).write.mode("overwrite").parquet(f"{path}/codes")

    @staticmethod
    def read(path: str, spark: SparkSession) -> "CodeGraphModel":
        r = spark.read.parquet(f"{path}/encoder").first()
        meta = json.loads(r["meta"])
        s = meta["settings"]
        s["train"] = TrainConfig(**s["train"])
        s["hidden"] = tuple(s["hidden"]) if s["hidden"] is not None else None
        codes = spark.read.parquet(f"{path}/codes").orderBy(F.desc("degree"), "code").collect()
        n = {k: tuple(v) if isinstance(v, list) else v for k, v in meta["normalizer"].items()}
        return CodeGraphModel(Settings(**s), EncoderSpec.from_json(r["spec"]), np.array(r["params"]), Normalizer(**n), np.array([c["code"] for c in codes], np.int64), np.array([c["degree"] for c in codes], float), np.array([c["cluster"] for c in codes]), meta["history"], meta["costs"])


def assign_clusters(encoded: DataFrame, code_labels: DataFrame, broadcast_up_to: int = 1_000_000) -> DataFrame:
    """encoded with ``cluster``: by its code, and a code without a label by its nearest labelled code.

    The distinct codes are labelled first, so rows meet one table of codes: broadcast where it is
    counted to be small, by key (counts combined, skew split) beyond.
    """
    encoded = checkpoint(encoded)
    known = code_labels.select("code", "cluster")
    unseen = checkpoint(encoded.select("code").distinct().join(known, "code", "left_anti"))
    if not unseen.isEmpty():
        near = nearest_code(unseen, code_labels).join(known.withColumnRenamed("code", "near"), "near").select("code", "cluster")
        known = checkpoint(known.union(near))
    small = known.limit(broadcast_up_to + 1).count() <= broadcast_up_to
    return encoded.join(F.broadcast(known) if small else known, "code", "left").select(*encoded.columns, "cluster")
