"""The online form: every micro-batch is one round; codes and counts are kept by model version."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.encode import encode, merge_degrees, site_degrees
from ..operators.features import Normalizer
from ..operators.network import EncoderSpec, init_params
from ..operators.sampling import bottom_rows, candidate_pool
from ..operators.train import train_round
from ..plans.pipeline import CodeGraphModel, Settings, cut_codes, graph_vertices
from ..session import shared_dir

_STEP = "version int, params array<double>, loss double, drift double, cut_at int"


class OnlineCodeGraph:
    """State lives in ``path``: the parameters of each version (one a micro-batch), the candidate pool, and counts of codes.

    A new object goes on from the newest version that is written, with its pool, counts, labels and history. A
    micro-batch that is replayed after a failure finds its version written and does nothing, so
    each is used once. Counts of codes of different versions are not mixed: a new version
    starts from the retained pool, coded anew.
    """

    def __init__(self, spark: SparkSession, settings: Settings, spec: EncoderSpec, normalizer: Normalizer, path: str | None = None, per_site: int = 256, cut_every: int = 3, drift_above: float = 0.25):
        self.spark, self.s, self.spec, self.normalizer = spark, settings, spec, normalizer
        self.path = path or f"{shared_dir(spark)}/online"
        self.per_site, self.cut_every, self.drift_above = per_site, cut_every, drift_above
        self.params, self.version, self.labels, self.cut_at, self.history = init_params(spec, settings.train.seed), 0, None, 0, []
        self._recover()

    def _at(self, what: str, version: int) -> str:
        return f"{self.path}/{what}/v{version}"

    def _there(self, path: str) -> bool:
        where = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return where.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(where)

    def _recover(self) -> None:
        if not self._there(f"{self.path}/step"):
            return
        steps = self.spark.read.schema(_STEP).parquet(f"{self.path}/step/*").select("version", "loss", "drift").orderBy("version").collect()  # three numbers a round
        if not steps:
            return
        last = self.spark.read.schema(_STEP).parquet(self._at("step", steps[-1]["version"])).first()
        self.params, self.version, self.cut_at = np.array(last["params"]), last["version"], last["cut_at"]
        self.history = [{"round": r["version"], "loss": r["loss"], "drift": r["drift"]} for r in steps]
        if self.cut_at:
            rows = self.spark.read.parquet(self._at("labels", self.cut_at)).orderBy(F.desc("degree"), "code").collect()
            self.labels = (np.array([r["code"] for r in rows], np.int64), np.array([r["degree"] for r in rows]), np.array([r["cluster"] for r in rows]), rows[0]["cut_value"] if rows else 0.0)

    def step(self, batch: DataFrame, batch_id: int) -> None:
        """One round on a micro-batch of ``site_id, row_id, vec``."""
        version = batch_id + 1
        if version <= self.version:
            return
        new = batch.select("site_id", "row_id", "vec")
        if self.version:
            new = new.unionByName(self.spark.read.parquet(self._at("pool", self.version)))
        kept = bottom_rows(new, self.per_site, self.s.train.seed)
        kept.select("site_id", F.col("key").alias("row_id"), "vec").write.mode("overwrite").parquet(self._at("pool", version))
        pool = self.spark.read.parquet(self._at("pool", version))
        sites = candidate_pool(pool, self.per_site, self.s.train.seed)
        n_sites = sites.count()
        if not n_sites:
            return
        self.params, loss = train_round(sites, self.spec, self.params, self.s.train, self.normalizer, version, n_sites)
        seeded = site_degrees(encode(pool.select("site_id", "vec"), self.spec, self.params, self.normalizer))
        fresh = site_degrees(encode(batch.select("site_id", "vec"), self.spec, self.params, self.normalizer))
        seeded.unionByName(fresh).groupBy("site_id", "code").agg(F.sum("degree").alias("degree")).write.mode("overwrite").parquet(self._at("degrees", version))
        moved = float(drift(self.spark.read.parquet(self._at("degrees", self.version)), self.spark.read.parquet(self._at("degrees", version))).first()[0]) if self.version else 1.0
        self.version = version
        if self.labels is None or version % self.cut_every == 0 or moved > self.drift_above:
            self.cut()
        self.history.append({"round": version, "loss": loss, "drift": moved})
        row = [(version, [float(x) for x in self.params], float(loss), moved, self.cut_at)]
        self.spark.createDataFrame(row, _STEP).coalesce(1).write.mode("overwrite").parquet(self._at("step", version))

    def cut(self) -> None:
        codes, degrees = graph_vertices(self.spark.read.parquet(self._at("degrees", self.version)), self.s)
        labels, value = cut_codes(self.spark, codes, degrees, self.s.bits, self.s.k, restarts=5)
        self.labels, self.cut_at = (codes, degrees, labels, value), self.version
        rows = [(int(c), float(d), int(x), float(value)) for c, d, x in zip(codes, degrees, labels)]
        self.spark.createDataFrame(rows, "code long, degree double, cluster int, cut_value double").coalesce(1).write.mode("overwrite").parquet(self._at("labels", self.version))

    def run(self, stream: DataFrame, checkpoint: str | None = None, trigger: dict | None = None) -> "OnlineCodeGraph":
        where = checkpoint or f"{self.path}/checkpoint"
        stream.writeStream.foreachBatch(self.step).option("checkpointLocation", where).trigger(**(trigger or {"availableNow": True})).start().awaitTermination()
        return self

    def model(self) -> CodeGraphModel:
        codes, degrees, labels, value = self.labels
        return CodeGraphModel(self.s, self.spec, self.params, self.normalizer, codes, degrees, labels, self.history, {"cut_value": value})


def drift(old: DataFrame, new: DataFrame) -> DataFrame:
    """One row ``drift``: half the sum of differences of the shares of codes (total variation), of two tables of degrees."""
    share = lambda df, name: merge_degrees(df).crossJoin(F.broadcast(df.agg(F.sum("degree").alias("all")))).select("code", (F.col("degree") / F.col("all")).alias(name))
    both = share(old, "a").join(share(new, "b"), "code", "full")
    return both.agg((F.sum(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0)))) / 2).alias("drift"))


def changed_codes(old: DataFrame, new: DataFrame) -> DataFrame:
    """``site_id, changed``: share of a site's rows whose code differs between two encodings ``site_id, row_id, code``."""
    a = old.select("site_id", "row_id", F.col("code").alias("a"))
    both = a.join(new.select("site_id", "row_id", F.col("code").alias("b")), ["site_id", "row_id"])
    return both.groupBy("site_id").agg(F.avg((~F.col("a").eqNullSafe(F.col("b"))).cast("double")).alias("changed"))
