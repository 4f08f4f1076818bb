"""Streaming queries, replayed to the end of what is there and compared with batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.vectors import quantize
from ..operators.encode import encode_fixed
from ..operators.features import Normalizer
from ..operators.network import dense_encoder
from ..operators.train import TrainConfig
from ..streaming import streams
from .pipeline import Settings
from .queries_method import DEG_SQL, DIM, SITES, code_sql
from .registry import query


def _vectors(spark, d):
    e = streams.source(spark, d, "embeddings")
    return e.select(F.pmod("vec_id", F.lit(SITES)).cast("int").alias("site_id"), F.col("vec_id").cast("long").alias("row_id"), F.col("embedding").alias("vec"))


def _events(spark, d):
    e = streams.source(spark, d, "events")
    return e.select("event_id", "user_id", "event_type", F.col("ts").cast("timestamp").alias("ts"))


def _plain(df):
    """Window bounds as times without zone, as in the tables."""
    return df.select(*[F.col(c).cast("timestamp_ntz").alias(c) if c in ("start", "end") else F.col(c) for c in df.columns])


@query(f"WITH {code_sql(16)}{DEG_SQL} SELECT * FROM d")
def stream_degrees(spark, d):
    v = _vectors(spark, d).select("site_id", encode_fixed(quantize(F.col("vec")), DIM, 16).alias("code"))
    return streams.run(streams.code_degrees(v), "complete", "last")


@query("SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS \"end\", event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return _plain(streams.run(streams.windowed(_events(spark, d), "1 hour"), "complete", "last"))


@query("SELECT s AS start, s + INTERVAL 2 HOUR AS \"end\", event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 1 HOUR, ts), time_bucket(INTERVAL 1 HOUR, ts) - INTERVAL 1 HOUR]) AS s FROM events) GROUP BY ALL")
def stream_sliding(spark, d):
    return _plain(streams.run(streams.windowed(_events(spark, d), "2 hours", "1 hour"), "complete", "last"))


@query("""SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", user_id, count(*) AS n FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
  (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def stream_session(spark, d):
    return _plain(streams.run(streams.sessions(_events(spark, d), "30 minutes"), "complete", "last"))


@query("SELECT start, start + INTERVAL 1 HOUR AS \"end\", event_type, count(*) AS n FROM (SELECT event_type, time_bucket(INTERVAL 1 HOUR, ts) AS start FROM events) WHERE start + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 DAY GROUP BY start, event_type")
def stream_late(spark, d):
    """Only windows that the watermark has closed come out in append mode."""
    return _plain(streams.run(streams.windowed(_events(spark, d), "1 hour", watermark="1 day"), "append", "files"))


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, d):
    return streams.run(streams.deduplicated(_events(spark, d), ["user_id", "event_type"]).select("user_id", "event_type"), "append", "files")


@query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_join(spark, d):
    """Stream against a static table."""
    c = spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_mktsegment")
    e = _events(spark, d)
    return streams.run(e.join(c, e.user_id == c.c_custkey).select("event_id", "c_mktsegment"), "append", "files")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_interval_join(spark, d):
    return streams.run(streams.click_to_purchase(_events(spark, d)), "append", "files")


def _in_files(spark, d, n: int = 4):
    """The vectors as a stream of n files, one a micro-batch."""
    import uuid

    from ..session import shared_dir
    from ..sources.io import stream_dir
    from .queries_method import vectors

    path = f"{shared_dir(spark)}/files-{uuid.uuid4().hex}"
    v = vectors(spark, d).select("site_id", "row_id", "vec")
    for i in range(n):
        v.where(F.pmod(F.xxhash64("row_id"), F.lit(n)) == i).coalesce(1).write.mode("append").parquet(path)
    return stream_dir(spark, path, v.schema, max_files=1), v


@query()
def stream_reservoirs(spark, d):
    """A sample of each site, kept up over several micro-batches."""
    stream, _ = _in_files(spark, d)
    return streams.run(streams.site_reservoirs(stream, 16), "update", "merge", keys=["site_id"])


@query()
def stream_online_round(spark, d):
    """The online form: a round a micro-batch, several of them."""
    import uuid

    from ..session import shared_dir
    from ..streaming.online import OnlineCodeGraph

    stream, _ = _in_files(spark, d)
    online = OnlineCodeGraph(spark, Settings(10, 16, train=TrainConfig(batch=32)), dense_encoder(DIM, 16), Normalizer("none"), f"{shared_dir(spark)}/online-{uuid.uuid4().hex}")
    online.run(stream)
    return spark.createDataFrame([(h["round"], h["loss"], h["drift"]) for h in online.history], "round int, loss double, drift double")


@query(f"WITH {code_sql(16)}{DEG_SQL}, a AS (SELECT code, sum(degree) AS n FROM d WHERE site_id < 5 GROUP BY 1), b AS (SELECT code, sum(degree) AS n FROM d WHERE site_id >= 5 GROUP BY 1) SELECT round(sum(abs(coalesce(a.n, 0) / (SELECT CAST(sum(n) AS DOUBLE) FROM a) - coalesce(b.n, 0) / (SELECT CAST(sum(n) AS DOUBLE) FROM b))) / 2, 9) AS drift FROM a FULL JOIN b USING (code)")
def code_drift(spark, d):
    from ..streaming.online import drift
    from .queries_method import site_degrees

    s = site_degrees(spark, d)
    return drift(s.where("site_id < 5"), s.where("site_id >= 5")).select(F.round("drift", 9).alias("drift"))


@query(f"WITH {code_sql(16)} SELECT site_id, round(avg(CASE WHEN code % 4 = code % 8 THEN 0.0 ELSE 1.0 END), 9) AS changed FROM c GROUP BY site_id")
def codes_changed(spark, d):
    from ..streaming.online import changed_codes
    from .queries_method import coded

    c = coded(spark, d, 16).select("site_id", "row_id", "code")
    return changed_codes(c.withColumn("code", F.col("code") % 4), c.withColumn("code", F.col("code") % 8)).select("site_id", F.round("changed", 9).alias("changed"))
