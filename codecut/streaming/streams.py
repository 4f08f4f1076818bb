"""Streaming operators and sinks."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..session import shared_dir
from ..sources.io import stream_dir


def source(spark: SparkSession, sf_dir: str, name: str, max_files: int | None = None) -> DataFrame:
    """A table as a stream of its files, whether it is one file or a folder of them."""
    schema = spark.read.parquet(f"{sf_dir}/{name}.parquet").schema
    return stream_dir(spark, f"{sf_dir}/{name}.parque[t]", schema, max_files=max_files)  # a pattern may name a single file


def run(stream: DataFrame, mode: str = "append", sink: str = "files", name: str | None = None, checkpoint: str | None = None, trigger: dict | None = None, keys: list[str] | None = None, out: str | None = None) -> DataFrame:
    """Run to the end of the available input and return what came out.

    files: appended Parquet files. last: each micro-batch replaces the result (for complete mode).
    merge: the rows of a micro-batch replace those with the same keys (for update mode); each batch writes a whole
    new version, so one that is replayed writes the same again. memory: a table in the driver, for small results.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    w = stream.writeStream.outputMode(mode).option("checkpointLocation", checkpoint or f"{base}/checkpoint").trigger(**(trigger or {"availableNow": True}))
    out = out or f"{base}/out"
    if sink == "memory":
        table = name or f"m{uuid.uuid4().hex}"
        w.format("memory").queryName(table).start().awaitTermination()
        return spark.table(table)
    if sink == "last":
        w.foreachBatch(lambda df, _: df.write.mode("overwrite").parquet(out)).start().awaitTermination()
    elif sink == "merge":
        done = []

        def merge(df: DataFrame, batch: int) -> None:
            new = df
            if batch:
                old = df.sparkSession.read.schema(stream.schema).parquet(f"{out}/v{batch - 1}")
                new = df.unionByName(old.join(df.select(*keys), keys, "left_anti"))
            new.write.mode("overwrite").parquet(f"{out}/v{batch}")
            done.append(batch)

        w.foreachBatch(merge).start().awaitTermination()
        if not done:
            return spark.createDataFrame([], stream.schema)
        return spark.read.schema(stream.schema).parquet(f"{out}/v{done[-1]}")
    else:
        w.format("parquet").option("path", out).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def code_degrees(encoded: DataFrame) -> DataFrame:
    """Running counts of codes by site."""
    return encoded.groupBy("site_id", "code").agg(F.count("*").alias("degree"))


def windowed(events: DataFrame, width: str, slide: str | None = None, watermark: str | None = None, by: str = "event_type") -> DataFrame:
    """Counts by time window; with a watermark, rows later than it are left out and finished windows are dropped from the state."""
    e = events.withWatermark("ts", watermark) if watermark else events
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return e.groupBy(w.alias("w"), by).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n")


def sessions(events: DataFrame, gap: str, by: str = "user_id") -> DataFrame:
    s = events.groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count("*").alias("n"))
    return s.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n")


def deduplicated(events: DataFrame, keys: list[str], watermark: str | None = None) -> DataFrame:
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(keys) if watermark else events.dropDuplicates(keys)


def click_to_purchase(events: DataFrame, within: str = "1 hour", watermark: str = "2 hours", first: str = "click", then: str = "purchase") -> DataFrame:
    """Stream-stream interval join: purchases of a user at most ``within`` after a click."""
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("ua"), F.col("ts").alias("ta"), F.col("event_id").alias("a")).withWatermark("ta", watermark)
    b = events.where(F.col("event_type") == then).select(F.col("user_id").alias("ub"), F.col("ts").alias("tb"), F.col("event_id").alias("b")).withWatermark("tb", watermark)
    return a.join(b, F.expr(f"ua = ub AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("a", "b")


def site_reservoirs(vectors: DataFrame, size: int, seed: int = 0) -> DataFrame:
    """A bounded sample of each site kept in the state: the rows with the smallest hashes.

    Input ``site_id, row_id, vec``; output, when a site's sample changes, its ``site_id, n, row_ids``.
    """
    import pandas as pd

    h = vectors.select("site_id", "row_id", F.pmod(F.xxhash64("row_id", F.lit(seed)), F.lit(1 << 40)).alias("h"))

    def update(key, frames, state):
        kept = dict(zip(*state.get)) if state.exists else {}
        before = set(kept)
        for f in frames:
            kept.update(zip(f["row_id"].tolist(), f["h"].tolist()))
        kept = dict(sorted(kept.items(), key=lambda x: (x[1], x[0]))[:size])
        state.update((list(kept), list(kept.values())))
        if set(kept) != before:
            yield pd.DataFrame({"site_id": [key[0]], "n": [len(kept)], "row_ids": [sorted(kept)]})

    return h.groupBy("site_id").applyInPandasWithState(update, "site_id int, n long, row_ids array<long>", "ids array<long>, hashes array<long>", "update", GroupStateTimeout.NoTimeout)
