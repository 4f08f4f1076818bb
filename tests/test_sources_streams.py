"""Sources, sinks, the synthetic data source, streams and the online form."""

import json
import math

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from codecut.functions import udfs
from codecut.operators.features import Normalizer
from codecut.operators.network import dense_encoder
from codecut.operators.train import TrainConfig
from codecut.plans.pipeline import CodeGraphClustering, Settings
from codecut.sources import gaussians, io
from codecut.streaming import streams
from codecut.streaming.online import OnlineCodeGraph, changed_codes, drift


@pytest.mark.parametrize("fmt", ["parquet", "csv", "json", "orc"])
def test_formats(spark, sf, tmp_path, fmt):
    n = io.load(spark, sf, "nation")
    io.save(n, f"{tmp_path}/{fmt}", fmt)
    assert io.read_as(spark, f"{tmp_path}/{fmt}", fmt, n.schema).exceptAll(n).isEmpty()


def test_pushdown(spark, sf):
    plan = io.load(spark, sf, "lineitem", ["l_orderkey", "l_quantity"]).where("l_quantity > 49")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,49.0)]" in plan and "l_comment" not in plan
    assert "ReadSchema: struct<l_orderkey:bigint,l_quantity:double>" in plan


def test_corrupt_rows(spark, tmp_path):
    (tmp_path / "x.json").write_text('{"a": 1}\n{"a": oops\n{"a": 3}\n')
    good, bad = io.read_json_tolerant(spark, f"{tmp_path}/x.json", T.StructType([T.StructField("a", T.LongType())]))
    assert sorted(r["a"] for r in good.cache().collect()) == [1, 3] and bad.count() == 1


def test_code_store_prunes(spark, tmp_path):
    df = spark.range(100).select((F.col("id") % 4).cast("int").alias("site_id"), F.col("id").alias("code"), F.lit(1).alias("degree"))
    io.write_codes(df, f"{tmp_path}/codes")
    one = spark.read.parquet(f"{tmp_path}/codes").where("site_id = 2")
    assert one.count() == 25 and "PartitionFilters: [isnotnull(site_id" in one._jdf.queryExecution().executedPlan().toString()
    with pytest.raises(ValueError):
        io.collect_guarded(df, 10)


def test_generator_moments():
    x = gaussians.subspace_cluster(64, 4, 4000, 1)
    u = x.mean(0)
    assert np.abs(u).max() <= 20 / math.log2(64) + 0.1
    # a map of unit Frobenius norm gives total variance 1, the noise adds 1/10
    assert ((x - u) ** 2).sum(1).mean() == pytest.approx(1.1, abs=0.05)
    assert len(gaussians.subspace_plan(1)) == 120 and len(gaussians.subspace_plan(5)) == 200
    wave, y = gaussians.waveform_noise(3000, 2)
    assert wave.shape == (3000, 40) and abs(wave[:, 21:].var() - 1) < 0.05 and set(y) == {0, 1, 2}


def test_data_source(spark):
    gaussians.register(spark)
    options = {"dim": 64, "per_cluster": 5, "per_latent": 1, "seed": 3}
    batch = spark.read.format("subspace_gaussians").options(**options).load()
    direct = gaussians.subspace_dataset(spark, 1, 1, 5, 3)
    assert batch.count() == 30 and batch.exceptAll(direct).isEmpty()
    stream = spark.readStream.format("subspace_gaussians").options(**options).load()
    assert streams.run(stream.select("row_id", "truth")).count() == 30


def test_late_rows_are_left_out_of_windows(spark, tmp_path):
    def put(i, rows):
        spark.createDataFrame(rows, "event_id long, event_type string, t string").select("event_id", "event_type", F.to_timestamp("t").alias("ts")).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")

    schema = "event_id long, event_type string, ts timestamp"
    read = lambda: streams.stream_dir(spark, f"{tmp_path}/in", schema)
    put(0, [(1, "a", "2024-01-01 10:00:00"), (2, "a", "2024-01-01 12:30:00")])
    run = lambda: streams.windowed(read(), "1 hour", watermark="30 minutes").writeStream.outputMode("append").format("parquet").option("path", f"{tmp_path}/out").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start().awaitTermination()
    run()
    put(1, [(3, "a", "2024-01-01 10:10:00"), (4, "a", "2024-01-01 15:00:00")])  # the first is late by now
    run()
    put(2, [(5, "a", "2024-01-01 20:00:00")])
    run()
    got = {(r["start"].hour, r["n"]) for r in spark.read.parquet(f"{tmp_path}/out").collect()}
    assert (10, 1) in got and (12, 1) in got and (15, 1) in got and (10, 2) not in got


def test_reservoirs(spark, sf, tmp_path):
    """Over several micro-batches, some of which change few sites, the sample is the one of all rows."""
    e = io.load(spark, sf, "embeddings").select((F.col("vec_id") % 3).cast("int").alias("site_id"), F.col("vec_id").cast("long").alias("row_id"), F.col("embedding").alias("vec"))
    for part in (F.col("row_id") % 2 == 0, (F.col("row_id") % 2 == 1) & (F.col("site_id") > 0), F.lit(False)):
        e.where(part).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    got = streams.run(streams.site_reservoirs(streams.stream_dir(spark, f"{tmp_path}/in", e.schema, max_files=1), 10), "update", "merge", keys=["site_id"])
    h = F.pmod(F.xxhash64("row_id", F.lit(0)), F.lit(1 << 40))
    seen = e.where("row_id % 2 = 0 or site_id > 0").select("site_id", "row_id", h.alias("h")).collect()
    want = {s: sorted(r["row_id"] for r in sorted((r for r in seen if r["site_id"] == s), key=lambda r: (r["h"], r["row_id"]))[:10]) for s in range(3)}
    assert {r["site_id"]: r["row_ids"] for r in got.collect()} == want


def test_online(spark, sf, tmp_path):
    e = io.load(spark, sf, "embeddings").select((F.col("vec_id") % 3).cast("int").alias("site_id"), F.col("vec_id").cast("long").alias("row_id"), F.col("embedding").alias("vec"))
    batches = [e.where(F.col("row_id") % 3 == i) for i in range(3)]
    s = Settings(4, 12, train=TrainConfig(batch=16))
    make = lambda name: OnlineCodeGraph(spark, s, dense_encoder(64, 12), Normalizer("none"), f"{tmp_path}/{name}", per_site=40)
    whole = make("whole")
    for i, b in enumerate(batches):
        whole.step(b, i)
        # stopped after every micro-batch and begun anew
        make("cut").step(b, i)
    assert whole.version == 3 and len(whole.history) == 3
    again = make("cut")
    assert np.array_equal(again.params, whole.params) and again.history == whole.history and again.cut_at == whole.cut_at
    assert all(np.array_equal(a, b) for a, b in zip(again.labels[:3], whole.labels[:3]))
    assert again.model().transform(e).where("cluster is null").isEmpty()
    # a micro-batch that is replayed changes nothing
    again.step(e, 1)
    assert again.version == 3 and np.array_equal(again.params, whole.params)
    d = spark.read.parquet(f"{tmp_path}/cut/degrees/v1")
    assert drift(d, d).first()[0] == 0
    codes = whole.model().encode(e)
    assert all(r["changed"] == 0 for r in changed_codes(codes, codes).collect())


def test_user_functions(spark, sf):
    udfs.register(spark)
    assert spark.sql("SELECT hamming(5, 6), code_l1(5, 6), pack_bits(array(1, 0, 1)), vec_dot(array(1D, 2D), array(3D, 4D)), vec_l2(array(0D, 0D), array(3D, 4D))").first()[:] == (2, 4, 5, 11.0, 5.0)
    assert spark.sql("SELECT count(*) FROM code_neighbors(0, 10, 2)").first()[0] == 1 + 10 + 45
    assert [r["gram"] for r in spark.sql("SELECT * FROM char_ngrams('abcd', 3)").collect()] == ["abc", "bcd"]
    assert [tuple(r) for r in spark.sql("SELECT * FROM bit_bands(13, 4, 2)").collect()] == [(0, 1), (1, 3)]
    df = io.load(spark, sf, "embeddings").select(F.col("vec_id").alias("row_id"), F.lit(0).alias("site_id"), F.col("embedding").alias("vec"))
    model = CodeGraphClustering(Settings(3, 8, encoder="hyperplane")).fit(df)
    a = df.select("row_id", udfs.encode_udf(model)("vec").alias("code"))
    assert a.exceptAll(model.encode(df).select("row_id", "code")).isEmpty()
    m = df.groupBy("site_id").agg(udfs.mean_vector("vec").alias("m"), udfs.vector_sum("vec").alias("s")).first()
    assert np.allclose(np.array(m["m"]) * df.count(), m["s"])
    assert a.agg(udfs.medoid_code("code")).first()[0] is not None
    assert json.loads(json.dumps(len(df.select(udfs.normalize_udf(model.normalizer)("vec").alias("v")).first()["v"]))) == 64
