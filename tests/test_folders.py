"""Tables that are folders of files."""


def test_stream_of_a_folder(spark, sf, tmp_path):
    from codecut.streaming import streams

    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    e.repartition(3).write.parquet(f"{tmp_path}/embeddings.parquet")
    spark.range(5).write.parquet(f"{tmp_path}/other.parquet")
    for d in (sf, str(tmp_path)):
        got = streams.run(streams.source(spark, d, "embeddings").select("vec_id"), "append", "files")
        assert sorted(r[0] for r in got.collect()) == sorted(r[0] for r in e.select("vec_id").collect())
