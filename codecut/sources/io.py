"""Reading and writing tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def save(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite") -> None:
    w = df.write.mode(mode)
    (w.option("header", True) if fmt == "csv" else w).format(fmt).save(path)


def read_as(spark: SparkSession, path: str, fmt: str, schema) -> DataFrame:
    """With a given schema: nothing is inferred, so nothing is read twice."""
    r = spark.read.schema(schema)
    return (r.option("header", True) if fmt == "csv" else r).format(fmt).load(path)


def read_json_tolerant(spark: SparkSession, path: str, schema: T.StructType) -> tuple[DataFrame, DataFrame]:
    """(good rows, raw lines that do not fit)."""
    wide = T.StructType([*schema.fields, T.StructField("_corrupt_record", T.StringType())])
    # parsed from lines: the JSON reader refuses queries on the raw record alone
    x = spark.read.text(path).select(F.from_json("value", wide, {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_corrupt_record"}).alias("x"), "value")
    good = x.where(F.col("x._corrupt_record").isNull()).select(*[F.col(f"x.{f.name}").alias(f.name) for f in schema.fields])
    return good, x.where(F.col("x._corrupt_record").isNotNull()).select("value")


def write_codes(site_codes: DataFrame, path: str) -> None:
    """Codes and counts by site; within files by code, so that row groups can be skipped."""
    site_codes.repartition("site_id").sortWithinPartitions("site_id", "code").write.mode("overwrite").partitionBy("site_id").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A table whose later joins on key need no shuffle."""
    df.repartition(buckets, key).write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def stream_dir(spark: SparkSession, path: str, schema, pattern: str | None = None, max_files: int | None = None) -> DataFrame:
    r = spark.readStream.schema(schema)
    if pattern:
        r = r.option("pathGlobFilter", pattern)
    if max_files:
        r = r.option("maxFilesPerTrigger", max_files)
    return r.parquet(path)


def collect_guarded(df: DataFrame, max_rows: int):
    """All rows as a pandas frame, or an error if there are more than max_rows."""
    out = df.limit(max_rows + 1).toPandas()
    if len(out) > max_rows:
        raise ValueError(f"more than {max_rows} rows")
    return out


def register_views(spark: SparkSession, sf_dir: str, names: list[str] = TABLES) -> None:
    for name in names:
        load(spark, sf_dir, name).createOrReplaceTempView(name)
