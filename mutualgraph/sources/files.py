"""Edge lists and results in files: CSV, JSON, ORC and Parquet with explicit schemas; partitioned and bucketed sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])
ANCHORS = T.StructType([T.StructField("u1", T.LongType()), T.StructField("u2", T.LongType())])
POSTS = T.StructType([T.StructField("post_id", T.LongType()), T.StructField("user_id", T.LongType())])
ATTRIBUTES = T.StructType([T.StructField("post_id", T.LongType()), T.StructField("kind", T.StringType()), T.StructField("attr", T.StringType())])


def read(spark: SparkSession, path: str, schema: T.StructType, format: str = "parquet", **options) -> DataFrame:
    """Rows of a file or a partitioned folder; CSV and JSON rows that are malformed in
    the columns that are read are dropped."""
    reader = spark.read.schema(schema).options(**({"mode": "DROPMALFORMED"} if format in ("csv", "json") else {}) | options)
    return reader.format(format).load(path)


def write_partitioned(df: DataFrame, path: str, by: str, mode: str = "overwrite") -> None:
    """One folder for each value of `by` (path counts by path, attributes by kind): readers prune by it."""
    df.write.mode(mode).partitionBy(by).parquet(path)


def write_bucketed(S: DataFrame, name: str, buckets: int, by: str = "dst", mode: str = "overwrite") -> DataFrame:
    """Closeness as a table bucketed and sorted by the column that the products join on: it's never shuffled again."""
    S.repartition(buckets, by).write.mode(mode).bucketBy(buckets, by).sortBy(by).saveAsTable(name)
    return S.sparkSession.table(name)


def append_trace(trace: DataFrame, path: str) -> None:
    trace.write.mode("append").parquet(path)


def write_report(report: DataFrame, path: str) -> None:
    report.write.mode("overwrite").json(path)
