"""Readers and writers with one way to call them; each is Spark's own, so filters and columns are pushed to the files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, path: str | list[str], kind: str = "parquet", schema=None, **options) -> DataFrame:
    """kind: parquet, csv, json, text, whole (a file a row), orc, table or jdbc."""
    if kind == "table":
        return spark.table(path)
    if kind == "jdbc":
        return spark.read.format("jdbc").options(url=path, **options).load()
    reader = spark.read.options(**options)
    if schema is not None:
        reader = reader.schema(schema)
    elif kind == "csv" and "inferSchema" not in options:
        reader = reader.option("inferSchema", True)
    if kind == "whole":
        return reader.option("wholetext", True).text(path)
    return getattr(reader, kind)(path)


def read_split(spark: SparkSession, train: str, test: str, kind: str = "parquet", **options) -> DataFrame:
    """Two files as one collection with a column `split`."""
    a = read(spark, train, kind, **options).withColumn("split", F.lit("train"))
    b = read(spark, test, kind, **options).withColumn("split", F.lit("test"))
    return a.unionByName(b)


def in_memory(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def read_stream(spark: SparkSession, path: str, schema, kind: str = "parquet", **options) -> DataFrame:
    return spark.readStream.schema(schema).options(**options).format(kind).load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", mode: str = "errorifexists", partition_by: list[str] = (), **options) -> None:
    """kind: parquet, csv, json, text, orc or noop (runs the plan and writes nothing)."""
    w = df.write.mode("overwrite" if kind == "noop" else mode).options(**options)
    if partition_by:
        w = w.partitionBy(*partition_by)
    w.format(kind).save(*([] if kind == "noop" else [path]))


def write_bucketed(df: DataFrame, table: str, by: str, buckets: int, mode: str = "overwrite") -> None:
    """A table whose joins and aggregations on `by` need no shuffle."""
    df.write.mode(mode).bucketBy(buckets, by).sortBy(by).saveAsTable(table)
