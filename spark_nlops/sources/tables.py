"""Readers and writers: Parquet tables, row formats, partitioned sinks, prompt memos and call ledgers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_table(spark: SparkSession, folder: str, name: str, columns: list[str] | None = None) -> DataFrame:
    df = spark.read.parquet(f"{folder}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_rows(spark: SparkSession, path: str, form: str, schema: T.StructType) -> DataFrame:
    """JSON lines, CSV, ORC or text with a given schema (no inference pass)."""
    reader = spark.read.schema(schema)
    return reader.option("header", "true").csv(path) if form == "csv" else reader.format(form).load(path)


def write_rows(df: DataFrame, path: str, form: str) -> None:
    writer = df.write.mode("overwrite")
    (writer.option("header", "true").csv(path) if form == "csv" else writer.format(form).save(path))


def write_partitioned(df: DataFrame, path: str, by: list[str]) -> None:
    """Partitioned Parquet; rows are first brought together by partition value, so that each task writes few files."""
    df.repartition(*by).write.mode("overwrite").partitionBy(*by).parquet(path)


def append_ledger(df: DataFrame, path: str) -> None:
    """Call ledgers (route, calls, ...) as an append-only table."""
    df.write.mode("append").parquet(path)
