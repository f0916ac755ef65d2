"""Readers and writers of corpus tables and sketch stores."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def collect(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A table in any of Spark's file formats; a declared schema saves a pass over the files."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_store(sketches: DataFrame, path: str) -> None:
    """Sketches partitioned by key name, so a request opens only the keys it has."""
    sketches.write.mode("overwrite").partitionBy("key_name").parquet(path)


def write_bucketed(sketches: DataFrame, table: str, buckets: int = 64) -> None:
    """Sketches bucketed by key value: joins with equally bucketed request sketches need no exchange."""
    sketches.write.mode("overwrite").bucketBy(buckets, "key_value").sortBy("key_value").saveAsTable(table)
