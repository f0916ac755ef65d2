"""Sketches and scores over streams: windows, sessions, deduplication, merging into a store."""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from augspark.cluster import holds_files, scratch_path
from augspark.ring import gram


def event_stream(spark: SparkSession, sf_dir: str, schema, per_trigger: int = 1) -> DataFrame:
    """The events table as a file stream; ts becomes a TIMESTAMP, which watermarks need."""
    raw = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", per_trigger).parquet(sf_dir)
    return raw.withColumn("t", F.col("ts").cast("timestamp"))


def windowed(stream: DataFrame, features: Sequence[str], window, delay: str = "1 hour", by: Sequence[str] = ()) -> DataFrame:
    """Gram sketch per window (tumbling, sliding or session) and key."""
    x = [gram.number(f) for f in features]
    aggs = [F.count(F.lit(1)).alias("_c"), *[F.sum(v).alias(f"_s{i}") for i, v in enumerate(x)], *[F.sum(x[i] * x[j]).alias(f"_q{i}_{j}") for i, j in gram.pairs(len(x))]]
    grouped = stream.withWatermark("t", delay).groupBy(window.alias("w"), *by).agg(*aggs)
    return grouped.select(F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), *by, gram.pack(len(x)).alias("g"))


def drain(stream: DataFrame, name: str, checkpoint: str, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there and return its result table, which batches write to shared storage.

    A batch that is repeated overwrites itself. In complete mode the last batch is the whole result.
    """
    spark, path = stream.sparkSession, scratch_path(stream.sparkSession, f"stream-{name}")

    def write(batch: DataFrame, number: int) -> None:
        place = f"{path}/batch=last" if mode == "complete" else f"{path}/batch={number}"
        batch.write.mode("overwrite").parquet(place)

    query = stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    if not holds_files(spark, path):
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(path).select(*stream.columns)


def for_each_batch(stream: DataFrame, merge: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    query = stream.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()


def merge_into(store: str, features: Sequence[str], by: Sequence[str]) -> Callable[[DataFrame, int], None]:
    """A batch's sketch is written under its batch id: a repeated batch overwrites itself, so totals never count twice."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        gram.gamma(batch, features, by).write.mode("overwrite").parquet(f"{store}/batch={batch_id}")

    return merge


def read_store(spark: SparkSession, store: str, m: int, by: Sequence[str]) -> DataFrame:
    return gram.sum_elements(spark.read.parquet(store), m, by)
