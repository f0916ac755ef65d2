"""One store of all sketches of a corpus: (key_name, sid, key_value, g) in Parquet, partitioned by key name.

A sid names one version of a dataset. However many datasets a request considers, their sketches of a key are one scan of
that key's partition, restricted to the sids asked for.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from augspark.cluster import drop_path, scratch_path
from augspark.sketch.build import ALL

SCHEMA = "sid string, key_value string, g struct<c: double, s: array<double>, q: array<double>>, key_name string"
#: Sids named in a filter; more are joined as a table.
LISTED = 200
#: Files that a task writes at once, by key name; only a task with more key names sorts its sketches.
OPEN, WRITERS = 4, "spark.sql.maxConcurrentOutputFileWriters"


class SketchStore:
    def __init__(self, spark: SparkSession, path: str | None = None) -> None:
        self.spark, self.path = spark, path or scratch_path(spark, "sketch-store")

    def append(self, sketches: DataFrame) -> None:
        """Add (sid, key_name, key_value, g). Each sid is written once, so a reader never sees half of a version."""
        own = sketches.select("sid", "key_value", "g", "key_name")
        was = self.spark.conf.get(WRITERS)
        self.spark.conf.set(WRITERS, str(OPEN))
        try:
            own.write.mode("append").partitionBy("key_name").parquet(self.path)
        finally:
            self.spark.conf.set(WRITERS, was)

    def read(self, key_name: str, sids: Sequence[str]) -> DataFrame:
        """(sid, key_value, g) of a key's sketches."""
        return self.read_keys([key_name], sids).select("sid", "key_value", "g")

    def read_keys(self, key_names: Sequence[str], sids: Sequence[str]) -> DataFrame:
        """(key_name, sid, key_value, g) of several keys' sketches in one scan: partition pruning by key, then the sids."""
        found = self.spark.read.schema(SCHEMA).parquet(self.path).filter(F.col("key_name").isin(list(key_names)))
        if len(sids) <= LISTED:
            found = found.filter(F.col("sid").isin(list(sids)))
        else:
            wanted = self.spark.createDataFrame([(s,) for s in sids], "sid string")
            found = found.join(F.broadcast(wanted), "sid", "left_semi")  # a row a candidate of the request
        return found.select("key_name", "sid", "key_value", "g")

    def total(self, sids: Sequence[str]) -> DataFrame:
        """(sid, g): the grand totals."""
        return self.read(ALL, sids).select("sid", "g")

    def compact(self, live: Sequence[str], files: int = 1) -> None:
        """Rewrite the store with the live sids only, in few files a key."""
        path, was = scratch_path(self.spark, "sketch-store"), self.path
        wanted = self.spark.createDataFrame([(s,) for s in live], "sid string")
        every = self.spark.read.schema(SCHEMA).parquet(was).join(F.broadcast(wanted), "sid", "left_semi")
        dealt = every.repartition("key_name", F.pmod(F.xxhash64("key_value"), F.lit(files))).sortWithinPartitions("key_name", "sid")
        dealt.select("sid", "key_value", "g", "key_name").write.partitionBy("key_name").parquet(path)
        self.path = path
        drop_path(self.spark, was)

    def bucketed(self, table: str, buckets: int = 64) -> DataFrame:
        """A table of the store bucketed by key value: equally bucketed request sketches join it without an exchange."""
        from augspark.sources.collect import write_bucketed

        write_bucketed(self.spark.read.schema(SCHEMA).parquet(self.path), table, buckets)
        return self.spark.table(table)
