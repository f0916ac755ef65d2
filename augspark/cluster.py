"""Helpers that keep jobs recoverable on a cluster: shared scratch tables and the session's checkpoint folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def checkpoint_dir(spark: SparkSession) -> str:
    """The session's shared checkpoint folder. A temporary one is set only where the session names none and is local."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        shared = sc.getConf().get("spark.checkpoint.dir")
        if not shared and not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(shared or tempfile.mkdtemp(prefix="augspark-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def scratch_path(spark: SparkSession, name: str) -> str:
    """A new path below the checkpoint folder; the driver's file system client removes it when the application ends."""
    path = f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4().hex}"
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(jpath)
    return path


def drop_path(spark: SparkSession, path: str) -> None:
    """Remove a scratch path that no later plan reads."""
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(jpath, True)


def materialize(df: DataFrame, name: str = "step", path: str | None = None) -> DataFrame:
    """Write a frame once to shared storage and return the reader over it.

    Unlike ``checkpoint()`` the lineage is computed once, and unlike a cached block the files outlive a lost executor.
    """
    spark = df.sparkSession
    path = path or scratch_path(spark, name)
    df.write.mode("overwrite").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def list_files(spark: SparkSession, path: str, suffix: str = "") -> list[tuple[str, int]]:
    """(uri, bytes) of the data files directly below a folder, listed by the cluster's own file system client."""
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = jpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    found = []
    for status in fs.listStatus(jpath):
        name = status.getPath().getName()
        if status.isFile() and not name.startswith(("_", ".")) and name.endswith(suffix):
            found.append((status.getPath().toString(), int(status.getLen())))
    return sorted(found)


def holds_files(spark: SparkSession, path: str) -> bool:
    """Whether a folder exists and is not empty."""
    jpath = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = jpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    return bool(fs.exists(jpath) and len(fs.listStatus(jpath)))


def free_shuffles(spark: SparkSession) -> None:
    """Let the session's cleaner remove shuffle files of jobs that are done: it acts only on what the JVM has collected."""
    spark._jvm.System.gc()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
