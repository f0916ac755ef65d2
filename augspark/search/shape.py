"""Rows and columns of a plan's output from sketches, without joining rows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def estimate(user_counts: DataFrame, candidate_counts: DataFrame, keys: Sequence[str], user_cols: int, mode: str = "weight", all_rows: float | None = None) -> DataFrame:
    """user (keys, c), candidates (dataset, keys, c, p) -> (dataset, rows, cols) of the left join.

    all_rows counts rows with a null key too, which are in no sketch by key.
    """
    total = user_counts.agg(F.sum("c").alias("_all")) if all_rows is None else user_counts.sparkSession.createDataFrame([(float(all_rows),)], "_all double")
    met = user_counts.withColumnRenamed("c", "_c").join(candidate_counts, list(keys))
    sums = met.groupBy("dataset").agg(F.sum("_c").alias("hit"), F.sum(F.col("_c") * F.col("c")).alias("fan"))
    every = candidate_counts.groupBy("dataset").agg(F.max("p").alias("p")).crossJoin(F.broadcast(total))  # a single row
    rows = F.col("_all") if mode != "raw" else F.col("_all") - F.coalesce("hit", F.lit(0)) + F.coalesce("fan", F.lit(0))
    return every.join(sums, "dataset", "left").select("dataset", rows.cast("long").alias("rows"), (F.col("p") + user_cols).cast("int").alias("cols"))
