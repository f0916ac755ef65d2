"""Accuracy, cost and summary measures over rows, sketches and run logs."""

from __future__ import annotations

import time
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

HOSTED_PRICE, SMALL_VM_PER_10_MIN = 21.252, 0.13


def r2(df: DataFrame, y: str, yhat: Column | str, by: Sequence[str] = ()) -> DataFrame:
    e = (F.col(y).cast("double") - (F.col(yhat) if isinstance(yhat, str) else yhat)) ** 2
    v = F.col(y).cast("double")
    return df.groupBy(*by).agg((1 - F.sum(e) / (F.var_pop(v) * F.count(v))).alias("r2"))


def sse(df: DataFrame, y: str, yhat: Column) -> DataFrame:
    return df.agg(F.sum((F.col(y).cast("double") - yhat) ** 2).alias("sse"))


def accuracy(df: DataFrame, y: str, yhat: Column, by: Sequence[str] = ()) -> DataFrame:
    return df.groupBy(*by).agg(F.avg((F.col(y) == yhat).cast("double")).alias("accuracy"))


def cost(seconds: Column, per_hour: float | Column) -> Column:
    return seconds * per_hour / 3600


def summarise(runs: DataFrame, by: Sequence[str], score: str = "score") -> DataFrame:
    return runs.groupBy(*by).agg(F.min(score).alias("low"), F.percentile(score, F.lit(0.5)).alias("median"), F.max(score).alias("high"), F.count("*").alias("runs"))


def cdf(scores: DataFrame, score: str, by: Sequence[str]) -> DataFrame:
    return scores.withColumn("share", F.cume_dist().over(Window.partitionBy(*by).orderBy(score)))


def heatmap(pairs: DataFrame, before: str, after: str, bins: int = 10) -> DataFrame:
    cell = lambda c: F.least(F.greatest(F.width_bucket(F.col(c), F.lit(0.0), F.lit(1.0), F.lit(bins)), F.lit(1)), F.lit(bins)).cast("int")
    return pairs.groupBy(cell(before).alias("before_bin"), cell(after).alias("after_bin")).agg(F.count("*").alias("requests"))


def anytime(trace: DataFrame, by: Sequence[str], at: str = "seconds", score: str = "score") -> DataFrame:
    w = Window.partitionBy(*by).orderBy(at).rowsBetween(Window.unboundedPreceding, 0)
    return trace.withColumn("best_score", F.max(score).over(w))


def cost_to_reach(trace: DataFrame, goal: Column, by: Sequence[str]) -> DataFrame:
    return trace.groupBy(*by).agg(F.min(F.when(F.col("score") >= goal, F.col("cost"))).alias("cost_to_reach"))


def query_count(requests: int | Column, steps: int, candidates: int | Column) -> int | Column:
    return requests * steps * candidates


class Timer:
    def __enter__(self) -> Timer:
        self.began = time.perf_counter()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.perf_counter() - self.began
