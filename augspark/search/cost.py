"""Training time from data shape: a forest over timed runs on random tables, made to over-predict."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.ml.feature import VectorAssembler
from pyspark.ml.regression import LinearRegression, RandomForestRegressor
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TRAININGS = 5
SHAPE = ["log_rows", "cols", "log_cells"]


def shaped(df: DataFrame) -> DataFrame:
    return df.withColumns({"log_rows": F.log1p("rows"), "log_cells": F.log1p(F.col("rows") * F.col("cols"))})


def calibrate(spark: SparkSession, grid: Sequence[tuple[int, int]], train: Callable[[DataFrame], object] | None = None, family: str = "linear") -> DataFrame:
    """(family, rows, cols, seconds) of one training on random data of each shape."""
    out = []
    for rows, cols in grid:
        x = spark.range(rows).select(*[F.rand(seed=i).alias(f"f{i}") for i in range(cols)], F.rand(seed=99).alias("y"))
        data = VectorAssembler(inputCols=[f"f{i}" for i in range(cols)], outputCol="x").transform(x).select("x", "y")
        began = time.perf_counter()
        (train or (lambda d: LinearRegression(featuresCol="x", labelCol="y", solver="normal").fit(d)))(data)
        out.append((family, rows, cols, time.perf_counter() - began))
    return spark.createDataFrame(out, "family string, rows long, cols int, seconds double")


def calibrate_on(tables: Sequence[tuple[DataFrame, Sequence[str], str]], family: str = "linear") -> DataFrame:
    """(family, rows, cols, seconds) of one training on every row of each (table, features, target)."""
    out = []
    for df, features, target in tables:
        x = df.select(*[F.col(c).cast("double").alias(c) for c in features], F.col(target).cast("double").alias("y"))
        data = VectorAssembler(inputCols=list(features), outputCol="x", handleInvalid="skip").transform(x).select("x", "y")
        began = time.perf_counter()
        model = LinearRegression(featuresCol="x", labelCol="y", solver="normal").fit(data)
        out.append((family, int(model.summary.numInstances), len(features), time.perf_counter() - began))
    return tables[0][0].sparkSession.createDataFrame(out, "family string, rows long, cols int, seconds double")


class CostModel:
    """Predicted seconds of the trainings that a model search runs on a table of a shape."""

    def __init__(self, timings: DataFrame, trainings: int = TRAININGS, safety: float = 1.2, trees: int = 20) -> None:
        self.spark, self.trainings, self.safety = timings.sparkSession, trainings, safety
        self.assemble = VectorAssembler(inputCols=SHAPE, outputCol="x")
        data = self.assemble.transform(shaped(timings))
        self.model = RandomForestRegressor(featuresCol="x", labelCol="seconds", numTrees=trees, maxDepth=6, seed=1).fit(data)
        self.over = self.model.transform(data).agg(F.max(F.col("seconds") / F.greatest("prediction", F.lit(1e-6)))).first()[0]

    @property
    def factor(self) -> float:
        """What a predicted training is multiplied by: the number of trainings, and a margin that covers every timing."""
        return self.trainings * self.safety * max(1.0, self.over or 1.0)

    def predict(self, shapes: DataFrame) -> DataFrame:
        """(rows, cols, ...) with predicted_s."""
        out = self.model.transform(self.assemble.transform(shaped(shapes)))
        return out.withColumn("predicted_s", F.col("prediction") * self.factor).drop("x", "prediction", *[c for c in SHAPE if c != "cols"])

    def admits(self, rows: int, cols: int, left_s: float) -> bool:
        one = self.spark.createDataFrame([(rows, cols)], "rows long, cols int")
        return self.predict(one).first()["predicted_s"] <= left_s


def budget_split(budget_s: float, policy: str = "cost", fixed_search_s: float = 300.0) -> tuple[float, float]:
    """(search, model) seconds: a fixed allowance where the final service can't be predicted, else all until it must stop."""
    search = min(budget_s, fixed_search_s) if policy == "fixed" else budget_s
    return search, budget_s - search if policy == "fixed" else budget_s
