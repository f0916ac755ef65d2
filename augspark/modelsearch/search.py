"""Model search over pyspark.ml families under a time budget, with an ensemble that grows while time is left.

Rows are split by hash before anything is fitted. Every family is tried in a few settings, cheap ones first; a watchdog
ends the setting that runs when the budget does. The ensemble is chosen from one sketch of the held rows' predictions.
"""

from __future__ import annotations

import time
from collections.abc import Iterator, Sequence
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.ml import Pipeline
from pyspark.ml.classification import LinearSVC, MultilayerPerceptronClassifier
from pyspark.ml.clustering import KMeans
from pyspark.ml.feature import Imputer, StandardScaler, VectorAssembler
from pyspark.ml.functions import vector_to_array
from pyspark.ml.regression import DecisionTreeRegressor, FMRegressor, GBTRegressor, GeneralizedLinearRegression, LinearRegression, RandomForestRegressor
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark import measures
from augspark.assess.solve import matrix
from augspark.cluster import materialize
from augspark.ring import gram
from augspark.search.deadline import Deadline

#: Rows of the nearest-neighbour family's reference sample, the smallest hashes.
NEIGHBOUR_ROWS = 2_000


class NearestModel:
    """Mean target of the k nearest reference rows, by brute force in vectorised batches."""

    def __init__(self, x: np.ndarray, y: np.ndarray, k: int, output: str = "prediction") -> None:
        self.x, self.y, self.k, self.output = x, y, min(k, len(y)), output

    def setPredictionCol(self, name: str) -> NearestModel:
        return NearestModel(self.x, self.y, self.k, name)

    def transform(self, df: DataFrame) -> DataFrame:
        x, y, k = self.x, self.y, self.k

        @F.pandas_udf("double")
        def near(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
            for batch in batches:
                q = np.stack(batch.to_numpy()) if len(batch) else np.zeros((0, x.shape[1]))
                far = (x**2).sum(axis=1)[None, :] - 2 * q @ x.T
                yield pd.Series(y[np.argpartition(far, k - 1, axis=1)[:, :k]].mean(axis=1), dtype="float64")

        return df.withColumn(self.output, near(vector_to_array("x")))


class Nearest:
    """The nearest-neighbour family over a bounded hash sample of the training rows."""

    def __init__(self, k: int, rows: int = NEIGHBOUR_ROWS) -> None:
        self.k, self.rows = k, rows

    def fit(self, df: DataFrame) -> NearestModel:
        got = df.select(vector_to_array("x").alias("x"), "y").orderBy(F.xxhash64(F.col("x"), F.col("y"))).limit(self.rows).toPandas()
        return NearestModel(np.stack(got["x"].to_numpy()), got["y"].to_numpy(float), self.k)


def families(kind: str, task: str, inputs: int) -> list[tuple[str, object]]:
    """(name, estimator) of every family and setting, the cheap ones first."""
    both = {"featuresCol": "x", "labelCol": "y"}
    trees = [
        ("tree", DecisionTreeRegressor(**both, maxDepth=5, seed=1)),
        ("forest", RandomForestRegressor(**both, numTrees=20, maxDepth=6, seed=1)),
        ("boosting", GBTRegressor(**both, maxIter=10, maxDepth=4, seed=1)),
        ("tree_deep", DecisionTreeRegressor(**both, maxDepth=10, minInstancesPerNode=5, seed=1)),
        ("forest_deep", RandomForestRegressor(**both, numTrees=40, maxDepth=10, minInstancesPerNode=3, seed=1)),
        ("boosting_long", GBTRegressor(**both, maxIter=40, maxDepth=5, stepSize=0.2, seed=1)),
    ]
    if kind == "trees":
        return trees
    broad = [("linear", LinearRegression(**both)), ("ridge", LinearRegression(**both, regParam=0.1)), *trees[:1], ("neighbours", Nearest(5)), *trees[1:3], ("glm", GeneralizedLinearRegression(**both))]
    if task == "class":
        broad += [
            ("svm", LinearSVC(**both, maxIter=20)),
            ("svm_tight", LinearSVC(**both, maxIter=20, regParam=0.1)),
            ("perceptron", MultilayerPerceptronClassifier(**both, layers=[inputs, 8, 2], maxIter=30, seed=1)),
            ("perceptron_wide", MultilayerPerceptronClassifier(**both, layers=[inputs, 24, 2], maxIter=60, seed=1)),
        ]
    return [*broad, ("neighbours_many", Nearest(15)), ("fm", FMRegressor(**both, factorSize=2, stepSize=0.05, maxIter=30, seed=1)), *trees[3:]]


@dataclass
class Ensemble:
    """A preparation and weighted models; a class is the mean's rounding at one half."""

    prepared: object
    models: list[tuple[str, object, float]]
    features: Sequence[str]
    task: str

    def predict(self, df: DataFrame) -> DataFrame:
        """df with prediction; its own columns stay, and columns of these names are replaced."""
        whole = df.withColumn("_row", F.struct(*[F.col(f"`{c}`") for c in df.columns])) if df.columns else df
        numbers = whole.select("_row", *[F.col(f"`{f}`").cast("double").alias(f"f{i}") for i, f in enumerate(self.features)])
        out = self.prepared.transform(numbers).select("_row", "x")
        for i, (_, model, _) in enumerate(self.models):
            out = predicted(model, out, f"p{i}")
        mean = sum((F.col(f"p{i}") * w for i, (_, _, w) in enumerate(self.models)), F.lit(0.0))
        result = (mean >= 0.5).cast("double") if self.task == "class" else mean
        return out.select(*[F.col("_row")[c].alias(c) for c in df.columns if c != "prediction"], result.alias("prediction"))


def predicted(model, df: DataFrame, name: str) -> DataFrame:
    """df with a model's prediction and none of its other outputs."""
    return model.setPredictionCol(name).transform(df).select(*df.columns, name)


@dataclass
class Found:
    models: list[tuple[str, object, float]] = field(default_factory=list)
    trace: list[tuple[float, str, float]] = field(default_factory=list)
    seconds: float = 0.0
    model: Ensemble | None = None
    score: float = float("nan")

    @property
    def best(self) -> tuple[str, object, float]:
        return max(self.models, key=lambda m: m[2])


def weights(c: float, s, q, n: int, rounds: int = 10) -> np.ndarray:
    """Weights of n models by greedy forward selection with repeats, from the sketch of their predictions and the target."""
    g, counts = matrix(c, s, q)[1:, 1:], np.zeros(n)
    best, kept = np.inf, counts
    for r in range(1, rounds + 1):
        trials = []
        for i in range(n):
            w = counts.copy()
            w[i] += 1
            v = np.append(w / r, -1.0)
            trials.append(v @ g @ v)
        i = int(np.argmin(trials))
        counts[i] += 1
        if trials[i] < best * (1 - 1e-9):
            best, kept = trials[i], counts / r
    return kept


class ModelSearch:
    """Fits families until the budget ends (at least one), scored on a held-out share of rows."""

    def __init__(self, kind: str = "broad", budget_s: float = 60.0, task: str = "regression", enforce: bool = True) -> None:
        self.kind, self.budget_s, self.task, self.enforce = kind, budget_s, task, enforce

    def run(self, df: DataFrame, features: Sequence[str], target: str, held: float = 0.2) -> Found:
        began, out = time.monotonic(), Found()
        numbers = df.select(*[F.col(f"`{f}`").cast("double").alias(f"f{i}") for i, f in enumerate(features)], F.col(f"`{target}`").cast("double").alias("y")).filter("y is not null")
        share = F.pmod(F.xxhash64(*numbers.columns), F.lit(1000)) < int(1000 * held)
        names = [f"f{i}" for i in range(len(features))]
        prepared = Pipeline(stages=[Imputer(inputCols=names, outputCols=[f"i{n}" for n in names]), VectorAssembler(inputCols=[f"i{n}" for n in names], outputCol="raw"), StandardScaler(inputCol="raw", outputCol="x", withMean=True)]).fit(numbers.filter(~share))
        ready = materialize(prepared.transform(numbers).select("x", "y", share.alias("held")), "model-search")
        train, test = ready.filter("not held").select("x", "y"), ready.filter("held").select("x", "y")
        scored = test
        for name, estimator in families(self.kind, self.task, len(features)):
            left = self.budget_s - (time.monotonic() - began)
            if out.models and self.enforce and left <= 0:
                break
            watch = Deadline(df.sparkSession, left if self.enforce and out.models else 1e6)
            try:
                with watch:
                    model = estimator.fit(train)
                    got = self.measure(predicted(model, test, "prediction"))
            except Exception:
                if not watch.expired:
                    raise
                break
            out.models.append((name, model, got))
            out.trace.append((time.monotonic() - began, name, got))
            scored = predicted(model, scored, f"p{len(out.models) - 1}")
        self.blend(out, scored, prepared, features, began)
        out.seconds = time.monotonic() - began
        return out

    def blend(self, out: Found, scored: DataFrame, prepared, features: Sequence[str], began: float) -> None:
        """The ensemble, unless a single model measures better."""
        names = [f"p{i}" for i in range(len(out.models))]
        g = gram.gamma(scored, [*names, "y"]).first()["g"]
        w = weights(g["c"], g["s"], g["q"], len(names))
        mean = sum((F.col(n) * float(x) for n, x in zip(names, w, strict=True)), F.lit(0.0))
        got = self.measure(scored.withColumn("prediction", mean))
        single = int(np.nanargmax([m[2] for m in out.models]))
        if not got >= out.models[single][2]:
            w, got = np.eye(len(names))[single], out.models[single][2]
        out.trace.append((time.monotonic() - began, "ensemble", got))
        out.score = got
        out.model = Ensemble(prepared, [(n, m, float(x)) for (n, m, _), x in zip(out.models, w, strict=True) if x > 0], features, self.task)

    def measure(self, scored: DataFrame) -> float:
        if self.task == "class":
            got = measures.accuracy(scored, "y", (F.col("prediction") >= 0.5).cast("double")).first()["accuracy"]
        else:
            got = measures.r2(scored, "y", "prediction").first()["r2"]
        return float("nan") if got is None else got


class HostedSimulator(ModelSearch):
    """A hosted service: runs to convergence whatever the budget, and bills at least a minimum of hours."""

    def __init__(self, min_s: float = 3600.0, price: float = measures.HOSTED_PRICE, task: str = "regression") -> None:
        super().__init__("broad", 0.0, task, enforce=False)
        self.min_s, self.price = min_s, price

    def bill(self, seconds: float | Column) -> float | Column:
        """Dollars of a run's seconds, or of a column of them."""
        if isinstance(seconds, Column):
            return F.greatest(seconds, F.lit(self.min_s)) * self.price / 3600
        return max(seconds, self.min_s) * self.price / 3600


def cluster_baseline(df: DataFrame, features: Sequence[str], k: int = 3) -> float:
    """Training cost of k-means over a materialised table, one of the learners that work on rows only."""
    data = VectorAssembler(inputCols=list(features), outputCol="features").transform(df.select(*[F.col(f).cast("double") for f in features]))
    return float(KMeans(k=k, seed=1).fit(data).summary.trainingCost)
