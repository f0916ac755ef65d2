"""Predictions of a plan: its joins, then a dot product of columns, or a model that a model search found."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from augspark.catalog import Corpus
from augspark.search import materialize
from augspark.search.engine import Search, clash_free
from augspark.search.request import Answer


def linear(theta: Sequence[float], features: Sequence[str]) -> Column:
    out = F.lit(float(theta[0]))
    for w, f in zip(theta[1:], features, strict=True):
        out = out + F.lit(float(w)) * F.col(f"`{f}`").cast("double")
    return out


@dataclass
class Scorer:
    """lookups: (own key, table with one row a key, that table's key); they are joined left and imputed by ``fill``."""

    theta: Sequence[float]
    features: Sequence[str]
    lookups: Sequence[tuple[str, DataFrame, str]] = ()
    fill: dict[str, float] | None = None

    def augment(self, df: DataFrame) -> DataFrame:
        for own, right, key in self.lookups:
            mine = F.col(f"`{own}`").cast("string") if isinstance(right.schema[key].dataType, StringType) else F.col(f"`{own}`")
            df = df.join(right.withColumnRenamed(key, f"_{key}"), mine == F.col(f"_{key}"), "left").drop(f"_{key}")
        for name, value in (self.fill or {}).items():
            if name in df.columns:
                df = df.withColumn(name, F.coalesce(F.col(f"`{name}`").cast("double"), F.lit(float(value))))
        return df

    def score(self, df: DataFrame) -> DataFrame:
        """Batch or stream: a stream joins the lookups as static tables."""
        return self.augment(df).withColumn("prediction", linear(self.theta, self.features))

    score_stream = score


def of_plan(search: Search, answer: Answer) -> Scorer:
    """The scorer of a search's linear model: it looks up the features that the plan's joins add, in the model's units."""
    corpus, lookups = search.corpus, []
    for step in answer.plan:
        if step.kind == "vertical":
            d = corpus.datasets[step.dataset]
            partner, _ = search.lookup(d, step.via)
            lookups.append((step.key, partner.select("key_value", *[F.col("g.s")[i].alias(n) for i, n in enumerate(clash_free(d.name, d.features))]), "key_value"))
            for other in d.carried.get(step.via, ()):
                lookups.append((step.key, d.fixed_by(step.via, other).toDF("key_value", f"{d.name}__{other}"), "key_value"))
    return Scorer(answer.theta, answer.feature_names, lookups, answer.fill)


@dataclass
class ModelScorer:
    """A model search's model behind the plan's joins; unions add training rows only."""

    corpus: Corpus
    answer: Answer
    model: object

    def score(self, df: DataFrame) -> DataFrame:
        return self.model.predict(materialize.apply(self.answer.plan, df, self.corpus, self.answer.keys, unions=False))


@dataclass
class RemoteScorer:
    """A service's own prediction call and what it charges; the user pays for inference."""

    call: Callable[[DataFrame], DataFrame]
    price_per_1000: float = 0.0

    def score(self, df: DataFrame) -> tuple[DataFrame, float]:
        out = self.call(df)
        return out, df.count() / 1000 * self.price_per_1000
