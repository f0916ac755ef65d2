"""What a request gets back by its return labels, and a plan's report for people."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from augspark.catalog import Corpus
from augspark.search.request import Answer, Request, Step


@dataclass
class Response:
    """RAW in the return labels gives plan and datasets, MD the model, API the scorer; the rest is empty.

    model is (theta, features) of the linear proxy, or a model search's model.
    """

    plan: list[Step] = field(default_factory=list)
    datasets: dict[str, DataFrame | None] = field(default_factory=dict)
    model: object = None
    api: object = None
    answer: Answer | None = None
    search_s: float = 0.0
    model_s: float = 0.0
    score: float | None = None


def build(req: Request, answer: Answer, corpus: Corpus, scorer=None, model=None) -> Response:
    out = Response(answer=answer, search_s=answer.seconds)
    if "RAW" in req.returns:
        out.plan, out.datasets = list(answer.plan), {s.dataset: corpus.datasets[s.dataset].data for s in answer.plan}
    if "MD" in req.returns:
        out.model = model if model is not None else (answer.theta, answer.feature_names)
    if "API" in req.returns:
        out.api = scorer
    return out


def report(spark: SparkSession, answer: Answer, corpus: Corpus) -> DataFrame:
    rows = [(i, s.kind, s.dataset, s.key, round(s.gain, 4), round(s.cv_r2, 4), ("RAW", "MD", "API")[corpus.datasets[s.dataset].label]) for i, s in enumerate(answer.plan, 1)]
    return spark.createDataFrame(rows, "step int, kind string, dataset string, key string, gain double, cv_r2 double, label string")
