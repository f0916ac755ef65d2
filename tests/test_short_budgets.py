"""Budgets that end before the first score."""

from augspark import catalog as cat
from augspark.search.engine import Search
from augspark.search.request import Request
from augspark.serve.scorer import of_plan
from augspark.serve.service import Service
from pyspark.sql import functions as F


def rows_of(spark):
    rows = spark.range(300).select((F.col("id") % 20).alias("k"), (F.col("id") % 11).cast("double").alias("x"), (F.col("id") % 10).cast("int").alias("fold"))
    return rows.withColumn("y", F.col("x") * 2 + F.sin("k"))


def test_model_search_without_a_score(spark):
    """The model search has the request's own features where the search had no time for any score."""
    r = Service(cat.Corpus(spark), final="trees").answer(Request(rows_of(spark), ["x"], "y", {"k": "k"}, budget_s=0.0, model="any", returns=("RAW", "MD")))
    assert r.plan == [] and r.model.features == ["x"] and r.score > 0.8


def test_linear_answer_without_time(spark):
    """A linear answer has its first model whatever the budget."""
    a = Search(cat.Corpus(spark)).run(Request(rows_of(spark), ["x"], "y", {"k": "k"}, budget_s=0.0))
    assert a.stopped == "budget" and len(a.theta) == 2 and a.cv_r2 > 0.9 and len(a.trace) == 1
    assert of_plan(Search(cat.Corpus(spark)), a).score(rows_of(spark)).filter("prediction is null").count() == 0
