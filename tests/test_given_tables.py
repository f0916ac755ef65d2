"""Queries of rules, costs and the plan cache work on rows of the given tables, all of them."""

import pytest
from pyspark.sql import functions as F

from augspark import catalog as cat
from augspark.queries import registry


@pytest.mark.parametrize("name", ["plan_table_function", "hosted_cost", "query_count_model", "release_filter", "release_kind_rule", "cost_model_predict", "cache_lru_trace"])
def test_reads_a_given_table(spark, sf_dir, name):
    assert f"{sf_dir}/" in " ".join(registry.queries()[name](spark, sf_dir).inputFiles())


def test_calibration_trains_on_all_rows(spark, sf_dir):
    rows = {(r["rows"], r["cols"]) for r in registry.queries()["cost_calibration"](spark, sf_dir).collect()}
    count = lambda t: spark.read.parquet(f"{sf_dir}/{t}.parquet").count()
    assert rows == {(count("orders"), 2), (count("lineitem"), 4)}


def test_joins_allowed_is_the_rule(spark):
    sets = [["RAW"], ["MD"], ["API"], ["RAW", "MD"], ["MD", "API"], ["RAW", "API"], ["RAW", "MD", "API"]]
    df = spark.createDataFrame([(s, f) for s in sets for f in (False, True)], "returns array<string>, f boolean")
    for r in df.withColumn("joins", cat.joins_allowed(F.col("returns"), F.col("f"))).collect():
        assert r["joins"] == ("vertical" in cat.allowed_kinds(r["returns"], r["f"]))
