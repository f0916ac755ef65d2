"""A key with nearly as many values in folds as there are rows is not summed: its sketches are the rows, and searches end alike."""

from augspark import catalog as cat
from augspark.search import engine
from augspark.search.engine import Search
from augspark.search.request import Request
from pyspark.sql import functions as F


def corpus_and_request(spark):
    rows = spark.range(600).select(F.col("id").alias("near"), (F.col("id") % 7).alias("j"), (F.col("id") % 11).cast("double").alias("x"), (F.col("id") % 10).cast("int").alias("fold"))
    rows = rows.withColumn("y", F.col("x") + F.sin("near") * 9 + F.cos("j") * 5)
    c = cat.Corpus(spark)
    for key, n, f in (("near", 600, F.sin("id")), ("j", 7, F.cos("id"))):
        c.upload(spark.range(n).select(F.col("id").alias(key), f.alias("f")), f"by_{key}", "RAW", [key], ["f"])
    return c, Request(rows, ["x"], "y", {"near": "near", "j": "j"})


def outcome(a):
    return [(s.dataset, round(s.cv_r2, 9)) for s in a.plan], round(a.base_r2, 9)


def test_rows_stand_for_sketches(spark, monkeypatch):
    c, req = corpus_and_request(spark)
    plan = Search(c).open(req)
    assert plan.loose == ("near",)
    written = [f for f in plan.sketches.inputFiles() if "/round-" in f]
    assert {r["key_name"] for r in spark.read.parquet(*written).select("key_name").distinct().collect()} == {"*", "j"}
    got = outcome(Search(c).run(req))
    assert [n for n, _ in got[0]] == ["by_near", "by_j"] and got[0][-1][1] > 0.999
    monkeypatch.setattr(engine, "LOOSE", 2.0)
    assert Search(c).open(req).loose == () and outcome(Search(c).run(req)) == got


def test_online_search_writes_no_key_sketch(spark):
    c, req = corpus_and_request(spark)
    s = Search(c, online=True)
    plan = s.open(req)
    assert {r["key_name"] for r in plan.sketches.select("key_name").distinct().collect()} == {"*"}
    assert outcome(s.run(req)) == outcome(Search(c).run(req))
