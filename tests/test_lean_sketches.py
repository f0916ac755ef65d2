"""A search keeps no more by key than rounds read: its scratch files and shuffles grow with features, not with their pairs."""

from augspark import catalog as cat
from augspark.search.engine import Search
from augspark.search.request import Request
from pyspark.sql import functions as F


def corpus_and_request(spark, **how):
    rows = spark.range(400).select((F.col("id") % 20).alias("k"), (F.col("id") % 7).alias("j"), (F.col("id") % 11).cast("double").alias("x"), (F.col("id") % 10).cast("int").alias("fold"))
    rows = rows.withColumn("y", F.col("x") + F.sin("k") * 9 + F.cos("j"))
    c = cat.Corpus(spark)
    for key, n in (("k", 20), ("j", 7)):
        c.upload(spark.range(n).select(F.col("id").alias(key), F.sin("id").alias("f")), f"by_{key}", "RAW", [key], ["f"])
    return c, Request(rows, ["x"], "y", {"k": "k", "j": "j"}, **how)


def test_keys_hold_no_pair_sums(spark):
    c, req = corpus_and_request(spark)
    s = Search(c)
    plan = s.open(req)
    for n in (2, 3):
        widths = {(r["key_name"] == "*", r["n"]) for r in plan.sketches.select("key_name", F.size("g.q").alias("n")).distinct().collect()}
        assert widths == {(True, n * (n + 1) // 2), (False, 0)}
        plan = s.extend(plan, s.candidates(req, plan)[0])


def test_only_keys_with_candidates_are_kept(spark):
    c, req = corpus_and_request(spark)
    s = Search(c)
    plan = s.open(req)
    first = next(x for x in s.candidates(req, plan) if x.dataset.name == "by_k")
    ahead = s.ahead(req, plan, first, None)
    assert ahead == {"j"}
    after = s.extend(plan, first, None, ahead)
    assert {r["key_name"] for r in after.sketches.select("key_name").distinct().collect()} == {"*", "j"}
