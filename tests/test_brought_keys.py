"""Keys that a join brings are summed from sketches, so sums by the other keys read rows that are not joined with them."""

from augspark import catalog as cat
from augspark.search.engine import Search
from augspark.search.request import Request
from pyspark.sql import functions as F


def test_sums_by_other_keys_lack_brought_ones(spark, monkeypatch):
    rows = spark.range(600).select((F.col("id") % 40).alias("k"), (F.col("id") % 7).alias("j"), (F.col("id") % 11).cast("double").alias("x"), (F.col("id") % 10).cast("int").alias("fold"))
    rows = rows.withColumn("y", F.col("x") + F.sin("k") * 9 + F.cos("j") * 3 + F.sin(F.col("k") % 5))
    c = cat.Corpus(spark)
    c.upload(spark.range(40).select(F.col("id").alias("k"), (F.col("id") % 5).alias("o"), F.sin("id").alias("f")), "by_k", "RAW", ["k", "o"], ["f"])
    for key, n in (("j", 7), ("o", 5)):
        c.upload(spark.range(n).select(F.col("id").alias(key), F.cos("id").alias("f")), f"by_{key}", "RAW", [key], ["f"])
    s, read = Search(c, pair_share=0.0), []
    rescanned = Search._rescanned
    monkeypatch.setattr(Search, "_rescanned", lambda self, plan, *a: read.append(plan.rows.columns) or rescanned(self, plan, *a))
    req = Request(rows, ["x"], "y", {"k": "k", "j": "j"})
    plan = s.open(req)
    (first,) = [x for x in s.candidates(req, plan) if x.dataset.name == "by_k"]
    grown = s.extend(plan, first)
    assert read and not any("by_k__o" in columns for columns in read)
    assert "by_k__o" in grown.rows.columns and "by_k__o" in grown.keys
    by = lambda df: sorted((r["key_value"], r["fold"], round(r["g"]["c"], 9), [round(x, 6) for x in r["g"]["s"]]) for r in df.collect())
    for k in ("j", "by_k__o"):
        assert by(grown.by(k)) == by(rescanned(s, grown, [k], False))
