"""A join's next total is the one it was scored by, and stand-ins for missing partners are summed once a dataset's version."""

from dataclasses import replace

from augspark import catalog as cat
from augspark.assess import vertical
from augspark.search.engine import Search
from augspark.search.request import Request
from pyspark.sql import functions as F


def test_rounds_form_no_total_twice(spark, monkeypatch):
    rows = spark.range(600).select((F.col("id") % 40).alias("k"), (F.col("id") % 7).alias("j"), (F.col("id") % 11).cast("double").alias("x"), (F.col("id") % 10).cast("int").alias("fold"))
    rows = rows.withColumn("y", F.col("x") + F.sin("k") * 9 + F.cos("j") * 3 + F.sin(F.col("k") * 3))
    c = cat.Corpus(spark)
    made = c.upload_tables([(spark.range(33).select(F.col("id").alias("k"), F.sin("id").alias("f"), F.sin(F.col("id") * 3).alias("h")), "k", ["f", "h"]), (spark.range(7).select(F.col("id").alias("j"), F.cos("id").alias("g")), "j", ["g"])])
    assert {(d.name, d.keys, d.row_count) for d in made} == {("f", ("k",), 33), ("h", ("k",), 33), ("g", ("j",), 7)}
    assert c.datasets["g"].data.columns == ["j", "g"]
    s, req = Search(c, pair_share=0.0), Request(rows, ["x"], "y", {"k": "k", "j": "j"})
    plan = s.open(req)
    some = s.candidates(req, plan)
    best, row, _ = s.pick(plan, some, dict.fromkeys(range(len(some)), 0.0), req)
    flat = lambda df: sorted((r["key_name"], r["key_value"] or "", r["fold"], round(r["g"]["c"], 9), [round(v, 6) for v in (*r["g"]["s"], *r["g"]["q"])]) for r in df.collect())
    assert flat(s.extend(replace(plan, scored=row["f"]), best).sketches) == flat(s.extend(plan, best).sketches)

    calls = {"batch": 0, "defaults": 0}
    for name in calls:
        real = getattr(vertical, name)
        monkeypatch.setattr(vertical, name, lambda *a, real=real, name=name: calls.__setitem__(name, calls[name] + 1) or real(*a))
    a = Search(c, delta=0.005, pair_share=0.0).run(req)
    assert len(a.plan) == 3 and calls == {"batch": a.rounds, "defaults": 0}
