"""Sketches of an upload are the same by passes of their own, and a store leaves the session's settings as they were."""

from augspark.ring import gram
from augspark.sketch import build, store
from pyspark.sql import functions as F


def test_apart_equals_one_pass(spark):
    rows = spark.range(90).select(F.when(F.col("id") % 9 > 0, F.col("id") % 7).alias("a"), F.when(F.col("id") % 8 > 0, (F.col("id") % 5).cast("string")).alias("b"), (F.col("id") % 11).cast("double").alias("x"))
    flat = lambda df: sorted((r["key_name"], r["key_value"] or "", r["g"]["c"], *r["g"]["s"], *r["g"]["q"]) for r in df.collect())
    made = [build.keyed(rows, [gram.number("x")], [["a"], ["b"], ["a", "b"]], apart=apart) for apart in (False, True)]
    assert flat(made[0]) == flat(made[1])
    assert made[0].schema == made[1].schema
    assert "Expand" not in made[1]._jdf.queryExecution().optimizedPlan().toString()
    held, was = store.SketchStore(spark), spark.conf.get(store.WRITERS)
    held.append(made[1].select(F.lit("s").alias("sid"), "key_name", "key_value", "g"))
    assert spark.conf.get(store.WRITERS) == was
    assert flat(held.read_keys([build.ALL, "a", "b", "a&b"], ["s"])) == flat(made[0])
