"""The model on all useful candidates takes as many features as there are candidates: thousands of pair sums."""

import time

import numpy as np
from augspark import workloads
from augspark.assess import solve
from augspark.ring import gram
from augspark.sketch import build
from pyspark.sql import functions as F


def test_matrix_of_arrays_is_that_of_generated_sums(spark):
    df = spark.range(500).select(F.sin("id").alias("a"), (F.col("id") % 7).alias("b.c"), F.cos("id").alias("y"))
    g = build.total(df.withColumnRenamed("b.c", "b"), ["a", "b", "y"]).first()["g"]
    assert np.allclose(gram.wide_matrix(df, ["a", "b.c", "y"]), solve.matrix(g["c"], g["s"], g["q"]))
    assert not gram.wide_matrix(df.limit(0), ["a", "y"]).any()


def test_ninety_joins(spark):
    keys = [f"j{i}" for i in range(1, 11)]
    rows = spark.range(3000).select(*[F.pmod(F.xxhash64("id", F.lit(k)), F.lit(20)).cast("int").alias(k) for k in keys], F.sin("id").alias("f1"))
    cell = lambda i, c: F.sin(F.col(f"j{i}") * 7 + c * 3)
    rows = rows.withColumn("y", F.col("f1") + sum((cell(i, 1) for i in range(2, 11)), F.lit(0.0))).cache()
    joins = {i: spark.range(20).select(F.col("id").cast("int").alias(f"j{i}")).select(f"j{i}", *[cell(i, c).alias(f"a{i}_{c}") for c in range(10)]) for i in range(2, 11)}
    chosen = {("join", i, c) for i in joins for c in range(10)}
    began = time.monotonic()
    assert workloads.omniscient_test(rows, rows.limit(0), joins, chosen, rows, keys) > 0.999
    assert time.monotonic() - began < 60
