"""SQL functions over sketches, and a table function that lists a plan."""

from __future__ import annotations

import json

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

ELEMENT = "STRUCT<c: DOUBLE, s: ARRAY<DOUBLE>, q: ARRAY<DOUBLE>>"


def gram_agg(*features: Column) -> Column:
    """Count, sums and pair sums of a group in one array, as an aggregate function; see ``element_of``.

    ``ring.gram.gamma`` does the same in generated code, with partial sums before the shuffle: this one is for convenience.
    """

    @F.pandas_udf("array<double>")
    def total(*columns: pd.Series) -> list[float]:
        x = np.column_stack([c.to_numpy(float) for c in columns])
        return [float(len(x)), *x.sum(axis=0).tolist(), *(x.T @ x)[np.triu_indices(x.shape[1])].tolist()]

    return total(*[f.cast("double") for f in features])


def element_of(flat: Column, m: int) -> Column:
    """The element of m features from the array of ``gram_agg``."""
    return F.struct(flat[0].alias("c"), F.slice(flat, 2, m).alias("s"), F.slice(flat, m + 2, m * (m + 1) // 2).alias("q"))


def register(spark: SparkSession) -> None:
    """gram_mean, gram_variance, gram_reweight, gram_slope and gram_r2 (feature 0 explains feature 1), and augmentation_plan."""
    one = {
        "gram_mean(g {E}, i INT) RETURNS DOUBLE": "g.s[i] / g.c",
        "gram_reweight(g {E}) RETURNS {E}": "named_struct('c', 1D, 's', transform(g.s, x -> x / g.c), 'q', transform(g.q, x -> x / g.c))",
        "gram_slope(g {E}) RETURNS DOUBLE": "(g.q[1] - g.s[0] * g.s[1] / g.c) / (g.q[0] - g.s[0] * g.s[0] / g.c)",
        "gram_r2(g {E}) RETURNS DOUBLE": "pow(g.q[1] - g.s[0] * g.s[1] / g.c, 2) / ((g.q[0] - g.s[0] * g.s[0] / g.c) * (g.q[2] - g.s[1] * g.s[1] / g.c))",
        "gram_sse(g {E}, a DOUBLE, b DOUBLE) RETURNS DOUBLE": "g.q[2] - 2 * a * g.s[1] - 2 * b * g.q[1] + a * a * g.c + 2 * a * b * g.s[0] + b * b * g.q[0]",
    }
    for head, body in one.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head.replace('{E}', ELEMENT)} RETURN {body}")

    @F.udtf(returnType="step int, kind string, dataset string, key string, score double")
    class AugmentationPlan:
        def eval(self, plan_json: str):
            for i, s in enumerate(json.loads(plan_json or "[]"), 1):
                yield i, s["kind"], s["dataset"], s.get("key"), float(s.get("cv_r2", 0.0))

    spark.udtf.register("augmentation_plan", AugmentationPlan)
