"""Column profiles: one aggregation for all columns, then one row a column."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.ring import gram

#: Columns whose distinct values are counted exactly in one pass.
EXACT = 4


def compute(df: DataFrame, columns: Sequence[str] | None = None, approximate: bool | None = None) -> DataFrame:
    """(column, rows, nulls, distinct_values, low, high, mean, std); the last four are null for what isn't a number.

    Exact distinct counts expand each row by its columns, so above EXACT columns they are approximate unless asked for.
    """
    columns = list(columns or df.columns)
    approximate = len(columns) > EXACT if approximate is None else approximate
    types = dict(df.dtypes)
    count = F.approx_count_distinct if approximate else F.count_distinct
    stats = []
    for c in columns:
        v = F.lit(None).cast("double") if types[c].startswith(("date", "timestamp", "boolean")) else F.col(c).try_cast("double")
        stats.append(F.struct(F.lit(c).alias("column"), F.count("*").alias("rows"), F.count_if(F.col(c).isNull()).alias("nulls"), count(F.col(c)).alias("distinct_values"), F.min(v).alias("low"), F.max(v).alias("high"), F.avg(v).alias("mean"), F.stddev_samp(v).alias("std")))
    return df.agg(F.array(*stats).alias("p")).select(F.inline("p"))


def covariance(sketch: DataFrame, features: Sequence[str]) -> DataFrame:
    """(a, b, covariance) from a total sketch."""
    m, g = len(features), F.col("g")
    cells = [
        F.struct(F.lit(features[i]).alias("a"), F.lit(features[j]).alias("b"), ((g["q"][gram.at(i, j, m)] - g["s"][i] * g["s"][j] / g["c"]) / (g["c"] - 1)).alias("covariance"))
        for i, j in gram.pairs(m)
    ]
    return sketch.select(F.inline(F.array(*cells)))
