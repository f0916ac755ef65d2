"""Centre and scale: fitted from rows, or from a sketch without a scan; constant columns keep scale 1."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.ring import gram


def fit(df: DataFrame, columns: Sequence[str]) -> dict[str, tuple[float, float]]:
    row = df.agg(*[F.avg(c).alias(f"m{i}") for i, c in enumerate(columns)], *[F.stddev_samp(c).alias(f"s{i}") for i, c in enumerate(columns)]).first()
    return {c: (row[f"m{i}"] or 0.0, row[f"s{i}"] or 1.0) for i, c in enumerate(columns)}


def fit_sketch(g, features: Sequence[str]) -> dict[str, tuple[float, float]]:
    n, m, out = g["c"], len(features), {}
    for i, f in enumerate(features):
        mean = g["s"][i] / n
        var = (g["q"][gram.at(i, i, m)] - n * mean * mean) / (n - 1) if n > 1 else 0.0
        out[f] = (mean, var**0.5 if var > 1e-12 else 1.0)
    return out


def apply(df: DataFrame, fitted: dict[str, tuple[float, float]]) -> DataFrame:
    return df.withColumns({c: (F.col(c).cast("double") - F.lit(m)) / F.lit(s) for c, (m, s) in fitted.items()})
