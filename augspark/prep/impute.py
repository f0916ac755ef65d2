"""Missing values: constants fitted in one aggregation, applied as literals."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def fit(df: DataFrame, columns: Sequence[str], strategy: str = "mean", constant: float = 0.0) -> dict[str, float]:
    how = {
        "mean": lambda c: F.avg(c),
        "median": lambda c: F.percentile(F.col(c).cast("double"), F.lit(0.5)),
        "mode": lambda c: F.mode(c, deterministic=True),
        "constant": lambda c: F.max(F.lit(constant)),
    }[strategy]
    row = df.agg(*[how(c).cast("double").alias(c) for c in columns]).first()
    return {c: row[c] if row[c] is not None else constant for c in columns}


def apply(df: DataFrame, fitted: dict[str, float]) -> DataFrame:
    return df.withColumns({c: F.coalesce(F.col(c).cast("double"), F.lit(float(v))) for c, v in fitted.items()})
