"""The ring of counts and sums: annotate rows, add inside groups, multiply on join."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ANNOTATION = "a"


def annotate(df: DataFrame, value: Column | int = 1) -> DataFrame:
    return df.withColumn(ANNOTATION, value if isinstance(value, Column) else F.lit(value).cast("long"))


def gamma(df: DataFrame, *keys: str) -> DataFrame:
    """Sum of annotations per group, aggregated before the shuffle."""
    return df.groupBy(*keys).agg(F.sum(ANNOTATION).alias(ANNOTATION))


def join(a: DataFrame, b: DataFrame, on: list[str], how: str = "inner", missing: Column | int = 1) -> DataFrame:
    """Annotations multiply; a left join gives unmatched rows the annotation ``missing`` on the right."""
    right = b.withColumnRenamed(ANNOTATION, "_right")
    missing = missing if isinstance(missing, Column) else F.lit(missing)
    both = a.join(right, on, how)
    product = F.col(ANNOTATION) * (F.coalesce("_right", missing) if how == "left" else F.col("_right"))
    return both.withColumn(ANNOTATION, product).drop("_right")
