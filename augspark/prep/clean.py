"""Simple cleaning: trim strings, coerce numeric text, drop columns without information and exact duplicates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType


def trim_and_coerce(df: DataFrame, numeric_share: float = 1.0) -> DataFrame:
    """Strings are trimmed (blank to null); a column whose values all read as numbers becomes double."""
    text = [f.name for f in df.schema.fields if isinstance(f.dataType, StringType)]
    df = df.withColumns({c: F.nullif(F.trim(c), F.lit("")) for c in text})
    if not text:
        return df
    row = df.agg(*[F.count(c).alias(f"n{i}") for i, c in enumerate(text)], *[F.count(F.col(c).try_cast("double")).alias(f"d{i}") for i, c in enumerate(text)]).first()
    numbers = [c for i, c in enumerate(text) if row[f"n{i}"] and row[f"d{i}"] >= numeric_share * row[f"n{i}"]]
    return df.withColumns({c: F.col(c).try_cast("double") for c in numbers})


def informative(df: DataFrame) -> list[str]:
    """Columns with at least two distinct values."""
    row = df.agg(*[(F.min(c) != F.max(c)).alias(f"x{i}") for i, c in enumerate(df.columns)]).first()
    return [c for i, c in enumerate(df.columns) if row[f"x{i}"]]


def run(df: DataFrame) -> DataFrame:
    df = trim_and_coerce(df)
    return df.select(*informative(df)).dropDuplicates()
