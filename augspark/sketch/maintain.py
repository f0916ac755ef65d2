"""Incremental maintenance of sketches: signed deltas are added, and keys whose count falls to zero leave."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.ring import gram


def delta(rows: DataFrame, features: Sequence[str], by: Sequence[str], op: str = "insert", exact: bool = False) -> DataFrame:
    """The signed sketch of inserted or deleted rows."""
    return signed(gram.gamma(rows, features, by, exact), len(features), op)


def signed(sketches: DataFrame, m: int, op: str) -> DataFrame:
    if op not in ("insert", "delete"):
        raise ValueError("op is insert or delete; an update is a delete and an insert")
    return sketches if op == "insert" else sketches.withColumn("g", gram.subtract(gram.zero(m), F.col("g")))


def apply(sketch: DataFrame, deltas: Sequence[DataFrame], m: int, by: Sequence[str]) -> DataFrame:
    """Stored sketch and deltas -> the new sketch; an update is a delete and an insert."""
    every = sketch
    for d in deltas:
        every = every.unionByName(d)
    return gram.sum_elements(every, m, by).filter("g.c > 0")
