"""Aggregates of joins and unions from the sketches of their inputs: both sides are grouped before they meet."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.ring import gram


def join_gamma(r: DataFrame, t: DataFrame, on: Sequence[str], m: int, p: int, by: Sequence[str] = ()) -> DataFrame:
    """Sketches by key (and more) of both sides -> the sketch of their equi-join, per ``by``."""
    both = r.withColumnRenamed("g", "_a").join(t.withColumnRenamed("g", "_b"), list(on))
    return gram.sum_elements(both.withColumn("g", gram.multiply(F.col("_a"), F.col("_b"), m, p)), m + p, by)


def left_gamma(r: DataFrame, t: DataFrame, on: Sequence[str], m: int, p: int, default: Column, by: Sequence[str] = ()) -> DataFrame:
    """As join_gamma for a left join: keys without partner meet the ``default`` element."""
    both = r.withColumnRenamed("g", "_a").join(t.withColumnRenamed("g", "_b"), list(on), "left")
    return gram.sum_elements(both.withColumn("g", gram.multiply(F.col("_a"), F.coalesce(F.col("_b"), default), m, p)), m + p, by)


def union_gamma(sketches: Sequence[DataFrame], m: int, by: Sequence[str] = ()) -> DataFrame:
    """The sketch of a union of tables from theirs."""
    every = sketches[0]
    for s in sketches[1:]:
        every = every.unionByName(s)
    return gram.sum_elements(every, m, by)


def chain(parts: Sequence[tuple[DataFrame, Sequence[str], Sequence[str], int]]) -> DataFrame:
    """A chain of joins: (sketches by key, keys to join the chain so far on, keys that stay, features) from left to right."""
    (left, _, keep, m), *rest = parts
    left = gram.sum_elements(left, m, keep)
    for right, on, keep, p in rest:
        left, m = join_gamma(left, right, on, m, p, keep), m + p
    return left


def theta_gamma(r: DataFrame, t: DataFrame, condition: Column, m: int, p: int, by: Sequence[str] = ()) -> DataFrame:
    """Sketch of a join on any condition over the distinct keys of the two sides (never over rows)."""
    both = r.withColumnRenamed("g", "_a").join(t.withColumnRenamed("g", "_b"), condition)
    return gram.sum_elements(both.withColumn("g", gram.multiply(F.col("_a"), F.col("_b"), m, p)), m + p, by)


def anti_gamma(r: DataFrame, t: DataFrame, on: Sequence[str], m: int, by: Sequence[str] = ()) -> DataFrame:
    """Sketch of the rows of r without partner in t."""
    return gram.sum_elements(r.join(t.select(*on).distinct(), list(on), "left_anti"), m, by)
