"""MinHash signatures of columns' value sets, similarity estimates and banded candidate pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

K, BANDS = 64, 16


def _hash(value: Column, seed: int, portable: bool) -> Column:
    return F.md5(F.concat(F.lit(f"{seed}:"), value)) if portable else F.xxhash64(F.lit(seed), value)


def signature(values: DataFrame, by: list[str], value: str = "value", k: int = K, portable: bool = False) -> DataFrame:
    """(by, value) -> (by, signature): the least hash per seed; partial minima before the shuffle.

    ``portable`` uses MD5, which other engines share; the default is the faster 64-bit hash.
    """
    v = F.col(value).cast("string")
    least = [F.min(_hash(v, s, portable)).alias(f"_h{s}") for s in range(k)]
    return values.filter(v.isNotNull()).groupBy(*by).agg(*least).select(*by, F.array(*[F.col(f"_h{s}") for s in range(k)]).alias("signature"))


def merge(a: Column, b: Column) -> Column:
    """The signature of a union: elementwise least, also how inserts are absorbed."""
    return F.zip_with(a, b, lambda x, y: F.least(x, y))


def similarity(a: Column, b: Column) -> Column:
    """The share of equal places, an estimate of the Jaccard similarity."""
    same = F.zip_with(a, b, lambda x, y: (x == y).cast("int"))
    return F.aggregate(same, F.lit(0), lambda t, x: t + x) / F.size(a)


def candidates(signatures: DataFrame, name: str, bands: int = BANDS, k: int = K) -> DataFrame:
    """(a, b) pairs of names that agree on all rows of some band: an equi-join on band values, near-linear in columns."""
    rows = k // bands
    banded = signatures.select(name, F.posexplode(F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda i: F.sha2(F.array_join(F.slice("signature", i * rows + 1, rows).cast("array<string>"), ","), 256))).alias("band", "value"))
    left, right = banded.withColumnRenamed(name, "a"), banded.withColumnRenamed(name, "b")
    return left.join(right, ["band", "value"]).filter("a < b").select("a", "b").distinct()
