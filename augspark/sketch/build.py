"""Sketches of tables: totals, by key, and all of a round in one pass."""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.ring import gram


def total(df: DataFrame, features: Sequence[str], fold: str | None = None, exact: bool = False) -> DataFrame:
    return gram.gamma(df, features, [fold] if fold else [], exact)


def by_key(df: DataFrame, features: Sequence[str], keys: Sequence[str], fold: str | None = None, exact: bool = False) -> DataFrame:
    """Rows with a null key join nothing, so they are left out of key sketches (not of totals)."""
    for k in keys:
        df = df.filter(F.col(k).isNotNull())
    return gram.gamma(df, features, [*keys, *([fold] if fold else [])], exact)


ALL = "*"


def keyed(df: DataFrame, x: Sequence[Column], keys: Sequence[Sequence[str]], fold: Column | None = None, total: bool = True, products: dict[tuple[int, int], Column] | None = None, apart: bool = False) -> DataFrame:
    """(key_name, key_value, fold, g) of every list of keys and, as key_name '*', overall: one grouping-sets pass.

    A list of several keys is named by its keys joined with '&', and its values likewise are a JSON array; rows with a
    null key are in no sketch of that key. apart reads the rows once for each list of keys instead, as ``linear`` does.
    """
    own = sorted({k for ks in keys for k in ks})
    n, types = len(own), dict(df.dtypes)
    spare = {(i, j): c.alias(f"_p{i}_{j}") for (i, j), c in (products or {}).items()}
    rows = df.select((F.lit(0) if fold is None else fold).alias("fold"), *[_plain(k, types).alias(f"_k{i}") for i, k in enumerate(own)], *[v.alias(f"_x{i}") for i, v in enumerate(x)], *spare.values())
    marks = {k: F.col(f"_k{i}") for i, k in enumerate(own)}
    aggs = gram.sums([F.col(f"_x{i}") for i in range(len(x))], {ij: F.col(f"_p{ij[0]}_{ij[1]}") for ij in spare})
    if apart:
        parts = []
        for ks in [*([[]] if total else []), *keys]:
            texts = [marks[k].cast("string") for k in ks]
            value = F.lit(None).cast("string") if not ks else texts[0] if len(ks) == 1 else F.to_json(F.array(*texts))
            known = rows.filter(~_any([marks[k].isNull() for k in ks])) if ks else rows
            parts.append(known.groupBy("fold", *[marks[k] for k in ks]).agg(*aggs).select(F.lit("&".join(ks) or ALL).alias("key_name"), value.alias("key_value"), "fold", gram.pack(len(x)).alias("g")))
        return reduce(DataFrame.unionByName, parts)
    sets = [[F.col("fold"), *[marks[k] for k in ks]] for ks in [*([[]] if total else []), *keys]]
    grouped = rows.groupingSets(sets, F.col("fold"), *marks.values()).agg(*aggs, F.grouping_id().alias("_level"))
    name, value = F.lit(ALL), F.lit(None).cast("string")
    for ks in keys:
        level = sum(1 << (n - 1 - i) for i, k in enumerate(own) if k not in ks)
        here, is_null = F.col("_level") == level, [marks[k].isNull() for k in ks]
        texts = [marks[k].cast("string") for k in ks]
        joined = texts[0] if len(ks) == 1 else F.when(~_any(is_null), F.to_json(F.array(*texts)))
        name, value = F.when(here, "&".join(ks)).otherwise(name), F.when(here, joined).otherwise(value)
    out = grouped.select(name.alias("key_name"), value.alias("key_value"), "fold", gram.pack(len(x)).alias("g"))
    return out.filter(f"key_name = '{ALL}' or key_value is not null")


def linear(df: DataFrame, x: Sequence[Column], keys: Sequence[Sequence[str]], fold: Column, apart: bool = False) -> DataFrame:
    """(key_name, key_value, fold, g) of every list of keys, as ``keyed`` names them, without pair sums.

    Scoring and extending a plan take counts and sums from a key and pair sums from totals alone, so this is what a request's
    keys need: its width grows with the number of features, not with their pairs. apart reads the rows once for each list
    of keys, which is less to shuffle where reading them is cheap.
    """
    if apart and len(keys) > 1:
        out = linear(df, x, keys[:1], fold)
        for ks in keys[1:]:
            out = out.unionByName(linear(df, x, [ks], fold))
        return out
    types = dict(df.dtypes)
    own = sorted({k for ks in keys for k in ks})
    rows = df.select(fold.alias("fold"), *[_plain(k, types).alias(f"_k{i}") for i, k in enumerate(own)], *[v.alias(f"_x{i}") for i, v in enumerate(x)])
    marks = {k: F.col(f"_k{i}") for i, k in enumerate(own)}
    aggs = [F.expr("count(1) AS _c"), *[F.expr(f"sum(_x{i}) AS _s{i}") for i in range(len(x))]]
    text = lambda k: marks[k].cast("string")
    value = lambda ks: text(ks[0]) if len(ks) == 1 else F.to_json(F.array(*[text(k) for k in ks]))
    known = lambda ks: ~_any([marks[k].isNull() for k in ks])
    g = gram.pack_linear(len(x)).alias("g")
    if len(keys) == 1:
        grouped = rows.filter(known(keys[0])).groupBy(*[marks[k] for k in keys[0]], "fold").agg(*aggs)
        return grouped.select(F.lit("&".join(keys[0])).alias("key_name"), value(keys[0]).alias("key_value"), "fold", g)
    grouped = rows.groupingSets([[F.col("fold"), *[marks[k] for k in ks]] for ks in keys], F.col("fold"), *marks.values()).agg(*aggs, F.grouping_id().alias("_level"))
    name, values = F.lit(None).cast("string"), F.lit(None).cast("string")
    for ks in keys:
        here = F.col("_level") == sum(1 << (len(own) - 1 - i) for i, k in enumerate(own) if k not in ks)
        name, values = F.when(here, "&".join(ks)).otherwise(name), F.when(here & known(ks), value(ks)).otherwise(values)
    return grouped.select(name.alias("key_name"), values.alias("key_value"), "fold", g).filter("key_value is not null")


def single(df: DataFrame, x: Sequence[Column], key: str, fold: Column) -> DataFrame:
    """``linear`` of one key without summing: an element a row. What sums elements by a key takes both alike."""
    k = F.col(f"`{key}`").cast("string")
    z = lambda v: F.coalesce(v, F.lit(0.0))
    return df.filter(F.col(f"`{key}`").isNotNull()).select(F.lit(key).alias("key_name"), k.alias("key_value"), fold.alias("fold"), gram.linear(F.lit(1.0), [z(v) for v in x]).alias("g"))


def _plain(key: str, types: dict[str, str]) -> Column:
    """A key to group by: whole numbers as they are, as texts take more room in a shuffle."""
    return F.col(f"`{key}`") if types[key] in ("tinyint", "smallint", "int", "bigint") else F.col(f"`{key}`").cast("string")


def _any(columns: Sequence[Column]) -> Column:
    out = columns[0]
    for c in columns[1:]:
        out = out | c
    return out


def round_sketches(df: DataFrame, features: Sequence[str], keys: Sequence[str], fold: str = "fold", exact: bool = False) -> DataFrame:
    """(key_name, key_value, fold, g) for every key and, as key_name '*', overall: one grouping-sets pass over the rows."""
    return keyed(df, [gram.number(f, exact) for f in features], [[k] for k in keys], F.col(fold))
