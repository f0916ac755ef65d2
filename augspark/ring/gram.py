"""The gram ring: (count, sums, pair sums) of a feature list.

An element is a struct g of c double, s array of m sums and q array of m(m+1)/2 pair sums, the upper triangle by rows.
Aggregation runs over generated scalar columns, so it stays in whole-stage code with partial sums before the shuffle;
arrays are packed only afterwards.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def pairs(m: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(m) for j in range(i, m)]


def at(i: int, j: int, m: int) -> int:
    """Place of a pair in q."""
    i, j = min(i, j), max(i, j)
    return i * m - i * (i - 1) // 2 + j - i


def number(feature: str | Column, exact: bool = False) -> Column:
    """A feature as double, or as exact decimal where sums must not depend on their order."""
    c = feature if isinstance(feature, Column) else F.col(feature)
    return c.cast("decimal(18,2)") if exact else c.cast("double")


def element(c: Column, s: Sequence[Column], q: Sequence[Column]) -> Column:
    as_array = lambda xs: F.array(*xs) if xs else F.array().cast("array<double>")
    return F.struct(c.cast("double").alias("c"), as_array([x.cast("double") for x in s]).alias("s"), as_array([x.cast("double") for x in q]).alias("q"))


def zero(m: int) -> Column:
    return element(F.lit(0.0), [F.lit(0.0)] * m, [F.lit(0.0)] * len(pairs(m)))


def one(m: int) -> Column:
    return element(F.lit(1.0), [F.lit(0.0)] * m, [F.lit(0.0)] * len(pairs(m)))


def lift(features: Sequence[str]) -> Column:
    """The element of one row."""
    x = [number(f) for f in features]
    return element(F.lit(1.0), x, [x[i] * x[j] for i, j in pairs(len(x))])


def sums(x: Sequence[Column], products: dict[tuple[int, int], Column] | None = None) -> list[Column]:
    """Aggregates that ``pack`` turns into an element; products replaces x[i] * x[j] of a pair (i <= j).

    A row that stands for several weighted partners has their mean as x and the mean of their products as product.
    """
    products = products or {}
    out = [F.count(F.lit(1)).alias("_c"), *[F.sum(v).alias(f"_s{i}") for i, v in enumerate(x)]]
    return out + [F.sum(products[i, j] if (i, j) in products else x[i] * x[j]).alias(f"_q{i}_{j}") for i, j in pairs(len(x))]


def gamma(df: DataFrame, features: Sequence[str], by: Sequence[str] = (), exact: bool = False) -> DataFrame:
    """Sketch of each group: by..., g. Features must not be null (impute first)."""
    x = [number(f, exact) for f in features]
    return df.groupBy(*by).agg(*sums(x)).select(*by, pack(len(x)).alias("g"))


def pack(m: int) -> Column:
    """The element of aggregated scalar columns; those of no rows are zero."""
    z = lambda name: F.coalesce(F.col(name).cast("double"), F.lit(0.0))
    return element(z("_c"), [z(f"_s{i}") for i in range(m)], [z(f"_q{i}_{j}") for i, j in pairs(m)])


def sum_elements(df: DataFrame, m: int, by: Sequence[str] = (), g: str = "g") -> DataFrame:
    """Ring addition inside groups of sketches."""
    aggs = [F.sum(f"{g}.c").alias("_c")]
    aggs += [F.sum(F.col(f"{g}.s")[i]).alias(f"_s{i}") for i in range(m)]
    aggs += [F.sum(F.col(f"{g}.q")[at(i, j, m)]).alias(f"_q{i}_{j}") for i, j in pairs(m)]
    return df.groupBy(*by).agg(*aggs).select(*by, pack(m).alias("g"))


def linear(c: Column, s: Sequence[Column]) -> Column:
    """An element without pair sums: all that a product with another table takes from a key."""
    return element(c, s, [])


def sum_linear(df: DataFrame, m: int, by: Sequence[str] = (), g: str = "g") -> DataFrame:
    """Ring addition inside groups of sketches without pair sums."""
    aggs = [F.expr(f"sum({g}.c) AS _c"), *[F.expr(f"sum({g}.s[{i}]) AS _s{i}") for i in range(m)]]
    return df.groupBy(*by).agg(*aggs).select(*by, pack_linear(m).alias("g"))


def pack_linear(m: int) -> Column:
    """``pack`` without pair sums; one text, as forming it column by column takes longer than summing small groups."""
    z = lambda name: f"coalesce(CAST({name} AS double), 0D)"
    s = f"array({', '.join(z(f'_s{i}') for i in range(m))})"
    return F.expr(f"named_struct('c', {z('_c')}, 's', CAST({s} AS array<double>), 'q', CAST(array() AS array<double>))")


def add(a: Column, b: Column, sign: int = 1) -> Column:
    plus = lambda x, y: x + sign * y
    return F.struct(plus(a["c"], b["c"]).alias("c"), F.zip_with(a["s"], b["s"], plus).alias("s"), F.zip_with(a["q"], b["q"], plus).alias("q"))


def subtract(a: Column, b: Column) -> Column:
    """The ring's inverse: deletions, and a total without one fold."""
    return add(a, b, -1)


def multiply(a: Column, b: Column, m: int, p: int) -> Column:
    """The element over both feature lists for every pair of rows that a and b stand for."""
    ac, bc = a["c"], b["c"]
    s = [a["s"][i] * bc for i in range(m)] + [b["s"][i] * ac for i in range(p)]

    def q(i: int, j: int) -> Column:
        if j < m:
            return a["q"][at(i, j, m)] * bc
        if i >= m:
            return b["q"][at(i - m, j - m, p)] * ac
        return a["s"][i] * b["s"][j - m]

    return element(ac * bc, s, [q(i, j) for i, j in pairs(m + p)])


def affine(g: Column, shift: Sequence, scale: Sequence) -> Column:
    """The element of (x - shift) / scale, without going back to rows."""
    m = len(shift)
    h, k = [F.lit(v) if not isinstance(v, Column) else v for v in shift], [F.lit(v) if not isinstance(v, Column) else v for v in scale]
    c, s, q = g["c"], g["s"], g["q"]
    sums = [(s[i] - c * h[i]) / k[i] for i in range(m)]
    both = [(q[at(i, j, m)] - h[i] * s[j] - h[j] * s[i] + c * h[i] * h[j]) / (k[i] * k[j]) for i, j in pairs(m)]
    return element(c, sums, both)


def reweight(g: Column, m: int, mode: str = "weight") -> Column:
    """Make a key's element count once: ``weight`` spreads its rows, ``mean`` replaces them by their mean, ``raw`` keeps them."""
    if mode == "raw":
        return g
    c = g["c"]
    s = [g["s"][i] / c for i in range(m)]
    if mode == "weight":
        return element(F.lit(1.0), s, [g["q"][at(i, j, m)] / c for i, j in pairs(m)])
    if mode == "mean":
        return element(F.lit(1.0), s, [s[i] * s[j] for i, j in pairs(m)])
    raise ValueError(f"unknown fan-out mode {mode}")


def pick(g: Column, at: Sequence[int], m: int) -> Column:
    """The element over some of m features, in the order of their places."""
    return element(g["c"], [g["s"][i] for i in at], [g["q"][_place(at, i, j, m)] for i, j in pairs(len(at))])


def _place(of: Sequence[int], i: int, j: int, m: int) -> int:
    return at(of[i], of[j], m)


def flat(features: Sequence[str], g: Column | None = None, digits: int = 4) -> list[Column]:
    """Scalar columns c, s_<feature>, q_<feature>_<feature> of an element, for reports and comparisons."""
    g, m = F.col("g") if g is None else g, len(features)
    out = [F.round(g["c"], digits).alias("c")]
    out += [F.round(g["s"][i], digits).alias(f"s_{f}") for i, f in enumerate(features)]
    return out + [F.round(g["q"][at(i, j, m)], digits).alias(f"q_{features[i]}_{features[j]}") for i, j in pairs(m)]


def wide(df: DataFrame, array: str, m: int, by: Sequence[str] = ()) -> DataFrame:
    """(by, i, j, value) of array columns too wide for generated sums: i = j = -1 is the count, i = -1 the sums.

    Each task adds up outer products of its batches and sends one row a group and place; the rest is a plain sum.
    """
    kept = [f for f in df.schema.fields if f.name in by]

    def partial(batches):
        held: dict[tuple, np.ndarray] = {}
        for batch in batches:
            groups = batch.groupby(list(by), dropna=False, sort=False) if by else [((), batch)]
            for key, rows in groups:
                x = np.c_[np.ones(len(rows)), np.stack(rows[array].to_numpy()).astype(float)]
                key = key if isinstance(key, tuple) else (key,)
                held[key] = held.get(key, 0) + x.T @ x
        i, j = np.triu_indices(m + 1)
        for key, g in held.items():
            yield pd.DataFrame({b: key[n] for n, b in enumerate(by)} | {"i": i - 1, "j": j - 1, "value": g[i, j]})

    fields = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), "i int", "j int", "value double"])
    return df.select(*by, array).mapInPandas(partial, fields).groupBy(*by, "i", "j").agg(F.sum("value").alias("value"))


def wide_matrix(df: DataFrame, features: Sequence[str]) -> np.ndarray:
    """(m + 1, m + 1): the matrix of pair sums of a whole table, with the constant 1 as first feature, for as many features as
    generated sums don't compile for. Its places alone reach the driver."""
    m = len(features)
    out = np.zeros((m + 1, m + 1))
    for r in wide(df.select(F.array(*[number(f"`{f}`") for f in features]).alias("x")), "x", m).collect():
        out[r["i"] + 1, r["j"] + 1] = out[r["j"] + 1, r["i"] + 1] = r["value"]
    return out
