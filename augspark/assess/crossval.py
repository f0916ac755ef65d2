"""Cross-validation from fold sketches: the training side of a fold is the total without it."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.assess import solve
from augspark.ring import gram

#: Rows of added tables carry this fold: they train every fold and validate none.
ADDED = -1


def _scored(target: int, lam: float, held: bool):
    """A batch of candidates, each with all its folds, solved in stacks of equal shape."""

    @F.pandas_udf("struct<cv_r2:double,theta:array<double>>")
    def run(fold: pd.Series, c: pd.Series, s: pd.Series, q: pd.Series) -> pd.DataFrame:
        best, thetas = np.full(len(fold), np.nan), np.empty(len(fold), object)
        shapes: dict[tuple[int, int], list[int]] = {}
        for i, (f, x) in enumerate(zip(fold, s, strict=True)):
            shapes.setdefault((len(f), len(x)), []).append(i)
        for (n, width), at in shapes.items():
            take = lambda column: np.stack([column.iloc[i] for i in at]).reshape(len(at) * n, -1)
            g = solve.matrices(take(c)[:, 0], take(s), take(q))
            m = width // n + 1
            whole = g.reshape(len(at), n, m, m).sum(axis=1)
            sides = np.repeat(whole, n, axis=0) - g
            kept = take(fold)[:, 0] != ADDED
            got = np.full(len(g), np.nan)
            got[kept] = solve.r2s(g[kept], target, solve.ridges(sides[kept], target, lam))
            got = got.reshape(len(at), n)
            known = ~np.isnan(got)
            best[at] = np.where(known.any(axis=1), np.nansum(got, axis=1) / np.maximum(1, known.sum(axis=1)), np.nan)
            fitted = whole - (g * kept[:, None, None]).reshape(len(at), n, m, m).sum(axis=1) if held else whole
            for i, theta in zip(at, solve.ridges(fitted, target, lam), strict=True):
                thetas[i] = theta
        return pd.DataFrame({"cv_r2": best, "theta": thetas})

    return run


def score(folds: DataFrame, target: int, by: str = "dataset", lam: float = 1e-6, held: bool = False, elements: bool = False) -> DataFrame:
    """(by, fold, g) -> (by, cv_r2, theta): mean R² over folds, and parameters on all rows (held: on added rows only).

    A candidate's few folds are gathered into one row; a worker solves a whole batch of candidates at once. With elements
    that row's array of (fold, g) is kept as f.
    """
    rows = F.array_sort(F.collect_list(F.struct("fold", "g")))
    each = folds.groupBy(by).agg(rows.alias("f"))
    part = lambda of: F.transform("f", of)
    found = _scored(target, lam, held)(part(lambda x: x["fold"]), part(lambda x: x["g"]["c"]), F.flatten(part(lambda x: x["g"]["s"])), F.flatten(part(lambda x: x["g"]["q"])))
    return each.select(by, found.alias("r"), "f").select(by, F.nanvl("r.cv_r2", F.lit(None).cast("double")).alias("cv_r2"), "r.theta", *(["f"] if elements else []))


def validate(train: DataFrame, held: DataFrame, target: int, lam: float = 0.0) -> DataFrame:
    """One-row sketches of a training and a validation table -> (r2, theta)."""
    both = train.withColumn("theta", solve.ols(F.col("g"), target, lam)).select("theta").crossJoin(F.broadcast(held))  # one row each
    return both.select(solve.r2_of(F.col("g"), target, F.col("theta")).alias("r2"), "theta")


def complements(folds: DataFrame, m: int, by: list[str]) -> DataFrame:
    """(by, fold, g) -> the same with ``train``: the group's total without the fold."""
    whole = gram.sum_elements(folds, m, by).withColumnRenamed("g", "_all")
    both = folds.join(whole, by) if by else folds.crossJoin(F.broadcast(whole))
    return both.withColumn("train", gram.subtract(F.col("_all"), F.col("g"))).drop("_all")
