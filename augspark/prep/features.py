"""Derived features: polynomials, interactions and principal components."""

from __future__ import annotations

import itertools
from collections.abc import Sequence
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.assess.solve import matrix


def polynomial(df: DataFrame, columns: Sequence[str], degree: int = 2) -> DataFrame:
    """All monomials of total degree 2 to ``degree``; degree 1 is there already."""
    new = {}
    for d in range(2, degree + 1):
        for combo in itertools.combinations_with_replacement(columns, d):
            new["_x_".join(combo)] = reduce(lambda a, b: a * b, [F.col(c).cast("double") for c in combo])
    return df.withColumns(new)


def interactions(df: DataFrame, pairs: Sequence[tuple[str, str]]) -> DataFrame:
    return df.withColumns({f"{a}_x_{b}": F.col(a).cast("double") * F.col(b).cast("double") for a, b in pairs})


def pca_from_gram(c: float, s, q, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(variances, components by row) of the k leading directions from a sketch; signs make the largest entry positive."""
    g = matrix(c, s, q)
    mean = g[0, 1:] / c
    cov = (g[1:, 1:] - c * np.outer(mean, mean)) / max(c - 1, 1)
    values, vectors = np.linalg.eigh(cov)
    best = np.argsort(values)[::-1][:k]
    parts = vectors[:, best].T
    parts *= np.sign(parts[np.arange(len(parts)), np.abs(parts).argmax(axis=1)])[:, None]
    return values[best], parts


def pca(df: DataFrame, columns: Sequence[str], k: int) -> DataFrame:
    """df with pc_1..pc_k, the projections on components found from one sketch."""
    from augspark.sketch import build

    g = build.total(df.dropna(subset=list(columns)), columns).first()["g"]
    _, parts = pca_from_gram(g["c"], g["s"], g["q"], k)
    mean = [x / g["c"] for x in g["s"]]
    project = lambda part: reduce(lambda a, b: a + b, [(F.col(c).cast("double") - float(m)) * float(w) for c, m, w in zip(columns, mean, part, strict=True)])
    return df.withColumns({f"pc_{i}": project(p) for i, p in enumerate(parts, 1)})
