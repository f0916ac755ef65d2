"""Linear models from sketches alone: parameters, squared loss and R² of (count, sums, pair sums)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def matrices(c, s, q) -> np.ndarray:
    """(n, m + 1, m + 1): of each of n elements the symmetric matrix of pair sums, with the constant 1 as first feature."""
    s, q = np.asarray(s, float), np.asarray(q, float)
    n, m = s.shape
    out, (rows, cols) = np.empty((n, m + 1, m + 1)), np.triu_indices(m)
    out[:, 0, 0], out[:, 0, 1:], out[:, 1:, 0] = c, s, s
    out[:, rows + 1, cols + 1] = q
    out[:, cols + 1, rows + 1] = q
    return out


def matrix(c: float, s, q) -> np.ndarray:
    return matrices([c], [list(s)], [list(q)])[0]


def _centred(g: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(counts, means, centred pair sums); of no rows they are zero."""
    n = g[:, 0, 0]
    mean = g[:, 0, 1:] / np.where(n > 0, n, 1.0)[:, None]
    return n, mean, g[:, 1:, 1:] - n[:, None, None] * mean[:, :, None] * mean[:, None, :]


def ridges(g: np.ndarray, target: int, lam: float = 0.0) -> np.ndarray:
    """(intercept, weights) of each of n matrices, in a few stacked operations.

    Features are centred and scaled first, so the solve is well conditioned and the penalty applies to the original
    weights but not to the intercept. Constant features get weight 0; directions that features share get the least norm.
    """
    n, mean, cov = _centred(g)
    f = [i for i in range(g.shape[1] - 1) if i != target]
    theta = np.zeros((len(g), len(f) + 1))
    if f:
        a = cov[:, f][:, :, f] + lam * np.eye(len(f))
        own = np.maximum(np.einsum("nii->ni", a), 0.0)
        size = np.maximum(np.einsum("nii->ni", g[:, 1:, 1:])[:, f], 1e-300)
        live = np.sqrt(own) > 1e-9 * np.sqrt(size)
        k = np.where(live, np.sqrt(own), 1.0)
        both = live[:, :, None] & live[:, None, :]
        scaled = np.where(both, a / (k[:, :, None] * k[:, None, :]), 0.0)
        values, vectors = np.linalg.eigh(scaled)
        inverse = np.where(values > 1e-10 * values.max(axis=1, keepdims=True).clip(1e-300), 1 / np.where(values > 0, values, 1.0), 0.0)
        side = np.where(live, cov[:, f, target] / k, 0.0)
        w = np.einsum("nij,nj,nkj,nk->ni", vectors, inverse, vectors, side, optimize=True) / k
        theta[:, 1:] = np.where(live, w, 0.0)
    theta[:, 0] = mean[:, target] - np.einsum("ni,ni->n", theta[:, 1:], mean[:, f])
    theta[n <= 0] = 0.0
    return theta


def ridge(g: np.ndarray, target: int, lam: float = 0.0) -> np.ndarray:
    return ridges(g[None], target, lam)[0]


def losses(g: np.ndarray, target: int, theta: np.ndarray) -> np.ndarray:
    """Squared loss of each parameter vector over the rows that its matrix stands for, from centred sums."""
    n, mean, cov = _centred(g)
    v = np.zeros((len(g), g.shape[1] - 1))
    v[:, target] = 1.0
    v[:, [i for i in range(v.shape[1]) if i != target]] = -theta[:, 1:]
    bias = np.einsum("ni,ni->n", v, mean) - theta[:, 0]
    return np.where(n > 0, np.einsum("ni,nij,nj->n", v, cov, v) + n * bias * bias, 0.0)


def sse(g: np.ndarray, target: int, theta: np.ndarray) -> float:
    return float(losses(g[None], target, np.asarray(theta)[None])[0])


def r2s(g: np.ndarray, target: int, theta: np.ndarray) -> np.ndarray:
    """1 - squared loss over total squares; NaN where the target is constant."""
    _, _, cov = _centred(g)
    total = cov[:, target, target]
    known = (g[:, 0, 0] > 0) & (total > 1e-12 * np.maximum(1.0, g[:, target + 1, target + 1]))
    return np.where(known, 1.0 - losses(g, target, theta) / np.where(known, total, 1.0), np.nan)


def r2(g: np.ndarray, target: int, theta: np.ndarray) -> float:
    return float(r2s(g[None], target, np.asarray(theta)[None])[0])


def extend_inverse(inverse: np.ndarray, cross: np.ndarray, own: float) -> np.ndarray:
    """The inverse of a matrix grown by one row and column, through the Schur complement."""
    u = inverse @ cross
    rest = own - cross @ u
    grown = np.empty((len(u) + 1, len(u) + 1))
    grown[:-1, :-1] = inverse + np.outer(u, u) / rest
    grown[:-1, -1] = grown[-1, :-1] = -u / rest
    grown[-1, -1] = 1 / rest
    return grown


def _stacked(c: pd.Series, s: pd.Series, q: pd.Series):
    """(positions, matrices) of the elements of each width."""
    widths = s.map(len).to_numpy()
    for m in np.unique(widths):
        at = np.flatnonzero(widths == m)
        yield at, matrices(c.to_numpy()[at], np.stack(s.to_numpy()[at]), np.stack(q.to_numpy()[at]))


def ols(g: Column, target: int, lam: float = 0.0) -> Column:
    """θ of each sketch in a column."""

    @F.pandas_udf("array<double>")
    def solved(c: pd.Series, s: pd.Series, q: pd.Series) -> pd.Series:
        out = np.empty(len(c), object)
        for at, stack in _stacked(c, s, q):
            for i, theta in zip(at, ridges(stack, target, lam), strict=True):
                out[i] = theta
        return pd.Series(out, dtype=object)

    return solved(g["c"], g["s"], g["q"])


def _of_theta(measure, target: int):
    @F.pandas_udf("double")
    def measured(c: pd.Series, s: pd.Series, q: pd.Series, t: pd.Series) -> pd.Series:
        out = np.empty(len(c))
        for at, stack in _stacked(c, s, q):
            out[at] = measure(stack, target, np.stack(t.to_numpy()[at]))
        return pd.Series(out)

    return measured


def loss(g: Column, target: int, theta: Column) -> Column:
    return _of_theta(losses, target)(g["c"], g["s"], g["q"], theta)


def r2_of(g: Column, target: int, theta: Column) -> Column:
    """R² of parameters on a sketch, null for a constant target."""
    return F.nanvl(_of_theta(r2s, target)(g["c"], g["s"], g["q"], theta), F.lit(None).cast("double"))


def threshold(score: Column, cut: float = 0.5) -> Column:
    """Classes from scores of a regression on a 0/1 target."""
    return F.when(score >= cut, 1).otherwise(0)
