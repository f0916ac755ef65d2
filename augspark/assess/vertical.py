"""Vertical candidates of one key, all at once.

For a user element (c, s, Q) and a candidate element (1, u, V) of the same key value, the product adds only c u, s uᵀ and
c V to what the user already has, so the user's own block is never recomputed. A left join is the inner join plus one
subtraction: rows without partner are the user's total minus the matched sums, times the candidate's default element.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from augspark.ring import gram


def defaults(candidates: DataFrame, p: int, impute: str | float = "mean") -> DataFrame:
    """(dataset, u): the values that stand in for a missing partner, from the candidates' own per-key means."""
    means = [F.col("g.s")[i] / F.col("g.c") for i in range(p)]
    if impute == "mean":
        values = [F.avg(x) for x in means]
    elif impute == "median":
        values = [F.percentile(x, F.lit(0.5)) for x in means]
    elif impute == "mode":
        values = [F.mode(x, deterministic=True) for x in means]
    else:
        values = [F.max(F.lit(0.0 if impute == "zero" else float(impute)))] * p
    return candidates.groupBy("dataset").agg(F.array(*values).alias("u"))


def batch(user: DataFrame, candidates: DataFrame, totals: DataFrame, m: int, p: int, mode: str = "weight", impute: str | float = "mean", keys: Sequence[str] = ("key",), known: DataFrame | None = None) -> DataFrame:
    """user (keys, fold, g), candidates (dataset, keys, g), totals (fold, g) -> (dataset, fold, g over m + p features).

    ``mode``: weight (a key's rows share weight 1), mean (replaced by their mean) or raw (join multiplicity). known: the
    candidates' ``defaults``, where they were formed before.
    """
    # scalars are joined, as arrays take several times their room in a shuffle
    weighed, g = candidates.withColumn("_d", gram.reweight(F.col("g"), p, mode)), F.col("g")
    d, raw = F.col("_d"), mode == "raw"
    weighed = weighed.select("dataset", *keys, d["c"].alias("_dc"), *[d["s"][k].alias(f"_ds{k}") for k in range(p)], *[d["q"][gram.at(k, n, p)].alias(f"_dq{k}_{n}") for k, n in gram.pairs(p)])
    own_q = [g["q"][gram.at(i, j, m)].alias(f"_uq{i}_{j}") for i, j in gram.pairs(m)] if raw else []
    mine = user.select(*keys, "fold", *[F.expr(of) for of in ["g.c AS _uc", *[f"g.s[{i}] AS _us{i}" for i in range(m)]]], *own_q)
    both = mine.join(weighed, list(keys))
    # texts, as a wide plan takes thousands of calls to form by columns
    col, sums = F.col, {"mc": "_uc", "jc": "_uc * _dc"} | {f"ms{i}": f"_us{i}" for i in range(m)} | {f"u{k}": f"_uc * _ds{k}" for k in range(p)}
    sums |= {f"x{i}_{k}": f"_us{i} * _ds{k}" for i in range(m) for k in range(p)} | {f"v{k}_{n}": f"_uc * _dq{k}_{n}" for k, n in gram.pairs(p)}
    aggs = [F.expr(f"sum({of}) AS {name}") for name, of in sums.items()]
    if raw:
        aggs += [F.sum(col(f"_us{i}") * col("_dc")).alias(f"js{i}") for i in range(m)]
        aggs += [F.sum(f"_uq{i}_{j}").alias(f"mq{i}_{j}") for i, j in gram.pairs(m)]
        aggs += [F.sum(col(f"_uq{i}_{j}") * col("_dc")).alias(f"jq{i}_{j}") for i, j in gram.pairs(m)]
    matched = both.groupBy("dataset", "fold").agg(*aggs)
    frame = (defaults(candidates, p, impute) if known is None else known).crossJoin(F.broadcast(totals.select("fold", F.col("g").alias("_t"))))  # a row a fold
    return frame.join(matched, ["dataset", "fold"], "left").select("dataset", "fold", _complete(m, p, raw).alias("g"))


def _complete(m: int, p: int, raw: bool) -> Column:
    if not raw:  # the user's own block stays as it is, so it is cut out of its array: a row of pairs is one slice
        z = lambda name: f"coalesce({name}, 0D)"
        rest = lambda i: f"(_t.s[{i}] - {z(f'ms{i}')})"
        if not p:
            return F.col("_t")
        new_s = [f"{z(f'u{k}')} + (_t.c - {z('mc')}) * u[{k}]" for k in range(p)]
        rows = [f"slice(_t.q, {gram.at(i, i, m) + 1}, {m - i}), array({', '.join(f'{z(f"x{i}_{k}")} + {rest(i)} * u[{k}]' for k in range(p))})" for i in range(m)]
        tail = [f"{z(f'v{k}_{n}')} + (_t.c - {z('mc')}) * u[{k}] * u[{n}]" for k, n in gram.pairs(p)]
        return F.expr(f"named_struct('c', _t.c, 's', concat(_t.s, array({', '.join(new_s)})), 'q', concat({', '.join([*rows, f'array({", ".join(tail)})'])}))")
    z = lambda name: F.coalesce(F.col(name), F.lit(0.0))
    t, u = F.col("_t"), F.col("u")
    rest_c = t["c"] - z("mc")
    rest_s = [t["s"][i] - z(f"ms{i}") for i in range(m)]
    own_s = [z(f"js{i}") + rest_s[i] for i in range(m)]
    own_q = {(i, j): z(f"jq{i}_{j}") + t["q"][gram.at(i, j, m)] - z(f"mq{i}_{j}") for i, j in gram.pairs(m)}
    new_s = [z(f"u{k}") + rest_c * u[k] for k in range(p)]

    def q(i: int, j: int) -> Column:
        if j < m:
            return own_q[i, j]
        if i >= m:
            return z(f"v{i - m}_{j - m}") + rest_c * u[i - m] * u[j - m]
        return z(f"x{i}_{j - m}") + rest_s[i] * u[j - m]

    return gram.element(z("jc") + rest_c, own_s + new_s, [q(i, j) for i, j in gram.pairs(m + p)])


def best(scores: DataFrame, digits: int = 12) -> DataFrame:
    """Scores with their rank, the best first, ties by name."""
    return scores.withColumn("rank", F.row_number().over(Window.orderBy(F.desc(F.round("cv_r2", digits)), "dataset")))
