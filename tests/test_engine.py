"""Ring laws, solver, search rules, cache, budget and plans of the augmentation engine."""

import random
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from augspark import catalog as cat
from augspark.assess import crossval, solve, vertical
from augspark.assess.reuse import PlanMemo
from augspark.queries import searching
from augspark.ring import gram
from augspark.search.cache import PlanCache
from augspark.search.cost import budget_split
from augspark.search.deadline import Deadline
from augspark.search.engine import Search
from augspark.search.request import Request
from augspark.sketch import build


def sketch(rows):
    x = np.asarray(rows, float).reshape(len(rows), -1)
    m = x.shape[1]
    return (float(len(x)), x.sum(axis=0).tolist(), [float((x[:, i] * x[:, j]).sum()) for i, j in gram.pairs(m)])


def values(row):
    g = row["g"]
    return [g["c"], *g["s"], *g["q"]]


def test_ring_laws(spark):
    draw = np.random.default_rng(1)
    a, b, c = (sketch(draw.integers(-5, 5, (n, 2))) for n in (3, 4, 2))
    e = "struct<c:double,s:array<double>,q:array<double>>"
    df = spark.createDataFrame([(a, b, c)], f"a {e}, b {e}, c {e}")
    get = lambda g: values(df.select(g.alias("g")).first())
    A, B, C = F.col("a"), F.col("b"), F.col("c")
    assert get(gram.add(gram.add(A, B), C)) == get(gram.add(A, gram.add(B, C)))
    assert get(gram.add(A, B)) == get(gram.add(B, A))
    assert get(gram.add(A, gram.zero(2))) == get(A) == get(gram.multiply(A, gram.one(0), 2, 0))
    assert get(gram.subtract(gram.add(A, B), B)) == get(A)
    assert get(gram.multiply(A, gram.add(B, C), 2, 2)) == get(gram.add(gram.multiply(A, B, 2, 2), gram.multiply(A, C, 2, 2)))
    assert get(gram.multiply(gram.multiply(A, B, 2, 2), C, 4, 2)) == get(gram.multiply(A, gram.multiply(B, C, 2, 2), 2, 4))


def test_solver_against_numpy():
    draw = np.random.default_rng(2)
    x = draw.normal(100, 3, (200, 3))
    y = 7 + x @ [1.5, -2, 0.25] + draw.normal(size=200)
    g = solve.matrix(*sketch(np.c_[x, y]))
    theta = solve.ridge(g, 3)
    want = np.linalg.lstsq(np.c_[np.ones(200), x], y, rcond=None)[0]
    assert theta == pytest.approx(want, rel=1e-6)
    err = y - np.c_[np.ones(200), x] @ want
    assert solve.sse(g, 3, theta) == pytest.approx((err**2).sum(), rel=1e-6)
    assert solve.r2(g, 3, theta) == pytest.approx(1 - (err**2).sum() / ((y - y.mean()) ** 2).sum(), rel=1e-6)
    same = solve.matrix(*sketch(np.c_[x, x[:, 0], np.full(200, 4.0), y]))  # a duplicate and a constant feature
    assert solve.r2(same, 5, solve.ridge(same, 5)) == pytest.approx(solve.r2(g, 3, theta), rel=1e-6)
    assert np.isnan(solve.r2(solve.matrix(*sketch(np.ones((5, 2)))), 1, np.zeros(2)))
    assert solve.ridge(solve.matrix(0.0, [0.0, 0.0], [0.0, 0.0, 0.0]), 1).tolist() == [0.0, 0.0]


def test_vertical_edges(spark):
    user = spark.createDataFrame([(1, 0, 2.0), (1, 1, 4.0), (2, 0, 6.0), (None, 1, 8.0)], "key int, fold int, y double")
    totals, by = build.total(user, ["y"], "fold"), build.by_key(user, ["y"], ["key"], "fold")
    nobody = build.by_key(spark.createDataFrame([(9, 3.0)], "key int, x double"), ["x"], ["key"]).withColumn("dataset", F.lit("none"))
    out = {r["fold"]: values(r) for r in vertical.batch(by, nobody, totals, 1, 1).collect()}
    assert out == {0: [2.0, 8.0, 6.0, 40.0, 24.0, 18.0], 1: [2.0, 12.0, 6.0, 80.0, 36.0, 18.0]}
    assert vertical.batch(by, nobody.limit(0), totals, 1, 1).count() == 0
    scored = crossval.score(vertical.batch(by, nobody, totals, 1, 1), 0).first()
    assert scored["cv_r2"] is not None


def test_request_is_checked(spark):
    df = spark.createDataFrame([(1, 2.0, 0)], "k int, y double, fold int")
    for how in ({"model": "deep"}, {"returns": ()}, {"returns": ("ALL",)}, {"budget_s": -1}):
        with pytest.raises(ValueError):
            Request(df, [], "y", {"k": "k"}, **how)
    with pytest.raises(ValueError):
        Request(df, ["y"], "y", {})
    with pytest.raises(ValueError):
        Request(df, ["gone"], "y", {})


def test_planted_search(spark, sf_dir):
    d = "/root/testdata/sf0.01"
    c = searching.corpus(spark, d)
    a = Search(c).run(searching.request(spark, d))
    assert [s.dataset for s in a.plan] == ["supplier", "part", "orders"] and a.cv_r2 > 0.999 and abs(a.base_r2) < 0.01
    assert a.stopped in ("gain", "no candidate")
    theta = dict(zip(a.feature_names, a.theta[1:], strict=True))
    scale = {n: c.datasets[n].scales[f][1] for n, f in (("part", "p_retailprice"), ("supplier", "s_acctbal"))}  # features are standardised
    assert theta["part__p_retailprice"] == pytest.approx(10 * scale["part"], rel=1e-3) and theta["supplier__s_acctbal"] == pytest.approx(0.1 * scale["supplier"], rel=1e-3)
    own = Search(c).run(searching.request(spark, d, returns=("MD",)))
    assert own.plan == []
    none = Search(c).run(searching.request(spark, d, budget_s=0.0))
    assert none.plan == [] and none.stopped == "budget"


def test_lineage_and_labels(spark):
    c = cat.Corpus(spark)
    df = spark.createDataFrame([(1, 2.0), (2, 3.0)], "k int, x double")
    for name, label, lineage in (("a", "RAW", "own"), ("b", "MD", None), ("c", "API", None)):
        c.upload(df, name, label, ["k"], ["x"], lineage)
    assert {x.name for x in c.visible(["RAW", "API"])} == {"a"}
    assert {x.name for x in c.visible(["API"])} == {"a", "b", "c"}
    assert {x.name for x in c.visible(["API"], but="own")} == {"b", "c"}
    d = c.change("a", spark.createDataFrame([(3, 5.0)], "k int, x double"), "insert")
    assert d.row_count == 3 and d.version == 2
    d = c.change("a", spark.createDataFrame([(3, 5.0)], "k int, x double"), "delete")
    assert d.row_count == 2 and d.by_key["k"].count() == 2


def test_cache_is_least_recently_used():
    draw, cache, model = random.Random(3), PlanCache(3, 2), []
    for _ in range(500):
        s, p = str(draw.randint(0, 5)), draw.randint(0, 3)
        if draw.random() < 0.5:
            cache.put(s, str(p), p)
            model = [(a, [x for x in b if x != p] + [p] if a == s else b) for a, b in model]
            mine = next((b for a, b in model if a == s), [p])
            model = ([(a, b) for a, b in model if a != s] + [(s, mine[-2:])])[-3:]
        assert {a: list(reversed(b)) for a, b in model} == {a: cache.get(a) for a in cache.held}
    assert PlanCache(0).trial("x", lambda p: 1.0) == ("miss", None)


def test_memo_and_budget():
    memo, made = PlanMemo(), []
    steps = [("vertical", "a", ["k"]), ("vertical", "b", ["j"])]
    for order in (steps, steps[::-1]):
        memo.get(order, lambda: made.append(1) or "sketch")
    assert made == [1]
    assert budget_split(600, "fixed") == (300.0, 300.0) and budget_split(60) == (60, 60)


def test_deadline_cancels_jobs(spark):
    began = time.monotonic()
    with Deadline(spark, 1.0) as deadline, pytest.raises(Exception):  # noqa: B017
        spark.range(10**12).select(F.sum(F.sin("id"))).collect()
    assert deadline.expired and time.monotonic() - began < 30


def test_plan_shapes(spark, sf_dir):
    user, totals = searching.lines(spark, sf_dir), None
    by = build.by_key(user, ["l_quantity"], ["l_suppkey"], "fold").withColumnRenamed("l_suppkey", "key")
    totals = build.total(user, ["l_quantity"], "fold")
    cand = build.by_key(user, ["l_tax"], ["l_suppkey"]).withColumnRenamed("l_suppkey", "key").withColumn("dataset", F.lit("a"))
    plan = vertical.batch(by, cand, totals, 1, 1)._jdf.queryExecution().optimizedPlan().toString()
    join, aggregate = plan.index("Join Inner"), plan.index("Aggregate", plan.index("Join Inner"))
    assert join < aggregate  # both sides are aggregated below their join
    scan = user.filter("l_quantity > 45").select("l_orderkey")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in scan
