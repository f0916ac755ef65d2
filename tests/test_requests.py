"""The request path: corpus, discovery, re-use, edges of requests, service and model search."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from augspark import baselines, measures, workloads
from augspark import catalog as cat
from augspark.assess import crossval, solve
from augspark.modelsearch.search import HostedSimulator, ModelSearch, weights
from augspark.profile.index import ProfileIndex, unionable
from augspark.queries import searching
from augspark.ring import gram
from augspark.search import materialize
from augspark.search.engine import Search
from augspark.search.request import Request
from augspark.serve.scorer import RemoteScorer, of_plan
from augspark.sketch import build


def rows_of(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


def small(spark, n=400, seed=1):
    draw = np.random.default_rng(seed)
    rows = [(int(i % 20), int(i % 7), float(draw.normal()), int(i % 5)) for i in range(n)]
    base = spark.createDataFrame(rows, "k int, j int, x double, fold int")
    return base.withColumn("y", F.col("x") + F.sin(F.col("k").cast("double")) * 3 + F.cos(F.col("j") * 2.0) * 2)


def side(spark, key, n, f):
    return spark.createDataFrame([(i,) for i in range(n)], f"{key} int").withColumn("f", f(F.col(key).cast("double")))


def plan_sketches(plan):
    g = F.col("g")
    flat = plan.sketches.select("key_name", "key_value", "fold", F.round("g.c", 6).alias("c"), F.transform("g.s", lambda x: F.round(x, 6) + 0.0).alias("s"), F.transform("g.q", lambda x: F.round(x, 5) + 0.0).alias("q"))
    assert g is not None
    return rows_of(flat.filter(F.col("key_name").isin("*", *plan.keys)))


@pytest.mark.parametrize("mode", ["weight", "mean"])
@pytest.mark.parametrize("share", [0.0, 1.0])
def test_sketches_after_steps_equal_a_rescan(spark, mode, share):
    """Re-used sketches of keys, carried keys and totals are those of the joined rows, with fan-out and missing keys."""
    c = cat.Corpus(spark)
    many = side(spark, "k", 15, F.sin).unionByName(side(spark, "k", 9, F.cos)).withColumn("h", F.col("f") * F.col("k"))
    c.upload(many, "many", "RAW", ["k"], ["f", "h"])
    hop = side(spark, "j", 6, F.cos).withColumn("m", (F.col("j") % 3).cast("int"))
    c.upload(hop, "hop", "RAW", ["j", "m"], ["f"])
    req = Request(small(spark), ["x"], "y", {"k": "k", "j": "j"})
    s = Search(c, mode=mode, pair_share=share)
    plan = s.open(req)
    for name in ("many", "hop"):
        one = next(x for x in s.candidates(req, plan) if x.dataset.name == name)
        plan = s.extend(plan, one)
        plan.steps = [*plan.steps, one.step(0.0, 0.0)]
        again = replace(plan, sketches=s._rescanned(plan, list(plan.keys), True))
        assert plan_sketches(plan) == plan_sketches(again)
    assert "hop__m" in plan.keys


def test_union_then_join(spark):
    c = cat.Corpus(spark)
    rows = small(spark)
    c.upload(rows.filter("x > 0.3").select("k", "x", "y"), "more", "RAW", ["k"], ["x", "y"])
    c.upload(side(spark, "k", 20, F.sin), "side", "RAW", ["k"], ["f"])
    s, req = Search(c), Request(rows.filter("x <= 0.3"), ["x"], "y", {"k": "k"})
    plan = s.open(req)
    found = {x.dataset.name: x for x in s.candidates(req, plan) if x.dataset.name == "side" or x.kind == "horizontal"}
    plan = s.extend(plan, found["more"])
    assert plan_sketches(plan) == plan_sketches(replace(plan, sketches=s._rescanned(plan, ["k"], True)))
    assert plan.total().filter(F.col("fold") == crossval.ADDED).count() == 1
    plan.steps = [found["more"].step(0.0, 0.0)]
    plan = s.extend(plan, found["side"])
    plan.steps = [*plan.steps, found["side"].step(0.0, 0.0)]
    assert plan_sketches(plan) == plan_sketches(replace(plan, sketches=s._rescanned(plan, ["k"], True)))
    assert not any(x.kind == "horizontal" for x in s.candidates(req, plan))  # no union after a join


def test_provider_sketches_without_rows(spark):
    c, rows, extra = cat.Corpus(spark), small(spark), side(spark, "k", 20, F.sin)
    for name, label in (("a:b", "RAW"), ("c", "API")):
        c.upload_sketch(name, label, build.total(extra, ["f"]), {"k": build.by_key(extra, ["f"], ["k"])}, ["f"], 20)
    more = rows.filter("x > 0").select("k", "x", "y")
    c.upload_sketch("union", "RAW", build.total(more, ["x", "y"]), {"k": build.by_key(more, ["x", "y"], ["k"])}, ["x", "y"], more.count())
    a = Search(c).run(Request(rows.filter("x <= 0"), ["x"], "y", {"k": "k"}))
    assert ("vertical", "a:b") in {(s.kind, s.dataset) for s in a.plan} and a.cv_r2 > 0.5
    assert of_plan(Search(c), a).score(rows).count() == rows.count()


def test_request_edges(spark):
    c = cat.Corpus(spark)
    c.upload(spark.createDataFrame([], "k int, f double"), "empty", "RAW", ["k"], ["f"])
    c.upload(side(spark, "k", 20, lambda v: v * 0 + 4), "constant", "RAW", ["k"], ["f"])
    c.upload(side(spark, "k", 20, F.sin).withColumnRenamed("f", "x"), "clash", "RAW", ["k"], ["x"])
    c.upload(small(spark).select("k", "y"), "target", "RAW", ["k"], ["y"])
    c.upload(side(spark, "k", 20, F.sin).unionByName(spark.createDataFrame([(None, 5.0)], "k int, f double")), "nullkey", "RAW", ["k"], ["f"])
    rows = small(spark).withColumn("x", F.when(F.col("x") < 2, F.col("x"))).withColumn("y", F.when(F.col("j") < 6, F.col("y")))
    rows = rows.withColumn("k", F.when(F.col("k") != 3, F.col("k")))
    a = Search(c).run(Request(rows, ["x"], "y", {"k": "k"}))
    assert a.stopped == "gain" and {s.dataset for s in a.plan} <= {"clash", "nullkey"} and a.cv_r2 > 0.3
    assert "target" not in {s.dataset for s in a.plan}
    scored = of_plan(Search(c), a).score(rows)
    assert scored.filter("prediction is null").count() == 0 and scored.count() == rows.count()
    none = Search(cat.Corpus(spark)).run(Request(rows, ["x"], "y", {"k": "k"}, fold=None))
    assert none.plan == [] and none.stopped == "no candidate"
    flat = Search(c).run(Request(rows.withColumn("y", F.lit(1.0)), ["x"], "y", {"k": "k"}))
    assert flat.plan == [] and flat.base_r2 is None and flat.stopped == "constant target"


def test_upload_keeps_all_rows_and_changes_agree(spark):
    df = spark.createDataFrame([(1, 2.0, None), (1, None, 3.0), (2, 4.0, 5.0), (None, 6.0, 7.0)], "k int, a double, b double")
    c = cat.Corpus(spark)
    d = c.upload(df, "t", "RAW", ["k"], ["a", "b"])
    assert d.row_count == 4 and d.fill == {"a": 4.0, "b": 5.0}
    values = lambda x: rows_of(x.total.select("g.c", "g.s", "g.q"))
    first = values(d)
    more = spark.createDataFrame([(2, None, 1.0)], "k int, a double, b double")
    assert c.change("t", more, "insert").row_count == 5
    assert values(c.change("t", more, "delete")) == first and c.datasets["t"].data.count() == 4
    c.compact()
    assert values(c.datasets["t"]) == first and c.store.read("k", [d.sid]).count() == 2


def test_bulk_uploads_equal_single_ones(spark):
    wide = side(spark, "k", 30, F.sin).withColumn("h", F.when(F.col("k") % 4 > 0, F.cos("k")))
    c = cat.Corpus(spark)
    for d in c.upload_columns(wide, "k", ["f", "h"], prefix="bulk_"):
        one = c.upload(wide.select("k", d.features[0]), "single", "RAW", ["k"], [d.features[0]])
        flat = lambda x: rows_of(x.by_key["k"].select("k", F.round("g.c", 9), F.round(F.col("g.s")[0], 9), F.round(F.col("g.q")[0], 9)))
        assert flat(d) == flat(one) and d.row_count == one.row_count == 30
    parts = c.upload_partitions(small(spark), "fold", ["x", "y"], ["k"], prefix="part")
    assert [d.name for d in parts] == [f"part{i}" for i in range(5)] and sum(d.row_count for d in parts) == 400


def test_index_finds_keys_by_values_and_names(spark):
    index = ProfileIndex(spark)
    index.insert("same_values", spark.range(1000).select(F.col("id").alias("number"), F.rand(1).alias("z")), ["number"], ["z"])
    index.insert("other_values", spark.range(50_000, 51_000).select(F.col("id").alias("code"), F.rand(2).alias("z")), ["code"], ["z"])
    index.insert("same_name", spark.range(200_000).select(F.col("id").alias("a_member"), F.rand(3).alias("z")), ["a_member"], ["z"])
    rows = spark.range(900).select(F.col("id").alias("b_member"), F.rand(4).alias("price"), F.rand(5).alias("y"))
    got = {(r["dataset"], r["via"]) for r in index.candidates(index.profile(rows, ["b_member"], ["price", "y"])).filter("kind = 'vertical'").collect()}
    assert got == {("same_values", "number"), ("same_name", "a_member")}
    schemas = spark.createDataFrame([("a", "c_price", "double"), ("a", "c_day", "date"), ("b", "Price", "double"), ("b", "day", "date"), ("c", "other", "double")], "dataset string, column string, type string")
    assert {(r["a"], r["b"], r["mapped"]) for r in unionable(schemas, 0.8).collect()} == {("a", "b", 2), ("b", "a", 2)}


def test_discovered_union_has_other_names(spark):
    index = ProfileIndex(spark)
    c = cat.Corpus(spark, index)
    rows = small(spark)
    c.upload(rows.filter("x > 0").select(F.col("x").alias("t_income"), F.col("y").alias("t_score")), "renamed", "RAW", (), ["t_income", "t_score"])
    train = rows.filter("x <= 0").select(F.col("x").alias("income"), F.col("y").alias("score"), "fold")
    s, req = Search(c, discovery=index), Request(train, ["income"], "score", {})
    (one,) = s.candidates(req, s.open(req), s.discover(req))
    assert one.kind == "horizontal" and one.mapping == {"income": "t_income", "score": "t_score"}
    out = materialize.apply([one.step(0.1, 0.1)], train, c, {})
    assert out.count() == rows.count() and out.filter("income > 0").count() == rows.filter("x > 0").count()


def test_materialised_weights(spark):
    c = cat.Corpus(spark)
    c.upload(side(spark, "k", 5, F.sin).unionByName(side(spark, "k", 2, F.cos)), "many", "RAW", ["k"], ["f"])
    rows = small(spark, 40)
    step = next(x for x in Search(c).candidates(Request(rows, ["x"], "y", {"k": "k"}))).step(0.1, 0.1)
    out = materialize.apply([step], rows, c, {"k": "k"}, fanout="weight")
    assert out.agg(F.sum("weight")).first()[0] == pytest.approx(40) and out.count() == 44
    assert materialize.apply([step], rows, c, {"k": "k"}).count() == 40


def test_crossval_stacks_like_single_solves(spark):
    draw = np.random.default_rng(4)
    made = []
    for name, m, folds in (("a", 2, 3), ("b", 4, 3), ("c", 2, 5)):
        for f in range(folds):
            x = draw.normal(size=(30, m))
            x[:, -1] += x[:, 0]
            made.append((name, f - (name == "c"), (30.0, x.sum(axis=0).tolist(), [float((x[:, i] * x[:, j]).sum()) for i, j in gram.pairs(m)])))
    df = spark.createDataFrame(made, "dataset string, fold int, g struct<c:double,s:array<double>,q:array<double>>").repartition(4)
    for target in (1,):
        for r in crossval.score(df, target, lam=0.0).collect():
            grams = {f: solve.matrix(*g) for n, f, g in made if n == r["dataset"]}
            whole = sum(grams.values())
            want = np.mean([solve.r2(g, target, solve.ridge(whole - g, target)) for f, g in grams.items() if f != crossval.ADDED])
            assert r["cv_r2"] == pytest.approx(want) and r["theta"] == pytest.approx(solve.ridge(whole, target))


def test_service_learns_beyond_linear(spark, sf_dir):
    c = cat.Corpus(spark)
    c.upload(side(spark, "k", 20, lambda v: v), "side", "RAW", ["k"], ["f"])
    rows = small(spark, 1200).withColumn("y", F.when(F.col("k") > 9, 3.0).otherwise(0.0) + F.col("x") * 0.1)
    from augspark.serve.service import Service

    r = Service(c, final="trees", delta=0.001).answer(Request(rows, ["x"], "y", {"k": "k"}, model="any", returns=("RAW", "API"), budget_s=25.0))
    assert [s.dataset for s in r.plan] == ["side"] and r.model is None and r.score > r.answer.cv_r2 + 0.05
    got = measures.r2(r.api.score(rows), "y", "prediction").first()["r2"]
    assert got > 0.95
    assert set(rows.columns) <= set(r.api.score(rows).columns)


def test_model_search_on_both_tasks(spark):
    rows = small(spark, 600)
    found = ModelSearch("broad", 45).run(rows, ["x", "k", "j"], "y")
    assert {"linear", "neighbours", "forest"} <= {n for n, _, _ in found.models} and found.score >= found.best[2] - 1e-9
    assert found.model.predict(rows).filter("prediction is null").count() == 0
    classes = rows.withColumn("y", (F.col("y") > 0).cast("int"))
    found = ModelSearch("broad", 60, "class").run(classes, ["x", "k", "j"], "y")
    assert {"svm", "perceptron"} <= {n for n, _, _ in found.models}
    assert set(r["prediction"] for r in found.model.predict(classes).select("prediction").distinct().collect()) <= {0.0, 1.0}
    short = ModelSearch("trees", 0.0).run(rows, ["x"], "y")
    assert len(short.models) == 1
    assert HostedSimulator().bill(10) == pytest.approx(21.252)


def test_ensemble_weights():
    draw = np.random.default_rng(5)
    y = draw.normal(size=500)
    p = np.c_[y + draw.normal(size=500), y + draw.normal(size=500), draw.normal(size=500), y]
    s, q = p.sum(axis=0), [float((p[:, i] * p[:, j]).sum()) for i, j in gram.pairs(4)]
    w = weights(500.0, s, q, 3)
    assert w.sum() == pytest.approx(1) and w[2] <= min(w[0], w[1])


def test_remote_scorer_charges(spark):
    out, charge = RemoteScorer(lambda df: df.withColumn("prediction", F.lit(1.0)), 2.0).score(spark.range(500))
    assert out.columns == ["id", "prediction"] and charge == pytest.approx(1.0)


def test_injection_keeps_planted_features(spark):
    draw = np.random.default_rng(6)
    x = draw.normal(size=(3000, 3))
    rows = spark.createDataFrame([(float(a), float(b), float(c), float(3 * a + 0.1 * draw.normal())) for a, b, c in x], "a double, b double, c double, y double")
    votes = {r["feature"]: r["votes"] for r in baselines.injection_select(rows, ["a", "b", "c"], "y", rounds=3, trees=20, sample=0.5).collect()}
    assert votes["a"] == 6 and votes["b"] < 6 and votes["c"] < 6
    timing = {r["feature"]: r["votes"] for r in baselines.injection_select(rows, ["a", "b"], "y", inject=False, trees=10).collect()}
    assert timing["a"] == 2
    with pytest.raises(ValueError):
        baselines.neighbours(rows.withColumn("id", F.monotonically_increasing_id()), spark.range(20_001).withColumn("a", F.lit(1.0)), ["a"])


def test_labels_limit_requests(spark, sf_dir):
    c = searching.corpus(spark, sf_dir, supplier="MD")
    assert {x.dataset.name for x in Search(c).candidates(searching.request(spark, sf_dir))} == {"part", "orders"}
    joins = Search(c, api_may_join=True).candidates(searching.request(spark, sf_dir, returns=("API",)))
    assert {x.dataset.name for x in joins} == {"part", "supplier", "orders", "size"}


def test_measures_of_workloads(spark, sf_dir):
    tasks = workloads.six(spark, sf_dir)
    assert [t.classes for t in tasks] == [False] * 3 + [True] * 3
    train, test = workloads.split(tasks[0].rows)
    n = tasks[0].rows.count()
    assert train.count() + test.count() == n and abs(test.count() / n - 0.2) < 0.05
    assert workloads.size_class(tasks[0].rows)[1] in ("small", "medium", "large")


def test_cache_of_real_requests(spark, sf_dir):
    from augspark.search.cache import PlanCache

    study, cache = workloads.CacheStudy(spark, sf_dir, users=4, candidates=12, domain=150), PlanCache(1, 1)
    got = study.run([(1, 0), (2, 0), (3, 1), (4, 1), (5, 2), (6, 0)], cache)
    assert [g[2] for g in got] == ["miss", "hit", "failed_trial", "hit", "miss", "miss"]
    assert all(g[4] > 0.999 for g in got) and got[1][3] < got[0][3]
    assert study.run([(1, 0)], None)[0][2] == "miss"
