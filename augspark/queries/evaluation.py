"""Queries of measures, baselines and experiment workloads."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from augspark import baselines, measures
from augspark.assess import crossval, horizontal, solve, vertical
from augspark.cluster import materialize, table
from augspark.queries.common import LINE, TIE, cv_sql, greedy_sql, lines, planted, sql_gram, sql_means
from augspark.queries.registry import register
from augspark.ring import gram
from augspark.sketch import build

# measures

_HAT = "(5 + 1.5::DOUBLE * l_quantity)"


def _hat():
    return F.lit(5.0) + F.lit(1.5) * F.col("l_quantity")


@register("measure_r2", f"SELECT l_returnflag, round(1 - sum(pow(l_extendedprice / 1000 - {_HAT}, 2)) / (var_pop(l_extendedprice / 1000) * count(*)), 5) AS r2 FROM lineitem GROUP BY 1")
def measure_r2(spark, d):
    df = table(spark, d, "lineitem").withColumn("y", F.col("l_extendedprice") / 1000)
    return measures.r2(df, "y", _hat(), ["l_returnflag"]).withColumn("r2", F.round("r2", 5))


@register("measure_accuracy", "SELECT round(avg(((l_quantity > 25) = (l_extendedprice > 50000))::INTEGER), 6) AS accuracy FROM lineitem")
def measure_accuracy(spark, d):
    df = table(spark, d, "lineitem").withColumn("y", F.col("l_quantity") > 25)
    return measures.accuracy(df, "y", F.col("l_extendedprice") > 50000).select(F.round("accuracy", 6).alias("accuracy"))


@register("measure_sse", f"SELECT round(sum(pow(l_extendedprice / 1000 - {_HAT}, 2)) / 1000000, 4) AS sse FROM lineitem")
def measure_sse(spark, d):
    df = table(spark, d, "lineitem").withColumn("y", F.col("l_extendedprice") / 1000)
    return measures.sse(df, "y", _hat()).select(F.round(F.col("sse") / 1000000, 4).alias("sse"))


_RUNS = "(SELECT o_orderstatus AS config, o_orderkey % 10 AS run, round(avg(o_totalprice) / 500000, 6) AS score, (o_orderkey % 10) * 60.0::DOUBLE AS seconds FROM orders GROUP BY ALL)"


def runs(spark, d):
    o = table(spark, d, "orders")
    return o.groupBy(F.col("o_orderstatus").alias("config"), (F.col("o_orderkey") % 10).alias("run")).agg(F.round(F.avg("o_totalprice") / 500000, 6).alias("score")).withColumn("seconds", F.col("run") * 60.0)


@register("measure_cost", f"SELECT config, run, round(seconds * 0.78::DOUBLE / 3600, 6) AS cost FROM {_RUNS}")
def measure_cost(spark, d):
    return runs(spark, d).select("config", "run", F.round(measures.cost(F.col("seconds"), 0.78), 6).alias("cost"))


@register("run_summary", f"SELECT config, min(score) AS low, round(median(score), 6) AS median, max(score) AS high, count(*)::BIGINT AS runs FROM {_RUNS} GROUP BY 1")
def run_summary(spark, d):
    return measures.summarise(runs(spark, d), ["config"]).withColumn("median", F.round("median", 6))


@register("score_cdf", f"SELECT config, run, round(cume_dist() OVER (PARTITION BY config ORDER BY score), 9) AS share FROM {_RUNS}")
def score_cdf(spark, d):
    return measures.cdf(runs(spark, d), "score", ["config"]).select("config", "run", F.round("share", 9).alias("share"))


@register("score_heatmap", f"WITH r AS {_RUNS} SELECT least(greatest(floor(a.score * 10)::INTEGER + 1, 1), 10) AS before_bin, least(greatest(floor(b.score * 10)::INTEGER + 1, 1), 10) AS after_bin, count(*)::BIGINT AS requests FROM r a JOIN r b ON a.run = b.run AND a.config = 'F' AND b.config = 'O' GROUP BY 1, 2")
def score_heatmap(spark, d):
    r = runs(spark, d)
    pairs = r.filter("config = 'F'").select("run", F.col("score").alias("b")).join(r.filter("config = 'O'").select("run", F.col("score").alias("a")), "run")
    return measures.heatmap(pairs, "b", "a")


@register("anytime_curve", f"SELECT config, seconds, max(score) OVER (PARTITION BY config ORDER BY seconds ROWS UNBOUNDED PRECEDING) AS best_score FROM {_RUNS}")
def anytime_curve(spark, d):
    return measures.anytime(runs(spark, d), ["config"]).select("config", "seconds", "best_score")


@register("cost_to_reach", f"SELECT config, min(seconds / 100) FILTER (score >= 0.5) AS cost_to_reach FROM {_RUNS} GROUP BY 1")
def cost_to_reach(spark, d):
    return measures.cost_to_reach(runs(spark, d).withColumn("cost", F.col("seconds") / 100), F.lit(0.5), ["config"])


@register("query_count_model", "SELECT o_orderstatus, count(*) * 3 * count(DISTINCT o_custkey) AS queries FROM orders GROUP BY 1")
def query_count_model(spark, d):
    """Models trained without sketches: each order a request of three steps, each customer of its status a candidate."""
    return table(spark, d, "orders").groupBy("o_orderstatus").agg(measures.query_count(F.count("*"), 3, F.count_distinct("o_custkey")).alias("queries"))


# baselines


@register("injection_join_input", "SELECT l_orderkey, l_linenumber, round(p_retailprice, 4) AS price, round(s_acctbal, 4) AS balance FROM lineitem LEFT JOIN part ON l_partkey = p_partkey LEFT JOIN supplier ON l_suppkey = s_suppkey")
def injection_join_input(spark, d):
    joined = baselines.injection_join(lines(spark, d), [("l_partkey", table(spark, d, "part"), "p_partkey", ["p_retailprice"]), ("l_suppkey", table(spark, d, "supplier"), "s_suppkey", ["s_acctbal"])])
    return joined.select("l_orderkey", "l_linenumber", F.round("j0_p_retailprice", 4).alias("price"), F.round("j1_s_acctbal", 4).alias("balance"))


@register("injection_select")
def injection_select(spark, d):
    """Votes of joined features against injected random columns in ten rounds of a forest of 100 trees and a sparse model."""
    cands = [("l_partkey", table(spark, d, "part"), "p_partkey", ["p_retailprice", "p_size"]), ("l_suppkey", table(spark, d, "supplier"), "s_suppkey", ["s_acctbal"]), ("l_orderkey", table(spark, d, "orders"), "o_orderkey", ["o_totalprice", "o_custkey"])]
    joined = baselines.injection_join(planted(spark, d), cands)
    names = [f"j{n}_{f}" for n, c in enumerate(cands) for f in c[3]]
    return baselines.injection_select(joined, [*LINE, *names], "y")


def _points(spark, d):
    """Lines with one row an (order, line number): id, two features of few values, and a target."""
    df = table(spark, d, "lineitem").withColumn("id", F.col("l_orderkey") * 10 + F.col("l_linenumber"))
    n = F.row_number().over(Window.partitionBy("id").orderBy("l_extendedprice", "l_partkey"))
    return df.withColumn("n", n).filter("n = 1").select("id", F.col("l_quantity").alias("a"), (F.col("l_discount") * 100).alias("b"), (F.col("l_extendedprice") / 1000).alias("y"))


@register("novelty_rank")
def novelty_rank(spark, d):
    """How well 3-NN tells large orders' lines from small ones', over all rows; SQL would form every pair of rows."""
    s = materialize(_points(spark, d), "novelty-rows")
    return baselines.novelty(s.filter("a <= 30").select("id", "a", "b"), s.filter("a > 30").select("id", "a", "b"), ["a", "b"], near=baselines.neighbours_all).select(F.round("novelty", 6).alias("novelty"))


@register("knn_regress")
def knn_regress(spark, d):
    """3-NN regression of every row by all others; SQL would form every pair of rows."""
    s = materialize(_points(spark, d), "knn-rows")
    return baselines.knn_regress(s, s, ["a", "b"], "y", near=baselines.neighbours_all).select("qid", F.round("prediction", 5).alias("prediction"))


@register("modelsearch_broad")
def modelsearch_broad(spark, d):
    return _model_search(spark, d, "broad")


@register("modelsearch_trees")
def modelsearch_trees(spark, d):
    return _model_search(spark, d, "trees")


def _model_search(spark, d, kind):
    from augspark.modelsearch.search import ModelSearch

    df = planted(spark, d).join(table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice"), "l_partkey")
    found = ModelSearch(kind, 30).run(df, ["p_retailprice", "l_quantity"], "y")
    return spark.createDataFrame([(n, float(s)) for _, n, s in found.trace], "family string, score double")


@register("modelsearch_class")
def modelsearch_class(spark, d):
    """All families on a 0/1 target, among them support vectors and the perceptron: accuracy by family and setting."""
    from augspark.modelsearch.search import ModelSearch

    df = table(spark, d, "lineitem").select("l_quantity", "l_discount", "l_extendedprice", (F.col("l_quantity") * (1 - 5 * F.col("l_discount")) > 15).cast("int").alias("y"))
    found = ModelSearch("broad", 60, "class").run(df, ["l_quantity", "l_discount", "l_extendedprice"], "y")
    return spark.createDataFrame([(n, float(s)) for _, n, s in found.trace], "family string, score double")


@register("hosted_cost", f"SELECT o_orderkey, round(greatest(o_totalprice / 50, 3600) * 21.252::DOUBLE / 3600 + {TIE}::DOUBLE, 6) AS cost FROM orders")
def hosted_cost(spark, d):
    """What a hosted service bills for runs of so many seconds as an order's price by 50: at least an hour, whatever the budget."""
    from augspark.modelsearch.search import HostedSimulator

    return table(spark, d, "orders").select("o_orderkey", F.round(HostedSimulator().bill(F.col("o_totalprice") / 50) + TIE, 6).alias("cost"))


# workloads


def grid(spark, d):
    """Rows in an 8 x 8 grid, with a target whose slope and offset depend on the cell."""
    cell = lambda c, low, width: F.least(F.greatest(F.floor((F.col(c) - low) / width), F.lit(0)), F.lit(7))
    df = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", (F.col("l_quantity")).alias("x"), (F.col("l_tax") * 100).alias("v"), (cell("l_quantity", 0, 6.5) * 8 + cell("l_extendedprice", 0, 15000)).cast("int").alias("cell"))
    return df.withColumn("z", (F.col("cell") % 7) * 0.5 * F.col("v") + (F.col("cell") % 5) * 3.0)


_GRID = "(SELECT l_orderkey, l_linenumber, l_partkey, l_quantity AS x, l_tax * 100 AS v, cell, (cell % 7) * 0.5::DOUBLE * (l_tax * 100) + (cell % 5) * 3.0::DOUBLE AS z FROM (SELECT *, (least(greatest(floor(l_quantity / 6.5::DOUBLE), 0), 7) * 8 + least(greatest(floor(l_extendedprice / 15000), 0), 7))::INTEGER AS cell FROM lineitem))"


@register("grid_cells", f"SELECT cell, count(*)::BIGINT AS n, round(avg(z), 5) AS mean_z FROM {_GRID} GROUP BY 1")
def grid_cells(spark, d):
    return grid(spark, d).groupBy("cell").agg(F.count("*").alias("n"), F.round(F.avg("z"), 5).alias("mean_z"))


HOME = 9


@register(
    "grid_pick_proxy",
    f"""WITH g AS {_GRID}, t AS (SELECT v, z, (l_orderkey % 5)::INTEGER AS fold FROM g WHERE cell = {HOME} AND l_partkey % 4 = 0),
    c AS (SELECT cell, v, z FROM g WHERE cell <> {HOME}), cells AS (SELECT DISTINCT cell FROM c), folds AS (SELECT DISTINCT fold FROM t),
    tr AS (SELECT cells.cell, folds.fold, t.v, t.z FROM cells, folds, t WHERE t.fold <> folds.fold UNION ALL SELECT c.cell, folds.fold, c.v, c.z FROM c, folds),
    m AS (SELECT cell, fold, regr_slope(z, v) AS b, regr_intercept(z, v) AS a FROM tr GROUP BY 1, 2),
    s AS (SELECT m.cell, m.fold, 1 - sum(pow(t.z - a - b * t.v, 2)) / (var_pop(t.z) * count(*)) AS r2 FROM m JOIN t USING (fold) GROUP BY 1, 2)
    SELECT cell, cv_r2 FROM (SELECT cell, round(avg(r2), 4) AS cv_r2, row_number() OVER (ORDER BY avg(r2) DESC, cell) AS n FROM s GROUP BY 1) WHERE n <= 3""",
)
def grid_pick_proxy(spark, d):
    """The three cells whose rows help a model of one cell most, by the proxy."""
    g = grid(spark, d)
    t = g.filter(f"cell = {HOME} and l_partkey % 4 = 0").withColumn("fold", (F.col("l_orderkey") % 5).cast("int"))
    cells = build.by_key(g.filter(f"cell <> {HOME}"), ["v", "z"], ["cell"]).select(F.col("cell").cast("string").alias("dataset"), "g")
    scores = crossval.score(horizontal.batch(build.total(t, ["v", "z"], "fold"), cells), 1, lam=0.0)
    top = scores.orderBy(F.desc(F.round("cv_r2", 12)), F.col("dataset").cast("int")).limit(3)
    return top.select(F.col("dataset").cast("int").alias("cell"), F.round("cv_r2", 4).alias("cv_r2"))


@register(
    "grid_pick_novelty",
    f"""WITH g AS {_GRID}, s AS (SELECT *, row_number() OVER (PARTITION BY cell ORDER BY md5((l_orderkey * 10 + l_linenumber)::VARCHAR || ':' || l_partkey::VARCHAR), l_orderkey, x, z) AS n FROM g), k AS (SELECT cell, cell * 1000 + n AS id, v, z FROM s WHERE n <= 30),
    pool AS (SELECT o.cell AS cand, k.id, k.v, k.z, (k.cell <> {HOME})::INTEGER AS origin FROM (SELECT DISTINCT cell FROM k WHERE cell <> {HOME}) o JOIN k ON k.cell IN ({HOME}, o.cell)),
    p AS (SELECT q.cand, q.id AS qid, q.origin AS mine, r.origin, row_number() OVER (PARTITION BY q.cand, q.id ORDER BY round(pow(q.v - r.v, 2) + pow(q.z - r.z, 2), 8), r.id) AS n FROM pool q JOIN pool r ON q.cand = r.cand AND q.id <> r.id),
    v AS (SELECT cand, qid, any_value(mine) AS mine, (sum(origin) * 2 > 3)::INTEGER AS vote FROM p WHERE n <= 3 GROUP BY 1, 2)
    SELECT cand AS cell, round(avg((mine = vote)::INTEGER), 6) AS novelty FROM v GROUP BY 1""",
)
def grid_pick_novelty(spark, d):
    """Novelty of every other cell, by 3-NN over 30 hash-sampled rows a cell: it prefers dissimilar cells."""
    order = Window.partitionBy("cell").orderBy(F.md5(F.concat((F.col("l_orderkey") * 10 + F.col("l_linenumber")).cast("string"), F.lit(":"), F.col("l_partkey").cast("string"))), "l_orderkey", "x", "z")
    k = materialize(grid(spark, d).withColumn("n", F.row_number().over(order)).filter("n <= 30").select("cell", (F.col("cell") * 1000 + F.col("n")).alias("id"), "v", "z"), "cells")
    others = k.filter(f"cell <> {HOME}").select(F.col("cell").alias("cand")).distinct()
    pool = others.join(F.broadcast(k), (F.col("cell") == HOME) | (F.col("cell") == F.col("cand"))).select("cand", "id", "v", "z", (F.col("cell") != HOME).cast("int").alias("origin"))  # 30 rows a cell, 64 cells
    q = pool.select("cand", F.col("id").alias("qid"), F.col("v").alias("qv"), F.col("z").alias("qz"), F.col("origin").alias("mine"))
    far = F.round((F.col("qv") - F.col("v")) ** 2 + (F.col("qz") - F.col("z")) ** 2, 8)
    near = q.join(pool, "cand").filter("qid <> id").withColumn("n", F.row_number().over(Window.partitionBy("cand", "qid").orderBy(far, "id"))).filter("n <= 3")
    voted = near.groupBy("cand", "qid").agg(F.first("mine").alias("mine"), (F.sum("origin") * 2 > 3).cast("int").alias("vote"))
    return voted.groupBy(F.col("cand").alias("cell")).agg(F.round(F.avg((F.col("mine") == F.col("vote")).cast("double")), 6).alias("novelty"))


def _replicated(spark, d, k: int):
    return lines(spark, d).crossJoin(F.broadcast(spark.range(k).select(F.col("id").alias("copy"))))  # k rows


_F4 = [*LINE, "l_extendedprice"]


@register("bench_horizontal", " UNION ALL ".join(f"SELECT {k} AS copies, {sql_gram(_F4, 2)} FROM lineitem, range(0, {k})" for k in (1, 2, 4)))
def bench_horizontal(spark, d):
    """Horizontal micro-benchmark inputs: totals of 1 to 4 copies of the lines."""
    out = None
    for k in (1, 2, 4):
        one = build.total(_replicated(spark, d, k), _F4, exact=True).select(F.lit(k).alias("copies"), *gram.flat(_F4, digits=2))
        out = one if out is None else out.unionByName(one)
    return out


def bench_vertical(spark, d, key: str, domain: int, copies: int = 1):
    user = _replicated(spark, d, copies).withColumn("key", F.col(key) % domain)
    cand = table(spark, d, "orders").select((F.col("o_custkey") % domain).alias("key"), (F.col("o_totalprice") / 100000).alias("x"))
    c = build.by_key(cand, ["x"], ["key"]).withColumn("dataset", F.lit("orders"))
    u = build.by_key(user.withColumn("fold", F.lit(0)), ["l_quantity"], ["key"], "fold")
    return vertical.batch(u, c, gram.sum_elements(u, 1, ["fold"]), 1, 1)


def _bench_sql(key, domain, copies):
    return f"WITH c AS (SELECT o_custkey % {domain} AS key, avg(o_totalprice / 100000) AS x, avg(o_totalprice / 100000 * (o_totalprice / 100000)) AS v FROM orders GROUP BY 1), u AS (SELECT avg(x) AS u FROM c) SELECT {sql_means(['l_quantity', 'x'], terms={('x', 'x'): 'v'})} FROM (SELECT l_quantity, coalesce(x, u) AS x, coalesce(v, u * u) AS v FROM lineitem LEFT JOIN c ON {key} % {domain} = c.key CROSS JOIN u CROSS JOIN range(0, {copies}))"


@register("bench_vertical_rows", " UNION ALL ".join(f"(SELECT {k} AS copies, * FROM ({_bench_sql('l_suppkey', 30, k)}))" for k in (1, 2, 3, 4)))
def bench_vertical_rows(spark, d):
    from augspark.queries.common import means

    out = None
    for k in (1, 2, 3, 4):
        one = bench_vertical(spark, d, "l_suppkey", 30, k).select(F.lit(k).alias("copies"), *means(["l_quantity", "x"]))
        out = one if out is None else out.unionByName(one)
    return out


@register("bench_vertical_domain", " UNION ALL ".join(f"(SELECT {n} AS domain, * FROM ({_bench_sql('l_orderkey', n, 1)}))" for n in (2000, 4000, 6000, 8000)))
def bench_vertical_domain(spark, d):
    from augspark.queries.common import means

    out = None
    for n in (2000, 4000, 6000, 8000):
        one = bench_vertical(spark, d, "l_orderkey", n).select(F.lit(n).alias("domain"), *means(["l_quantity", "x"]))
        out = one if out is None else out.unionByName(one)
    return out


def uniform(name: str, key: str):
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{name}:"), F.col(key).cast("string"))), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def uniform_sql(name: str, key: str) -> str:
    return f"(('0x' || substr(md5('{name}:' || {key}::VARCHAR), 1, 13))::UBIGINT::DOUBLE / 4503599627370496::DOUBLE)"


_SYN = "SELECT p_partkey, " + ", ".join(f"{uniform_sql(f'f{i}', 'p_partkey')} AS f{i}" for i in range(2, 6)) + " FROM part"


@register("synthetic_corpus_profile", " UNION ALL ".join(f"SELECT 'f{i}' AS feature, round(avg(f{i}), 6) AS mean, round(stddev_samp(f{i}), 6) AS std FROM ({_SYN})" for i in range(2, 6)))
def synthetic_corpus_profile(spark, d):
    """The generated features of the controlled study."""
    df = table(spark, d, "part").select("p_partkey", *[uniform(f"f{i}", "p_partkey").alias(f"f{i}") for i in range(2, 6)])
    cells = [F.struct(F.lit(f"f{i}").alias("feature"), F.round(F.avg(f"f{i}"), 6).alias("mean"), F.round(F.stddev_samp(f"f{i}"), 6).alias("std")) for i in range(2, 6)]
    return df.agg(F.array(*cells).alias("a")).select(F.inline("a"))


def _synthetic(shape: str, useful: int):
    @register(f"synthetic_{shape}_{useful}")
    def run(spark, d):
        """The controlled study: 100 candidates (10 unions, 90 joins on ten keys), so many of them useful; test R² of the
        request alone, of the engine and of a model on all useful candidates. Gains above 0.005 are taken."""
        from augspark import workloads

        return workloads.synthetic(spark, d, useful, shape, delta=0.005)


for _shape, _useful in (("linear", 0), ("linear", 1), ("linear", 5), ("linear", 10), ("linear", 50), ("linear", 100), ("square", 10), ("square", 100)):
    _synthetic(_shape, _useful)


RUNS: dict = {}


def once(spark, d, name: str, make):
    """A study's rows, run once a session and folder, for the queries that report on it."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in RUNS:
        RUNS[key] = make()
        RUNS[key] = materialize(RUNS[key], name)
    return RUNS[key]


def _loo(spark, d):
    from augspark import workloads

    return once(spark, d, "leave-one-out", lambda: workloads.leave_one_out(spark, d))


@register("leave_one_out")
def leave_one_out(spark, d):
    """Every dataset of the corpus as a request once: test R² of its proxy alone and after the search, and its steps."""
    return _loo(spark, d)


@register("never_worse", "SELECT 0::BIGINT AS degraded")
def never_worse(spark, d):
    """Requests that the search left worse than no augmentation, by more than runs differ."""
    from augspark.workloads import TOLERANCE

    return _loo(spark, d).agg(F.count_if(F.col("engine") < F.col("alone") - TOLERANCE).alias("degraded"))


@register("leave_one_out_cdf")
def leave_one_out_cdf(spark, d):
    """Cumulative distribution of scores, alone and after the search."""
    both = _loo(spark, d).select("dataset", F.expr("stack(2, 'alone', alone, 'engine', engine) as (config, score)"))
    return measures.cdf(both, "score", ["config"])


@register("leave_one_out_heatmap")
def leave_one_out_heatmap(spark, d):
    """Requests by score alone and after the search."""
    return measures.heatmap(_loo(spark, d), "alone", "engine")


@register("vary_budget")
def vary_budget(spark, d):
    """The six requests by search alone and by the engine under budgets of 2 to 10 minutes, and whether each budget held."""
    from augspark import workloads

    return once(spark, d, "vary-budget", lambda: workloads.vary_budget(spark, d))


@register("budget_held")
def budget_held(spark, d):
    """The six requests under budgets of 2 to 10 minutes, by whether search and model search together kept the budget."""
    return vary_budget(spark, d).groupBy("held").agg(F.count("*").alias("requests"))


@register("grid_outcome")
def grid_outcome(spark, d):
    """The best union of one cell's rows by the proxy and by novelty: seconds, and R² on training and test rows."""
    from augspark import workloads

    return workloads.grid_study(spark, d)


@register("usecase_churn", "WITH e AS (SELECT user_id, avg(value) / 100 AS v FROM events GROUP BY 1), u AS (SELECT avg(v) AS u FROM e), n AS (SELECT c_nationkey AS k, avg(c_acctbal) / 1000 AS rate FROM customer GROUP BY 1) SELECT count(*)::DOUBLE AS c, round(regr_r2(y, v), 6) AS r2 FROM (SELECT (v IS NOT NULL AND v > 0.5)::INTEGER AS y, coalesce(e.v, u) AS v FROM customer LEFT JOIN e ON c_custkey = user_id CROSS JOIN u JOIN n ON c_nationkey = n.k)")
def usecase_churn(spark, d):
    """Customers with a 0/1 target, an engagement feed that most lack, and the proxy's fit from sketches."""
    e = table(spark, d, "events").groupBy(F.col("user_id").alias("key")).agg((F.avg("value") / 100).alias("v"))
    req = table(spark, d, "customer").select(F.col("c_custkey").alias("key")).join(e, "key", "left").select("key", (F.col("v").isNotNull() & (F.col("v") > 0.5)).cast("int").alias("y"), F.lit(0).alias("fold"))
    cand = build.by_key(e, ["v"], ["key"]).withColumn("dataset", F.lit("feed"))
    g = vertical.batch(build.by_key(req, ["y"], ["key"], "fold"), cand, build.total(req, ["y"], "fold"), 1, 1, "mean").withColumn("t", solve.ols(F.col("g"), 0))
    return g.select(F.col("g.c").alias("c"), F.round(solve.r2_of(F.col("g"), 0, F.col("t")), 6).alias("r2"))


@register("usecase_region", f"SELECT c_nationkey, {sql_means(['bal', 'orders_n'])} FROM (SELECT c_nationkey, c_acctbal / 1000 AS bal, coalesce(n, m)::DOUBLE AS orders_n FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1) o ON c_custkey = o_custkey CROSS JOIN (SELECT avg(n) AS m FROM (SELECT count(*) AS n FROM orders GROUP BY o_custkey))) GROUP BY 1")
def usecase_region(spark, d):
    """Customers by nation, with a rollup of orders joined; sketches by the nation that stands for the region."""
    from augspark.queries.common import means

    o = table(spark, d, "orders").groupBy(F.col("o_custkey").alias("key")).agg(F.count("*").cast("double").alias("x"))
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("key"), "c_nationkey", (F.col("c_acctbal") / 1000).alias("bal"), F.col("c_nationkey").alias("fold"))
    cand = build.by_key(o, ["x"], ["key"]).withColumn("dataset", F.lit("orders"))
    out = vertical.batch(build.by_key(c, ["bal"], ["key"], "fold"), cand, build.total(c, ["bal"], "fold"), 1, 1, "mean")
    return out.select(F.col("fold").alias("c_nationkey"), *means(["bal", "orders_n"]))


_LINES = "SELECT ((l_orderkey + 3 * l_linenumber) % 10)::INTEGER AS fold, {y} AS y, l_quantity, l_discount, l_tax, p_retailprice / 1000 AS part, s_acctbal / 1000 AS supplier, o_totalprice / 100000 AS orders FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey"
_PLANTED = "(10 * (p_retailprice - 950) + 0.1::DOUBLE * s_acctbal + 0.002::DOUBLE * o_totalprice)"
_THREE = {"part": ["part"], "supplier": ["supplier"], "orders": ["orders"]}
_MEDIAN = f"med AS (SELECT median({_PLANTED}) AS m FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey)"
_FEED = "(SELECT user_id, avg(value) AS v, count(*)::DOUBLE AS n FROM events GROUP BY 1)"
_D4 = f"SELECT (c_custkey % 10)::INTEGER AS fold, (coalesce(v, 0) > 50)::INTEGER::DOUBLE AS y, c_nationkey::DOUBLE AS nation, coalesce(v, mv) / 100 AS spent, coalesce(n, mn) AS visits FROM customer LEFT JOIN {_FEED} e ON c_custkey = user_id CROSS JOIN (SELECT avg(v) AS mv, avg(n) AS mn FROM {_FEED})"
_D6 = "SELECT ((l_orderkey + 3 * l_linenumber) % 10)::INTEGER AS fold, (l_returnflag = 'R')::INTEGER::DOUBLE AS y, l_quantity, l_discount, l_tax FROM lineitem"
_ONLY = "SELECT 0 AS step, '-' AS dataset, round(cv_r2, 4) AS cv_r2 FROM r"
REQUEST_SQL = {
    "d1": greedy_sql("SELECT (o_orderkey % 10)::INTEGER AS fold, c_acctbal / 100 + o_orderkey % 17 AS y, o_totalprice / 1000 AS price, c_acctbal / 1000 AS customer FROM orders JOIN customer ON o_custkey = c_custkey", ["price"], {"customer": ["customer"]}, 1),
    "d2": greedy_sql(f"{_LINES.format(y=_PLANTED + ' / 1000')} WHERE l_linenumber <= 2", LINE, _THREE),
    "d3": greedy_sql(_LINES.format(y=_PLANTED + " / 1000"), LINE, _THREE),
    "d4": greedy_sql(_D4, ["nation"], {"feed": ["spent", "visits"]}, 1),
    "d5": greedy_sql(f"{_LINES.format(y=f'({_PLANTED} > m)::INTEGER::DOUBLE')}, med", LINE, _THREE, extra=_MEDIAN),
    "d6": f"WITH {cv_sql(_D6, {'-': LINE})} {_ONLY}",
}


def _request(name: str):
    @register(f"request_{name}", REQUEST_SQL[name])
    def run(spark, d):
        """A request's whole search over the dimension tables and rollups: score of the plan at each step."""
        from augspark import workloads
        from augspark.search.engine import Search
        from augspark.search.request import Request

        (task,) = workloads.six(spark, d, (name,))
        corpus = once_corpus(spark, d)
        a = Search(corpus).run(Request(task.rows, task.features, "y", task.keys))
        rows = [(0, "-", float(a.base_r2)), *((i, s.dataset, float(s.cv_r2)) for i, s in enumerate(a.plan, 1))]
        return spark.createDataFrame(rows, "step int, dataset string, r double").select("step", "dataset", F.round("r", 4).alias("cv_r2"))


def once_corpus(spark, d):
    """The corpus of the six requests, registered once a session and folder."""
    from augspark import workloads

    key = (spark.sparkContext.applicationId, d, "corpus")
    if key not in RUNS:
        RUNS[key] = workloads.dimensions(spark, d)
    return RUNS[key]


for _name in REQUEST_SQL:
    _request(_name)


@register("request_sizes", "SELECT 'd1' AS request, (SELECT count(*) FROM orders) * 32 AS bytes UNION ALL SELECT 'd2', (SELECT count(*) FROM lineitem WHERE l_linenumber <= 2) * 64 UNION ALL SELECT 'd3', (SELECT count(*) FROM lineitem) * 64 UNION ALL SELECT 'd4', (SELECT count(*) FROM customer) * 32 UNION ALL SELECT 'd5', (SELECT count(*) FROM lineitem) * 64 UNION ALL SELECT 'd6', (SELECT count(*) FROM lineitem) * 56")
def request_sizes(spark, d):
    """Bytes of each request's training table, by which requests are classed as small, medium or large."""
    from augspark import workloads

    return spark.createDataFrame(list(workloads.request_bytes(spark, d).items()), "request string, bytes long")


@register("six_requests")
def six_requests(spark, d):
    """Test score, seconds and dollars of six requests by model search alone and by the engine before it, under ten seconds."""
    from augspark import workloads

    return workloads.six_requests(spark, d, 10.0, 1, ("trees", "engine+trees"))
