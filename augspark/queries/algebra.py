"""Queries of the algebra: rings, push-down, models from sketches, cross-validation."""

from __future__ import annotations

from pyspark.sql import functions as F

from augspark.assess import crossval, solve
from augspark.cluster import table
from augspark.queries.common import FOLD_SQL, LINE, REQ_SQL, lines, means, planted, sql_gram, sql_means
from augspark.queries.registry import register
from augspark.ring import gram, natural, pushdown
from augspark.sketch import build

MONEY = ["o_totalprice"]


@register(
    "ring_count_sum",
    "SELECT c_nationkey, count(*)::BIGINT AS n_orders, sum(CAST(o_totalprice AS DECIMAL(18,2)))::DOUBLE AS total FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1",
)
def ring_count_sum(spark, d):
    """Counts and sums of a join from annotations that were summed below the join."""
    orders, customers = table(spark, d, "orders").select("o_custkey", "o_totalprice"), table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    right = natural.gamma(natural.annotate(customers), "o_custkey", "c_nationkey")
    counted = natural.gamma(natural.join(natural.gamma(natural.annotate(orders), "o_custkey"), right, ["o_custkey"]), "c_nationkey")
    summed = natural.gamma(natural.join(natural.gamma(natural.annotate(orders, gram.number("o_totalprice", True)), "o_custkey"), right, ["o_custkey"]), "c_nationkey")
    return counted.select("c_nationkey", F.col("a").alias("n_orders")).join(summed.select("c_nationkey", F.col("a").cast("double").alias("total")), "c_nationkey")


@register("ring_identities", f"SELECT 'zero' AS law, {sql_gram(LINE)} FROM lineitem UNION ALL SELECT 'one' AS law, {sql_gram(LINE)} FROM lineitem")
def ring_identities(spark, d):
    g = build.total(lines(spark, d), LINE, exact=True)
    plus = g.select(F.lit("zero").alias("law"), gram.add(F.col("g"), gram.zero(3)).alias("g"))
    times = g.select(F.lit("one").alias("law"), gram.multiply(F.col("g"), gram.one(0), 3, 0).alias("g"))
    return plus.unionByName(times).select("law", *gram.flat(LINE))


@register("ring_add", f"SELECT {sql_gram(LINE)} FROM lineitem WHERE l_linenumber <= 4")
def ring_add(spark, d):
    a, b = (build.total(lines(spark, d).filter(c), LINE, exact=True) for c in ("l_linenumber <= 2", "l_linenumber between 3 and 4"))
    return a.withColumnRenamed("g", "a").crossJoin(F.broadcast(b.withColumnRenamed("g", "b"))).select(gram.add(F.col("a"), F.col("b")).alias("g")).select(*gram.flat(LINE))  # one row each


@register("ring_subtract", f"SELECT {sql_gram(LINE)} FROM lineitem WHERE {FOLD_SQL} <> 3")
def ring_subtract(spark, d):
    folds = build.total(lines(spark, d), LINE, "fold", exact=True)
    return crossval.complements(folds, 3, []).filter("fold = 3").select(F.col("train").alias("g")).select(*gram.flat(LINE))


@register("gram_total_lineitem", f"SELECT {FOLD_SQL}::INTEGER AS fold, {sql_gram([*LINE, 'l_extendedprice'])} FROM lineitem GROUP BY 1")
def gram_total_lineitem(spark, d):
    f = [*LINE, "l_extendedprice"]
    return build.total(lines(spark, d), f, "fold", exact=True).select("fold", *gram.flat(f))


@register("gram_by_key_orders", f"SELECT o_custkey, {sql_gram(MONEY)} FROM orders GROUP BY 1")
def gram_by_key_orders(spark, d):
    return build.by_key(table(spark, d, "orders"), MONEY, ["o_custkey"], exact=True).select("o_custkey", *gram.flat(MONEY))


@register("gram_by_two_keys", f"SELECT l_suppkey, l_linenumber, {sql_gram(LINE)} FROM lineitem GROUP BY 1, 2")
def gram_by_two_keys(spark, d):
    return build.by_key(lines(spark, d), LINE, ["l_suppkey", "l_linenumber"], exact=True).select("l_suppkey", "l_linenumber", *gram.flat(LINE))


@register("ring_multiply", f"SELECT k, {sql_means(['price', 'bal'])} FROM (SELECT o_custkey AS k, o_totalprice / 100000 AS price, c_acctbal / 1000 AS bal FROM orders JOIN customer ON o_custkey = c_custkey) GROUP BY 1")
def ring_multiply(spark, d):
    a = build.by_key(table(spark, d, "orders").select(F.col("o_custkey").alias("k"), (F.col("o_totalprice") / 100000).alias("price")), ["price"], ["k"]).withColumnRenamed("g", "a")
    b = build.by_key(table(spark, d, "customer").select(F.col("c_custkey").alias("k"), (F.col("c_acctbal") / 1000).alias("bal")), ["bal"], ["k"]).withColumnRenamed("g", "b")
    return a.join(b, "k").select("k", gram.multiply(F.col("a"), F.col("b"), 1, 1).alias("g")).select("k", *means(["price", "bal"]))


@register(
    "pushdown_equals_materialized",
    "SELECT c_nationkey, count(*)::DOUBLE AS c, round(avg(l_quantity) + 1.3e-9::DOUBLE, 6) AS s_l_quantity, round(avg(o_totalprice / 100000) + 1.3e-9::DOUBLE, 6) AS s_price, round(avg(l_quantity * l_quantity) + 1.3e-9::DOUBLE, 6) AS q_l_quantity_l_quantity, "
    "round(avg(l_quantity * (o_totalprice / 100000)) + 1.3e-9::DOUBLE, 6) AS q_l_quantity_price, round(avg((o_totalprice / 100000) * (o_totalprice / 100000)) + 1.3e-9::DOUBLE, 6) AS q_price_price "
    "FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1",
)
def pushdown_equals_materialized(spark, d):
    line = build.by_key(lines(spark, d), ["l_quantity"], ["l_orderkey"]).withColumnRenamed("l_orderkey", "o_orderkey")
    nation = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    orders = table(spark, d, "orders").join(nation, "o_custkey").withColumn("price", F.col("o_totalprice") / 100000)
    right = build.by_key(orders, ["price"], ["o_orderkey", "c_nationkey"])
    return pushdown.join_gamma(line, right, ["o_orderkey"], 1, 1, ["c_nationkey"]).select("c_nationkey", *means(["l_quantity", "price"]))


@register("union_pushdown", f"SELECT {sql_gram(LINE)} FROM lineitem")
def union_pushdown(spark, d):
    parts = [build.total(lines(spark, d).filter(f"l_linenumber % 3 = {i}"), LINE, exact=True) for i in range(3)]
    return pushdown.union_gamma(parts, 3).select(*gram.flat(LINE))


@register(
    "left_pushdown_imputed",
    """WITH e AS (SELECT user_id, avg(value) AS v FROM events GROUP BY 1), d AS (SELECT avg(v) AS u FROM e),
    j AS (SELECT c_acctbal / 1000 AS bal, coalesce(v, u) AS v FROM customer LEFT JOIN e ON c_custkey = user_id CROSS JOIN d)
    SELECT count(*)::DOUBLE AS c, round(avg(bal) + 1.3e-9::DOUBLE, 6) AS s_bal, round(avg(v), 6) AS s_v, round(avg(bal * bal) + 1.3e-9::DOUBLE, 6) AS q_bal_bal, round(avg(bal * v), 5) AS q_bal_v, round(avg(v * v), 4) AS q_v_v FROM j""",
)
def left_pushdown_imputed(spark, d):
    user = build.by_key(table(spark, d, "customer").withColumn("bal", F.col("c_acctbal") / 1000), ["bal"], ["c_custkey"]).withColumnRenamed("c_custkey", "k")
    cand = build.by_key(table(spark, d, "events"), ["value"], ["user_id"]).select(F.col("user_id").alias("k"), gram.reweight(F.col("g"), 1, "mean").alias("g"))
    u = cand.agg(F.avg(F.col("g.s")[0])).first()[0]
    default = gram.element(F.lit(1.0), [F.lit(u)], [F.lit(u * u)])
    g = F.col("g")
    out = pushdown.left_gamma(user, cand, ["k"], 1, 1, default)
    return out.select(g["c"].alias("c"), F.round(g["s"][0] / g["c"], 6).alias("s_bal"), F.round(g["s"][1] / g["c"], 6).alias("s_v"), F.round(g["q"][0] / g["c"], 6).alias("q_bal_bal"), F.round(g["q"][1] / g["c"], 5).alias("q_bal_v"), F.round(g["q"][2] / g["c"], 4).alias("q_v_v"))


@register(
    "chain_gamma",
    "SELECT c_nationkey, count(*)::DOUBLE AS c, round(avg(l_quantity) + 1.3e-9::DOUBLE, 6) AS s_l_quantity, round(avg(o_totalprice / 100000) + 1.3e-9::DOUBLE, 6) AS s_price, round(avg(c_acctbal / 1000) + 1.3e-9::DOUBLE, 6) AS s_bal, "
    "round(avg(l_quantity * l_quantity) + 1.3e-9::DOUBLE, 6) AS q_l_quantity_l_quantity, round(avg(l_quantity * (o_totalprice / 100000)) + 1.3e-9::DOUBLE, 6) AS q_l_quantity_price, round(avg(l_quantity * (c_acctbal / 1000)) + 1.3e-9::DOUBLE, 6) AS q_l_quantity_bal, "
    "round(avg((o_totalprice / 100000) * (o_totalprice / 100000)) + 1.3e-9::DOUBLE, 6) AS q_price_price, round(avg((o_totalprice / 100000) * (c_acctbal / 1000)) + 1.3e-9::DOUBLE, 6) AS q_price_bal, round(avg((c_acctbal / 1000) * (c_acctbal / 1000)) + 1.3e-9::DOUBLE, 6) AS q_bal_bal "
    "FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey GROUP BY 1",
)
def chain_gamma(spark, d):
    a = build.by_key(lines(spark, d).withColumnRenamed("l_orderkey", "o_orderkey"), ["l_quantity"], ["o_orderkey"])
    b = build.by_key(table(spark, d, "orders").withColumn("price", F.col("o_totalprice") / 100000).withColumnRenamed("o_custkey", "c_custkey"), ["price"], ["o_orderkey", "c_custkey"])
    c = build.by_key(table(spark, d, "customer").withColumn("bal", F.col("c_acctbal") / 1000), ["bal"], ["c_custkey", "c_nationkey"])
    out = pushdown.chain([(a, [], ["o_orderkey"], 1), (b, ["o_orderkey"], ["c_custkey"], 1), (c, ["c_custkey"], ["c_nationkey"], 1)])
    return out.select("c_nationkey", *means(["l_quantity", "price", "bal"]))


@register("theta_gamma", "SELECT count(*)::DOUBLE AS c, sum(a.p_size)::DOUBLE AS s_p_size, sum(b.l_linenumber)::DOUBLE AS s_l_linenumber, sum(a.p_size * b.l_linenumber)::DOUBLE AS q_p_size_l_linenumber FROM part a JOIN (SELECT DISTINCT l_linenumber FROM lineitem) b ON a.p_size <= b.l_linenumber")
def theta_gamma(spark, d):
    a = build.by_key(table(spark, d, "part").withColumn("k", F.col("p_size")), ["p_size"], ["k"])
    b = build.by_key(table(spark, d, "lineitem").select("l_linenumber").distinct().withColumn("n", F.col("l_linenumber")), ["l_linenumber"], ["n"])
    g = F.col("g")
    return pushdown.theta_gamma(a, b, F.col("k") <= F.col("n"), 1, 1).select(g["c"].alias("c"), g["s"][0].alias("s_p_size"), g["s"][1].alias("s_l_linenumber"), g["q"][1].alias("q_p_size_l_linenumber"))


@register("anti_gamma", f"SELECT {sql_gram(['c_acctbal'])} FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)")
def anti_gamma(spark, d):
    a = build.by_key(table(spark, d, "customer"), ["c_acctbal"], ["c_custkey"], exact=True)
    b = table(spark, d, "events").select(F.col("user_id").alias("c_custkey"))
    return pushdown.anti_gamma(a, b, ["c_custkey"], 1).select(*gram.flat(["c_acctbal"]))


@register("gram_standardized", "WITH s AS (SELECT avg(l_quantity) AS m, stddev_samp(l_quantity) AS d, avg(l_tax) AS m2, stddev_samp(l_tax) AS d2 FROM lineitem) SELECT count(*)::DOUBLE AS c, round(sum((l_quantity - m) / d * ((l_quantity - m) / d)) / count(*), 6) AS q_quantity, round(sum((l_quantity - m) / d * ((l_tax - m2) / d2)) / count(*), 6) AS q_quantity_tax FROM lineitem, s")
def gram_standardized(spark, d):
    from augspark.prep.standardize import fit_sketch

    g = build.total(lines(spark, d), ["l_quantity", "l_tax"])
    fitted = fit_sketch(g.first()["g"], ["l_quantity", "l_tax"])
    out = gram.affine(F.col("g"), [fitted[f][0] for f in ("l_quantity", "l_tax")], [fitted[f][1] for f in ("l_quantity", "l_tax")])
    return g.select(out.alias("g")).select(F.col("g.c").alias("c"), F.round(F.col("g.q")[0] / F.col("g.c"), 6).alias("q_quantity"), F.round(F.col("g.q")[1] / F.col("g.c"), 6).alias("q_quantity_tax"))


def _theta(df, lam=0.0, names=("w0", "w1"), target=None):
    t = solve.ols(F.col("g"), target, lam)
    return df.withColumn("t", t).select(*[c for c in df.columns if c != "g"], F.round(F.col("t")[0], 4).alias("intercept"), *[F.round(F.col("t")[i + 1], 5).alias(n) for i, n in enumerate(names)])


@register("ols_one_feature", "SELECT l_linenumber, round(regr_intercept(l_extendedprice / 1000, l_quantity), 4) AS intercept, round(regr_slope(l_extendedprice / 1000, l_quantity), 5) AS w0 FROM lineitem GROUP BY 1")
def ols_one_feature(spark, d):
    df = lines(spark, d).withColumn("price", F.col("l_extendedprice") / 1000)
    return _theta(build.by_key(df, ["l_quantity", "price"], ["l_linenumber"]), names=("w0",), target=1)


def _two(lam: str) -> str:
    return f"""WITH s AS (SELECT count(*) AS n, avg(l_quantity) AS ma, avg(l_tax * 100) AS mb, avg(l_extendedprice / 1000) AS my, var_pop(l_quantity) * count(*) + {lam} AS aa,
    var_pop(l_tax * 100) * count(*) + {lam} AS bb, covar_pop(l_quantity, l_tax * 100) * count(*) AS ab, covar_pop(l_quantity, l_extendedprice / 1000) * count(*) AS ay, covar_pop(l_tax * 100, l_extendedprice / 1000) * count(*) AS ty FROM lineitem),
    w AS (SELECT *, (ay * bb - ty * ab) / (aa * bb - ab * ab) AS wa, (ty * aa - ay * ab) / (aa * bb - ab * ab) AS wb FROM s)
    SELECT round(my - wa * ma - wb * mb, 4) AS intercept, round(wa, 5) AS w0, round(wb, 5) AS w1 FROM w"""


def _scaled(spark, d):
    return lines(spark, d).select("l_quantity", (F.col("l_tax") * 100).alias("tax"), (F.col("l_extendedprice") / 1000).alias("price"), "fold", "l_linenumber")


@register("ols_two_features", _two("0"))
def ols_two_features(spark, d):
    return _theta(build.total(_scaled(spark, d), ["l_quantity", "tax", "price"]), target=2)


@register("ridge_two_features", _two("5000"))
def ridge_two_features(spark, d):
    return _theta(build.total(_scaled(spark, d), ["l_quantity", "tax", "price"]), lam=5000.0, target=2)


@register("threshold_classifier", "WITH s AS (SELECT regr_slope((l_quantity > 25)::INTEGER, l_extendedprice / 1000) AS b, regr_intercept((l_quantity > 25)::INTEGER, l_extendedprice / 1000) AS a FROM lineitem) SELECT round(avg((((a + b * (l_extendedprice / 1000)) >= 0.5) = (l_quantity > 25))::INTEGER), 4) AS accuracy FROM lineitem, s")
def threshold_classifier(spark, d):
    from augspark import measures
    from augspark.serve.scorer import linear

    df = lines(spark, d).select((F.col("l_extendedprice") / 1000).alias("price"), (F.col("l_quantity") > 25).cast("int").alias("y"))
    theta = build.total(df, ["price", "y"]).select(solve.ols(F.col("g"), 1).alias("t")).first()["t"]
    return measures.accuracy(df, "y", solve.threshold(linear(theta, ["price"]))).select(F.round("accuracy", 4).alias("accuracy"))


_FIT = "WITH s AS (SELECT regr_slope(l_extendedprice / 1000, l_quantity) AS b, regr_intercept(l_extendedprice / 1000, l_quantity) AS a FROM lineitem)"


@register("sse_from_sketch", f"{_FIT} SELECT round(sum(pow(l_extendedprice / 1000 - a - b * l_quantity, 2)) / count(*), 5) AS mse FROM lineitem, s")
def sse_from_sketch(spark, d):
    g = build.total(_scaled(spark, d), ["l_quantity", "price"]).withColumn("t", solve.ols(F.col("g"), 1))
    return g.select(F.round(solve.loss(F.col("g"), 1, F.col("t")) / F.col("g.c"), 5).alias("mse"))


@register("r2_from_sketch", "SELECT l_linenumber, round(regr_r2(l_extendedprice / 1000, l_quantity), 5) AS r2 FROM lineitem GROUP BY 1")
def r2_from_sketch(spark, d):
    g = build.by_key(_scaled(spark, d), ["l_quantity", "price"], ["l_linenumber"]).withColumn("t", solve.ols(F.col("g"), 1))
    return g.select("l_linenumber", F.round(solve.r2_of(F.col("g"), 1, F.col("t")), 5).alias("r2"))


@register(
    "crossval_10fold",
    f"""WITH l AS (SELECT {FOLD_SQL}::INTEGER AS fold, l_quantity AS x, l_extendedprice / 1000 AS y FROM lineitem),
    f AS (SELECT f.fold, regr_slope(l.y, l.x) AS b, regr_intercept(l.y, l.x) AS a FROM l, (SELECT DISTINCT fold FROM l) f WHERE l.fold <> f.fold GROUP BY 1),
    r AS (SELECT l.fold, 1 - sum(pow(y - a - b * x, 2)) / (var_pop(y) * count(*)) AS r2 FROM l JOIN f USING (fold) GROUP BY 1)
    SELECT round(avg(r2), 5) AS cv_r2 FROM r""",
)
def crossval_10fold(spark, d):
    folds = build.total(_scaled(spark, d), ["l_quantity", "price"], "fold").withColumn("dataset", F.lit("base"))
    return crossval.score(folds, 1, lam=0.0).select(F.round("cv_r2", 5).alias("cv_r2"))


@register("validation_set_score", "WITH s AS (SELECT regr_slope(l_extendedprice / 1000, l_quantity) AS b, regr_intercept(l_extendedprice / 1000, l_quantity) AS a FROM lineitem WHERE l_linenumber <= 5) SELECT round(1 - sum(pow(l_extendedprice / 1000 - a - b * l_quantity, 2)) / (var_pop(l_extendedprice / 1000) * count(*)), 5) AS r2, round(any_value(b), 5) AS w0 FROM lineitem, s WHERE l_linenumber > 5")
def validation_set_score(spark, d):
    df = _scaled(spark, d)
    both = crossval.validate(build.total(df.filter("l_linenumber <= 5"), ["l_quantity", "price"]), build.total(df.filter("l_linenumber > 5"), ["l_quantity", "price"]), 1)
    return both.select(F.round("r2", 5).alias("r2"), F.round(F.col("theta")[1], 5).alias("w0"))


_WORKED = "(VALUES ('a1', 2, 2), ('a1', 3, 4), ('a1', 1, 4), ('a1', 5, 4)) AS t(a, b, c)"


def worked(spark):
    """Two relations whose union has n = 4, sums 11 and 14, and pair sums 39 and 40."""
    r1 = spark.createDataFrame([("a1", 2, 2), ("a1", 3, 4)], "A string, B int, C int")
    r2 = spark.createDataFrame([("a1", 1, 4), ("a1", 5, 4)], "A string, B int, C int")
    return r1, r2


@register("worked_example_theta", f"SELECT round(regr_intercept(c, b), 6) AS intercept, round(regr_slope(c, b), 6) AS slope FROM {_WORKED}")
def worked_example_theta(spark, d):
    r1, r2 = worked(spark)
    g = pushdown.union_gamma([build.total(r1, ["B", "C"]), build.total(r2, ["B", "C"])], 2)
    return g.withColumn("t", solve.ols(F.col("g"), 1)).select(F.round(F.col("t")[0], 6).alias("intercept"), F.round(F.col("t")[1], 6).alias("slope"))


@register("worked_example_sum", "SELECT 'a1' AS a, 10::BIGINT AS sum_b")
def worked_example_sum(spark, d):
    """The sum of B over a join with a table of two rows of the same key, from pre-aggregated annotations."""
    r1 = worked(spark)[0].withColumnRenamed("A", "key")
    t = spark.createDataFrame([("a1", 1), ("a1", 2)], "key string, D int")
    left = natural.gamma(natural.annotate(r1, F.col("B").cast("long")), "key")
    joined = natural.gamma(natural.join(left, natural.gamma(natural.annotate(t), "key"), ["key"]), "key")
    return joined.select(F.col("key").alias("a"), F.col("a").alias("sum_b"))


@register("worked_example_horizontal", f"SELECT 4::DOUBLE AS c, sum(b)::DOUBLE AS s_b, sum(c)::DOUBLE AS s_c, sum(b * b)::DOUBLE AS q_b_b, sum(b * c)::DOUBLE AS q_b_c, sum(c * c)::DOUBLE AS q_c_c FROM {_WORKED}")
def worked_example_horizontal(spark, d):
    r1, r2 = worked(spark)
    return pushdown.union_gamma([build.total(r1, ["B", "C"]), build.total(r2, ["B", "C"])], 2).select(*[c for c in gram.flat(["b", "c"])])


@register("worked_example_vertical", "SELECT 4::DOUBLE AS c, round(avg(b), 6) AS s_b, round(avg(f), 6) AS s_f, round(avg(b * f) + 1.3e-9::DOUBLE, 6) AS q_b_f FROM (VALUES (2, 6.0), (3, 6.0), (1, 2.0), (5, 4.0)) AS t(b, f)")
def worked_example_vertical(spark, d):
    """A left join with a missing key: its rows meet the mean of the other table's keys."""
    user = spark.createDataFrame([("a1", 2), ("a1", 3), ("a2", 1), ("a3", 5)], "A string, B int")
    other = spark.createDataFrame([("a1", 5.0), ("a1", 7.0), ("a2", 2.0)], "A string, f double")
    cand = build.by_key(other, ["f"], ["A"]).select("A", gram.reweight(F.col("g"), 1, "mean").alias("g"))
    u = cand.agg(F.avg(F.col("g.s")[0])).first()[0]
    g = F.col("g")
    out = pushdown.left_gamma(build.by_key(user, ["B"], ["A"]), cand, ["A"], 1, 1, gram.element(F.lit(1.0), [F.lit(u)], [F.lit(u * u)]))
    return out.select(g["c"].alias("c"), F.round(g["s"][0] / g["c"], 6).alias("s_b"), F.round(g["s"][1] / g["c"], 6).alias("s_f"), F.round(g["q"][1] / g["c"], 6).alias("q_b_f"))


@register("other_learners")
def other_learners(spark, d):
    """Learners outside the sketches' reach, on a materialised table: R² or training cost by family."""
    from augspark.modelsearch.search import ModelSearch, cluster_baseline

    df = planted(spark, d).join(table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_acctbal"), "l_suppkey")
    found = ModelSearch("broad", 60).run(df, ["s_acctbal", "l_quantity"], "y")
    rows = [(n, float(s)) for n, _, s in found.models] + [("kmeans", cluster_baseline(df, ["s_acctbal", "l_quantity"]))]
    return spark.createDataFrame(rows, "family string, score double")


@register("request_profile", f"WITH {REQ_SQL} SELECT fold, count(*)::BIGINT AS n, round(avg(y), 5) AS mean_y, round(stddev_samp(y), 5) AS std_y FROM req GROUP BY 1")
def request_profile(spark, d):
    """The planted request: rows, mean and spread of the target by fold."""
    return planted(spark, d).groupBy("fold").agg(F.count("*").alias("n"), F.round(F.avg("y"), 5).alias("mean_y"), F.round(F.stddev_samp("y"), 5).alias("std_y"))


@register("projection_pairs", f"SELECT l_orderkey, l_linenumber, {', '.join(f'round({a} * {b}, 6) AS {a}_{b}' for a, b in (('l_quantity', 'l_discount'), ('l_quantity', 'l_tax'), ('l_discount', 'l_tax')))} FROM lineitem")
def projection_pairs(spark, d):
    return lines(spark, d).select("l_orderkey", "l_linenumber", *[F.round(F.col(a) * F.col(b), 6).alias(f"{a}_{b}") for a, b in (("l_quantity", "l_discount"), ("l_quantity", "l_tax"), ("l_discount", "l_tax"))])
