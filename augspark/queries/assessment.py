"""Queries of candidate assessment: unions and joins of many candidates at once, their variants, and re-use."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from augspark import baselines
from augspark.assess import crossval, horizontal, reuse, solve, vertical
from augspark.cluster import table
from augspark.queries.common import FOLD_SQL, LINE, REQ_SQL, lines, means, planted, sql_gram, sql_means
from augspark.queries.registry import register
from augspark.ring import gram
from augspark.sketch import build

USER = ["l_quantity", "l_tax"]


def user_by(spark, d, key: str):
    df = lines(spark, d)
    return build.by_key(df, USER, [key], "fold").withColumnRenamed(key, "key"), build.total(df, USER, "fold")


def part_candidates(spark, d):
    """Three one-feature candidates on the part key: two dimension columns and a rollup."""
    part = table(spark, d, "part")
    rollup = table(spark, d, "lineitem").groupBy("l_partkey").agg(F.avg("l_discount").alias("x"))
    frames = {"size": part.select(F.col("p_partkey").alias("key"), F.col("p_size").cast("double").alias("x")), "price": part.select(F.col("p_partkey").alias("key"), (F.col("p_retailprice") / 1000).alias("x")), "discount": rollup.withColumnRenamed("l_partkey", "key")}
    out = None
    for name, df in frames.items():
        one = build.by_key(df, ["x"], ["key"]).withColumn("dataset", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


_PART = {
    "size": "SELECT p_partkey AS k, p_size::DOUBLE AS x FROM part",
    "price": "SELECT p_partkey AS k, p_retailprice / 1000 AS x FROM part",
    "discount": "SELECT l_partkey AS k, avg(l_discount) AS x FROM lineitem GROUP BY 1",
}


def joined_sql(candidates: dict[str, str], key: str, fill: str = "avg(x)", fold: bool = True, names=("l_quantity", "l_tax", "x")) -> str:
    """Each candidate's left join over rows, one row a key, missing keys filled."""
    parts = []
    for name, sql in candidates.items():
        body = f"SELECT l_quantity, l_tax, {FOLD_SQL}::INTEGER AS fold, coalesce(c.x, u) AS x FROM lineitem l LEFT JOIN ({sql}) c ON l.{key} = c.k CROSS JOIN (SELECT {fill} AS u FROM ({sql}))"
        parts.append(f"SELECT '{name}' AS dataset, {'fold, ' if fold else ''}{sql_means(list(names))} FROM ({body}) GROUP BY 1{', 2' if fold else ''}")
    return " UNION ALL ".join(parts)


NAMES = [*USER, "x"]


@register("vertical_batch", joined_sql(_PART, "l_partkey"))
def vertical_batch(spark, d):
    """All candidates of the part key, assessed together from sketches: each equals its materialised left join."""
    user, totals = user_by(spark, d, "l_partkey")
    return vertical.batch(user, part_candidates(spark, d), totals, 2, 1).select("dataset", "fold", *means(NAMES))


@register("online_factorized_gram", joined_sql({"size": _PART["size"]}, "l_partkey"))
def online_factorized_gram(spark, d):
    """The same measure with user and candidate aggregated anew for the candidate."""
    part = table(spark, d, "part").withColumn("x", F.col("p_size").cast("double"))
    return baselines.online_factorized(lines(spark, d), USER, "l_partkey", {"size": (part, "p_partkey", ["x"])}).select("dataset", "fold", *means(NAMES))


@register("vertical_materialized", joined_sql({"price": _PART["price"]}, "l_partkey"))
def vertical_materialized(spark, d):
    part = table(spark, d, "part").withColumn("x", F.col("p_retailprice") / 1000)
    g = baselines.materialised(lines(spark, d), "l_partkey", part, "p_partkey", ["x"], USER)
    return g.select(F.lit("price").alias("dataset"), "fold", *means(NAMES))


def _events(spark, d):
    """Candidates keyed by user_id, with several rows a key; most orders' customers have none."""
    e = table(spark, d, "events").select(F.col("user_id").alias("key"), (F.col("value") / 100).alias("x"))
    return build.by_key(e, ["x"], ["key"]).withColumn("dataset", F.lit("events"))


def _customers(spark, d):
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("key"), (F.col("c_acctbal") / 1000).alias("bal"), (F.col("c_nationkey") * 1.0).alias("nation"), (F.col("c_custkey") % 5).cast("int").alias("fold"))
    return build.by_key(c, ["bal", "nation"], ["key"], "fold"), build.total(c, ["bal", "nation"], "fold")


_ROWS = "SELECT c_acctbal / 1000 AS bal, c_nationkey * 1.0::DOUBLE AS nation, (c_custkey % 5)::INTEGER AS fold, c_custkey AS k FROM customer"
_KEYS = "SELECT user_id AS k, count(*) AS n, avg(value / 100) AS x, avg(value / 100 * (value / 100)) AS v FROM events GROUP BY 1"
CNAMES = ["bal", "nation", "x"]


def _events_sql(fill: str = "avg(x)", pair: str = "coalesce(v, u * u)", weight: str = "1") -> str:
    body = f"SELECT bal, nation, fold, coalesce(x, u) AS x, coalesce(v, u * u) AS v, u, coalesce(n, 1) AS n FROM ({_ROWS}) r LEFT JOIN ({_KEYS}) e USING (k) CROSS JOIN (SELECT {fill} AS u FROM ({_KEYS}))"
    return f"SELECT fold, {sql_means(CNAMES, weight, terms={('x', 'x'): pair})} FROM ({body}) GROUP BY 1"


def _vertical_events(spark, d, mode="weight", impute="mean"):
    user, totals = _customers(spark, d)
    return vertical.batch(user, _events(spark, d), totals, 2, 1, mode, impute).select("fold", *means(CNAMES))


@register("vertical_left_missing", _events_sql())
def vertical_left_missing(spark, d):
    """Nine of ten rows have no partner: they come from totals minus matched sums."""
    return _vertical_events(spark, d)


@register("vertical_impute_mean", _events_sql("avg(x)", "x * x"))
def vertical_impute_mean(spark, d):
    return _vertical_events(spark, d, "mean", "mean")


@register("vertical_impute_zero", _events_sql("max(0.0::DOUBLE)", "x * x"))
def vertical_impute_zero(spark, d):
    return _vertical_events(spark, d, "mean", "zero")


@register("vertical_impute_median", _events_sql("median(x)", "x * x"))
def vertical_impute_median(spark, d):
    return _vertical_events(spark, d, "mean", "median")


_COUNTS = "SELECT user_id AS k, count(*)::DOUBLE AS x FROM events GROUP BY 1"
_MODE = f"(SELECT x AS u FROM ({_COUNTS}) GROUP BY x ORDER BY count(*) DESC, x LIMIT 1)"


def _fill_sql(fill: str) -> str:
    return f"SELECT fold, {sql_means(CNAMES)} FROM (SELECT bal, nation, fold, coalesce(x, u) AS x FROM ({_ROWS}) r LEFT JOIN ({_COUNTS}) e USING (k) CROSS JOIN {fill}) GROUP BY 1"


def _vertical_counts(spark, d, impute):
    user, totals = _customers(spark, d)
    counts = table(spark, d, "events").groupBy(F.col("user_id").alias("key")).agg(F.count("*").cast("double").alias("x"))
    cand = build.by_key(counts, ["x"], ["key"]).withColumn("dataset", F.lit("counts"))
    return vertical.batch(user, cand, totals, 2, 1, "weight", impute).select("fold", *means(CNAMES))


@register("vertical_impute_mode", _fill_sql(_MODE))
def vertical_impute_mode(spark, d):
    """Rows without partner meet the commonest value of the other table's keys, the smallest on ties."""
    return _vertical_counts(spark, d, "mode")


@register("vertical_impute_constant", _fill_sql("(SELECT 2.5::DOUBLE AS u)"))
def vertical_impute_constant(spark, d):
    return _vertical_counts(spark, d, 2.5)


@register("vertical_raw_fanout", _events_sql("avg(x)", "v", "n"))
def vertical_raw_fanout(spark, d):
    """Join multiplicity kept: a row with n partners counts n times."""
    return _vertical_events(spark, d, "raw")


@register("reweight_by_key", "SELECT user_id, 1.0::DOUBLE AS c, round(avg(value), 5) AS s_value, round(avg(value * value), 3) AS q_value FROM events GROUP BY 1")
def reweight_by_key(spark, d):
    g = build.by_key(table(spark, d, "events"), ["value"], ["user_id"]).select("user_id", gram.reweight(F.col("g"), 1).alias("g"))
    return g.select("user_id", F.col("g.c").alias("c"), F.round(F.col("g.s")[0], 5).alias("s_value"), F.round(F.col("g.q")[0], 3).alias("q_value"))


@register(
    "vertical_two_keys",
    f"WITH c AS (SELECT l_suppkey AS a, l_linenumber AS b, avg(l_discount) AS x FROM lineitem WHERE l_linenumber <= 5 GROUP BY 1, 2), u AS (SELECT avg(x) AS u FROM c) SELECT fold, {sql_means(NAMES)} FROM (SELECT l_quantity, l_tax, {FOLD_SQL}::INTEGER AS fold, coalesce(x, u) AS x FROM lineitem LEFT JOIN c ON l_suppkey = a AND l_linenumber = b CROSS JOIN u) GROUP BY 1",
)
def vertical_two_keys(spark, d):
    df = lines(spark, d)
    keys = ["l_suppkey", "l_linenumber"]
    cand = df.filter("l_linenumber <= 5").groupBy(*keys).agg(F.avg("l_discount").alias("x"))
    cand = build.by_key(cand, ["x"], keys).withColumn("dataset", F.lit("pairs"))
    out = vertical.batch(build.by_key(df, USER, keys, "fold"), cand, build.total(df, USER, "fold"), 2, 1, keys=keys)
    return out.select("fold", *means(NAMES))


@register(
    "horizontal_batch",
    " UNION ALL ".join(
        f"SELECT '{n}' AS dataset, fold, {sql_gram(LINE)} FROM (SELECT *, {f} AS fold FROM lineitem WHERE {c}) GROUP BY 2"
        for n in ("late", "middle")
        for f, c in ((f"{FOLD_SQL}::INTEGER", "l_linenumber <= 2"), ("-1", "l_linenumber >= 5" if n == "late" else "l_linenumber IN (3, 4)"))
    ),
)
def horizontal_batch(spark, d):
    """Unions of a request with two stored tables: added rows carry fold -1, so they train every fold and validate none."""
    df = lines(spark, d)
    user = build.total(df.filter("l_linenumber <= 2"), LINE, "fold", exact=True)
    slices = {"late": "l_linenumber >= 5", "middle": "l_linenumber in (3, 4)"}
    stored = [build.total(df.filter(c), LINE, exact=True).withColumn("dataset", F.lit(n)) for n, c in slices.items()]
    return horizontal.batch(user, stored[0].unionByName(stored[1])).select("dataset", "fold", *gram.flat(LINE))


@register(
    "round_sketches",
    f"SELECT '*' AS key_name, NULL AS key_value, {FOLD_SQL}::INTEGER AS fold, {sql_gram(LINE)} FROM lineitem GROUP BY 3 UNION ALL SELECT 'l_suppkey', l_suppkey::VARCHAR, {FOLD_SQL}::INTEGER, {sql_gram(LINE)} FROM lineitem GROUP BY 2, 3 "
    f"UNION ALL SELECT 'l_linenumber', l_linenumber::VARCHAR, {FOLD_SQL}::INTEGER, {sql_gram(LINE)} FROM lineitem GROUP BY 2, 3",
)
def round_sketches(spark, d):
    """Every sketch of a round, overall and by two keys, in one grouping-sets pass."""
    return build.round_sketches(lines(spark, d), LINE, ["l_suppkey", "l_linenumber"], exact=True).select("key_name", "key_value", "fold", *gram.flat(LINE))


_CHAIN = "FROM (SELECT l_partkey AS a, l_orderkey AS b, l_quantity FROM lineitem) r JOIN (SELECT o_orderkey AS b, o_custkey AS c, o_totalprice / 100000 AS price FROM orders) s USING (b) JOIN (SELECT c_custkey AS c, c_nationkey AS n, c_acctbal / 1000 AS bal FROM customer) t USING (c)"
CHAIN = ["l_quantity", "price", "bal"]


def chain_tables(spark, d):
    r = table(spark, d, "lineitem").select(F.col("l_partkey").alias("a"), F.col("l_orderkey").alias("b"), "l_quantity")
    s = table(spark, d, "orders").select(F.col("o_orderkey").alias("b"), F.col("o_custkey").alias("c"), (F.col("o_totalprice") / 100000).alias("price"))
    t = table(spark, d, "customer").select(F.col("c_custkey").alias("c"), F.col("c_nationkey").alias("n"), (F.col("c_acctbal") / 1000).alias("bal"))
    return r, s, t


def chain_by(spark, d, key: str):
    """The three-table plan's sketch by a key, re-using the sketch of the first two tables by c (and the key)."""
    r, s, t = chain_tables(spark, d)
    keep = [key] if key in ("a", "b") else []
    rb = build.by_key(r, ["l_quantity"], ["b", *(["a"] if key == "a" else [])])
    two = reuse.extend(rb, build.by_key(s, ["price"], ["b", "c"]), ["b"], list(dict.fromkeys(["c", *keep])), 1, 1)
    return reuse.extend(two, build.by_key(t, ["bal"], ["c", *(["n"] if key == "n" else [])]), ["c"], [key], 2, 1)


def _share(key):
    return register(f"bench_share_{ {'a': 'A', 'b': 'B', 'c': 'C', 'n': 'D'}[key] }", f"SELECT {key} AS key, {sql_means(CHAIN)} {_CHAIN} GROUP BY 1")


for _key in ("a", "b", "c", "n"):
    _share(_key)(lambda spark, d, _key=_key: chain_by(spark, d, _key).select(F.col(_key).alias("key"), *means(CHAIN)))


_HALF = "(SELECT o_orderkey, o_custkey, o_totalprice / 100000 AS price FROM orders WHERE o_orderkey % 3 <> 0)"
_LEFT = f"FROM lineitem LEFT JOIN {_HALF} o ON l_orderkey = o_orderkey CROSS JOIN (SELECT avg(price) AS u FROM {_HALF})"


def left_extended(spark, d, by: str):
    """Lines joined left to two thirds of the orders, from sketches, by a key of the lines or one that arrives with orders."""
    o = table(spark, d, "orders").filter("o_orderkey % 3 <> 0").select(F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("c"), (F.col("o_totalprice") / 100000).alias("price"))
    u = o.agg(F.avg("price")).first()[0]
    plan = build.by_key(lines(spark, d), ["l_quantity"], ["l_orderkey", *([by] if by != "c" else [])])
    added = build.by_key(o, ["price"], ["l_orderkey", *(["c"] if by == "c" else [])])
    return reuse.extend_left(plan, added, ["l_orderkey"], [by], 1, 1, reuse.constant([u]))


@register("reuse_left_missing", f"SELECT l_suppkey, {sql_means(['l_quantity', 'price'])} FROM (SELECT l_suppkey, l_quantity, coalesce(price, u) AS price {_LEFT}) GROUP BY 1")
def reuse_left_missing(spark, d):
    """A key of the plan: rows without partner keep their place and meet the mean of the other table's keys."""
    return left_extended(spark, d, "l_suppkey").select("l_suppkey", *means(["l_quantity", "price"]))


@register("reuse_new_key", f"SELECT o_custkey AS n, {sql_means(['l_quantity', 'price'])} FROM (SELECT o_custkey, l_quantity, price {_LEFT} WHERE price IS NOT NULL) GROUP BY 1")
def reuse_new_key(spark, d):
    """A key that arrives with the joined table: only its composite sketch is needed, and unmatched rows have no such key."""
    return left_extended(spark, d, "c").select(F.col("c").alias("n"), *means(["l_quantity", "price"]))


@register("reuse_old_key", f"SELECT l_linenumber, {sql_means(['l_quantity', 'price'])} FROM (SELECT l_linenumber, l_quantity, coalesce(price, u) AS price {_LEFT}) GROUP BY 1")
def reuse_old_key(spark, d):
    """A key of few values: the plan's composite sketch by it and the join key is extended."""
    return left_extended(spark, d, "l_linenumber").select("l_linenumber", *means(["l_quantity", "price"]))


@register("incremental_equals_full")
def incremental_equals_full(spark, d):
    """Growing an inverse by one feature gives the model of a full solve: largest difference of parameters by added feature."""
    df = lines(spark, d)
    g = build.total(df, [*LINE, "l_extendedprice"]).first()["g"]
    whole = solve.matrix(g["c"], g["s"], g["q"])
    rows, inverse = [], np.linalg.inv(whole[:2, :2])
    for n in (2, 3):
        inverse = solve.extend_inverse(inverse, whole[:n, n], whole[n, n])
        grown, full = inverse @ whole[: n + 1, 4], np.linalg.solve(whole[: n + 1, : n + 1], whole[: n + 1, 4])
        rows.append((n, float(np.abs(grown - full).max() / np.abs(full).max())))
    return spark.createDataFrame(rows, "features int, difference double")


@register(
    "brute_force_r2",
    f"WITH {REQ_SQL} " + " UNION ALL ".join(f"SELECT '{n}' AS dataset, round(regr_r2(y, x), 5) AS r2 FROM (SELECT y, {x} AS x FROM req JOIN {t} ON {k})" for n, t, k, x in (("part", "part", "l_partkey = p_partkey", "p_retailprice"), ("supplier", "supplier", "l_suppkey = s_suppkey", "s_acctbal"), ("orders", "orders", "l_orderkey = o_orderkey", "o_totalprice"))),
)
def brute_force_r2(spark, d):
    """Materialise and retrain for each candidate: what the proxy must equal."""
    req, out = planted(spark, d), None
    for name, t, key, own, feature in (("part", "part", "l_partkey", "p_partkey", "p_retailprice"), ("supplier", "supplier", "l_suppkey", "s_suppkey", "s_acctbal"), ("orders", "orders", "l_orderkey", "o_orderkey", "o_totalprice")):
        joined = req.join(table(spark, d, t).select(F.col(own).alias(key), feature), key)
        one = joined.agg(F.round(F.regr_r2("y", feature), 5).alias("r2")).select(F.lit(name).alias("dataset"), "r2")
        out = one if out is None else out.unionByName(one)
    return out


@register(
    "proxy_r2",
    f"WITH {REQ_SQL} " + " UNION ALL ".join(f"SELECT '{n}' AS dataset, round(regr_r2(y, x), 5) AS r2 FROM (SELECT y, {x} AS x FROM req JOIN {t} ON {k})" for n, t, k, x in (("part", "part", "l_partkey = p_partkey", "p_retailprice"), ("supplier", "supplier", "l_suppkey = s_suppkey", "s_acctbal"))),
)
def proxy_r2(spark, d):
    """The same fits from sketches alone."""
    req, out = planted(spark, d), None
    for name, t, key, own, feature in (("part", "part", "l_partkey", "p_partkey", "p_retailprice"), ("supplier", "supplier", "l_suppkey", "s_suppkey", "s_acctbal")):
        user = build.by_key(req, ["y"], [key]).withColumnRenamed(key, "key").withColumn("fold", F.lit(0))
        cand = build.by_key(table(spark, d, t), [feature], [own]).withColumnRenamed(own, "key").withColumn("dataset", F.lit(name))
        g = vertical.batch(user, cand, build.total(req, ["y"]).withColumn("fold", F.lit(0)), 1, 1).withColumn("t", solve.ols(F.col("g"), 0))
        one = g.select("dataset", F.round(solve.r2_of(F.col("g"), 0, F.col("t")), 5).alias("r2"))
        out = one if out is None else out.unionByName(one)
    return out


@register("crossval_of_candidates")
def crossval_of_candidates(spark, d):
    """Cross-validated score and parameters of every part-key candidate for predicting tax, from one batch."""
    user, totals = user_by(spark, d, "l_partkey")
    return crossval.score(vertical.batch(user, part_candidates(spark, d), totals, 2, 1), 1)
