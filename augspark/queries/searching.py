"""Queries of search, budget, release labels, cache, maintenance and serving."""

from __future__ import annotations

from dataclasses import replace
from pyspark.sql import Window
from pyspark.sql import functions as F

from augspark import catalog as cat
from augspark.cluster import table
from augspark.queries.common import LINE, REQ_SQL, TIE, Y_SQL, cv_sql, greedy_sql, lines, planted, sql_gram
from augspark.queries.registry import register
from augspark.ring import gram
from augspark.search import shape
from augspark.search.cache import PlanCache
from augspark.search.engine import ORDERS, Search
from augspark.search.request import Request, Step
from augspark.sketch import build, maintain

KEYS = {"l_partkey": "partkey", "l_suppkey": "suppkey", "l_orderkey": "orderkey"}


def corpus(spark, d, extra: bool = True, supplier: str = "RAW", index=None) -> cat.Corpus:
    """Dimension tables as join candidates, with decoys."""
    c = cat.Corpus(spark, index)
    c.upload(table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), "p_retailprice"), "part", "RAW", ["partkey"], ["p_retailprice"])
    c.upload(table(spark, d, "supplier").select(F.col("s_suppkey").alias("suppkey"), "s_acctbal"), "supplier", supplier, ["suppkey"], ["s_acctbal"])
    c.upload(table(spark, d, "orders").select(F.col("o_orderkey").alias("orderkey"), "o_totalprice"), "orders", "RAW", ["orderkey"], ["o_totalprice"])
    if extra:
        c.upload(table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), F.col("p_size").cast("double").alias("p_size")), "size", "API", ["partkey"], ["p_size"])
    return c


def request(spark, d, **how) -> Request:
    return Request(planted(spark, d), LINE, "y", KEYS, **how)


def service(spark, d, **how):
    """The whole request path over the corpus, with discovery and a plan cache."""
    from augspark.profile.index import ProfileIndex
    from augspark.serve.service import Service

    index = ProfileIndex(spark)
    return Service(corpus(spark, d, index=index), cache=PlanCache(), discovery=index, **how)


def timings_model(spark):
    """A cost model from timings that grow with the number of cells."""
    from augspark.search.cost import CostModel

    shapes = [(r, c) for r in (100, 1000, 10_000, 100_000, 1_000_000) for c in (2, 5, 10, 20)]
    return CostModel(spark.createDataFrame([("linear", r, c, 0.01 + r * c * 1e-6) for r, c in shapes], "family string, rows long, cols int, seconds double"))


XS = {"part": "p_retailprice", "supplier": "s_acctbal", "orders": "o_totalprice"}
_BASE = "SELECT fold, y / 1000 AS y, l_quantity, l_discount, l_tax, p_retailprice / 1000 AS part, s_acctbal / 1000 AS supplier, o_totalprice / 100000 AS orders FROM req JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey"
TRACE_SQL = greedy_sql(_BASE, LINE, {n: [n] for n in XS}, extra=REQ_SQL)


def _cv_sql(name: str, sets: dict[str, list[str]]) -> str:
    return f"{REQ_SQL}, {cv_sql(_BASE, sets, name=name)}"


def answer(spark, d, **how):
    c = corpus(spark, d)
    return c, Search(c, **how).run(request(spark, d))


def traced(spark, a):
    """(step, dataset, cv_r2) of an answer, from the model without augmentation on."""
    rows = [(0, "-", a.base_r2), *((i, s.dataset, s.cv_r2) for i, s in enumerate(a.plan, 1))]
    return spark.createDataFrame([(i, n, float(r)) for i, n, r in rows], "step int, dataset string, r double").select("step", "dataset", F.round("r", 4).alias("cv_r2"))


@register("greedy_plan_trace", TRACE_SQL)
def greedy_plan_trace(spark, d):
    """The planted search: three joins in the order of their gain, decoys never, a stop at a small gain."""
    return traced(spark, answer(spark, d)[1])


@register("search_mean_mode", TRACE_SQL)
def search_mean_mode(spark, d):
    """The same with partners replaced by their mean, and without standardising."""
    return traced(spark, answer(spark, d, mode="mean", standardise=False)[1])


@register("search_online", TRACE_SQL)
def search_online(spark, d):
    """The same search from base rows: no stored sketch is read when candidates are scored."""
    return traced(spark, answer(spark, d, online=True)[1])


@register("search_pair_sketches", TRACE_SQL)
def search_pair_sketches(spark, d):
    """The same where sketches by pairs of keys are kept whatever their size, so the first join rescans no row."""
    return traced(spark, answer(spark, d, pair_share=1.0)[1])


@register("search_sketch_only", TRACE_SQL)
def search_sketch_only(spark, d):
    """The same where one table is known by its provider's sketches alone, under a name with a colon."""
    c = corpus(spark, d)
    supplier = table(spark, d, "supplier").select(F.col("s_suppkey").alias("suppkey"), "s_acctbal")
    del c.datasets["supplier"]
    c.upload_sketch("supplier", "RAW", build.total(supplier, ["s_acctbal"]), {"suppkey": build.by_key(supplier, ["s_acctbal"], ["suppkey"])}, ["s_acctbal"], supplier.count())
    return traced(spark, Search(c).run(request(spark, d)))


@register("search_discovered", TRACE_SQL)
def search_discovered(spark, d):
    """The same with candidates from the discovery index: the request names its own columns only."""
    from augspark.profile.index import ProfileIndex

    index = ProfileIndex(spark)
    c = corpus(spark, d, index=index)
    return traced(spark, Search(c, discovery=index).run(replace(request(spark, d), keys=dict.fromkeys(KEYS))))


_HOPS = "SELECT ((l_orderkey + 3 * l_linenumber) % 10)::INTEGER AS fold, (0.002::DOUBLE * o_totalprice + 0.1::DOUBLE * c_acctbal) / 1000 AS y, l_quantity, o_totalprice / 100000 AS orders, c_acctbal / 1000 AS customer FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"


@register("search_carried_key", f"WITH {cv_sql(_HOPS, {'-': ['l_quantity'], 'orders': ['l_quantity', 'orders'], 'customer': ['l_quantity', 'orders', 'customer']})} SELECT CASE dataset WHEN '-' THEN 0 WHEN 'orders' THEN 1 ELSE 2 END AS step, dataset, round(cv_r2, 4) AS cv_r2 FROM r")
def search_carried_key(spark, d):
    """A second join on a key that the first one brings: the customer key arrives with orders."""
    o, cu = table(spark, d, "orders"), table(spark, d, "customer")
    rows = lines(spark, d).join(o.select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_totalprice"), "l_orderkey").join(cu.select(F.col("c_custkey").alias("o_custkey"), "c_acctbal"), "o_custkey")
    rows = rows.select("l_orderkey", "l_quantity", "fold", (F.lit(0.002) * F.col("o_totalprice") + F.lit(0.1) * F.col("c_acctbal")).alias("y"))
    c = cat.Corpus(spark)
    c.upload(o.select(F.col("o_orderkey").alias("orderkey"), F.col("o_custkey").alias("custkey"), "o_totalprice"), "orders", "RAW", ["orderkey", "custkey"], ["o_totalprice"])
    c.upload(cu.select(F.col("c_custkey").alias("custkey"), "c_acctbal"), "customer", "RAW", ["custkey"], ["c_acctbal"])
    return traced(spark, Search(c).run(Request(rows, ["l_quantity"], "y", {"l_orderkey": "orderkey"})))


@register("search_validation_set", "WITH req AS (SELECT l_quantity, l_discount, l_tax, l_linenumber, " + Y_SQL + " AS y FROM lineitem JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey), m AS (SELECT regr_slope(y, l_quantity) AS b, regr_intercept(y, l_quantity) AS a FROM req WHERE l_linenumber <= 4) SELECT round(1 - sum(pow(y - a - b * l_quantity, 2)) / (var_pop(y) * count(*)), 4) AS r2 FROM req, m WHERE l_linenumber > 4")
def search_validation_set(spark, d):
    """A request with its own validation rows: the model without augmentation is scored on them alone."""
    rows = planted(spark, d)
    req = Request(rows.filter("l_linenumber <= 4"), ["l_quantity"], "y", {}, validation=rows.filter("l_linenumber > 4"))
    a = Search(cat.Corpus(spark)).run(req)
    return spark.createDataFrame([(float(a.base_r2),)], "r double").select(F.round("r", 4).alias("r2"))


@register("answer_request_linear", TRACE_SQL)
def answer_request_linear(spark, d):
    """A whole linear request: profile, discovery, cache trial, search, response by labels."""
    return traced(spark, service(spark, d).answer(request(spark, d, returns=("RAW",))).answer)


@register("answer_request_scores", f"WITH {REQ_SQL} SELECT l_orderkey, l_linenumber, l_partkey, round(y, 5) AS prediction FROM req")
def answer_request_scores(spark, d):
    """The prediction API of a linear request, on rows without augmentation: the planted target, which it reaches exactly."""
    api = service(spark, d).answer(request(spark, d, returns=("RAW", "API"))).api
    return api.score(planted(spark, d).drop("y")).select("l_orderkey", "l_linenumber", "l_partkey", F.round("prediction", 5).alias("prediction"))


@register("answer_request_any")
def answer_request_any(spark, d):
    """A request for any model: search, the plan's rows, model search in the time left, and its score on held-out rows."""
    from augspark import measures, workloads

    train, test = workloads.split(planted(spark, d).drop("l_linenumber"))
    r = service(spark, d, final="trees", cost=timings_model(spark)).answer(replace(request(spark, d, model="any", returns=("RAW", "API"), budget_s=20.0), train=train))
    score = measures.r2(r.api.score(test), "y", "prediction").first()["r2"]
    return spark.createDataFrame([("+".join(sorted(s.dataset for s in r.plan)), type(r.api).__name__, float(score), r.search_s, r.model_s)], "plan string, api string, r2 double, search_s double, model_s double")


@register("answer_by_labels", "SELECT * FROM (VALUES ('RAW', 3, false, false), ('MD', 0, true, false), ('API', 0, false, true), ('RAW+API', 3, false, true)) AS t(returns, steps, model, api)")
def answer_by_labels(spark, d):
    """What is returned by return labels; without raw data no join is allowed, so only the proxy without plan remains."""
    s, rows = service(spark, d), []
    for returns in (("RAW",), ("MD",), ("API",), ("RAW", "API")):
        r = s.answer(request(spark, d, returns=returns))
        rows.append(("+".join(returns), len(r.plan), r.model is not None, r.api is not None))
    return spark.createDataFrame(rows, "returns string, steps int, model boolean, api boolean")


@register("search_trace")
def search_trace(spark, d):
    """Score of the plan over time."""
    from augspark.search.request import trace_table

    return trace_table(spark, answer(spark, d)[1])


@register("plan_report", f"WITH {_cv_sql('r', {'part': [*LINE, 'part'], 'orders': [*LINE, 'orders']})} SELECT (row_number() OVER (ORDER BY cv_r2 DESC))::INTEGER AS step, 'vertical' AS kind, dataset, CASE dataset WHEN 'part' THEN 'l_partkey' ELSE 'l_orderkey' END AS key, 'RAW' AS label FROM r")
def plan_report(spark, d):
    """The report of a request that may use raw data only: tables with a stricter label are never offered."""
    from augspark.serve.response import report

    c = corpus(spark, d, supplier="MD")
    a = Search(c).run(request(spark, d, returns=("RAW",)))
    return report(spark, a, c).select("step", "kind", "dataset", "key", "label")


@register("order_rule", "SELECT * FROM (VALUES ('horizontal_first', 'late', 'horizontal', 1), ('horizontal_first', 'part', 'vertical', 1), ('unions_alone', 'late', 'horizontal', 1), ('any', 'late', 'horizontal', 1), ('any', 'part', 'vertical', 1)) AS t(rule, dataset, kind, round)")
def order_rule(spark, d):
    """Kinds offered by round under each rule, for a request that can union and join: round 2 comes after a join."""
    df = lines(spark, d).withColumn("y", F.col("l_extendedprice") / 1000)
    c = cat.Corpus(spark)
    c.upload(df.filter("l_linenumber >= 5").select("l_quantity", "y"), "late", "RAW", (), ["l_quantity", "y"])
    c.upload(table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), "p_retailprice"), "part", "RAW", ["partkey"], ["p_retailprice"])
    req, rows = Request(df.filter("l_linenumber <= 2"), ["l_quantity"], "y", {"l_partkey": "partkey"}), []
    for rule in ORDERS:
        s = Search(c, order=rule)
        plan = s.open(req)
        some = s.candidates(req, plan)
        rows += [(rule, x.dataset.name, x.kind, 1) for x in some]
        joined = [x for x in some if x.kind == "vertical"][:1]
        if joined:
            after = s.extend(plan, joined[0])
            after.steps = [joined[0].step(0.0, 0.0)]
            rows += [(rule, x.dataset.name, x.kind, 2) for x in s.candidates(req, after)]
    return spark.createDataFrame(rows, "rule string, dataset string, kind string, round int")


_RETURNS = {"raw": ["RAW"], "md": ["MD"], "api": ["API"], "raw_md": ["RAW", "MD"], "md_api": ["MD", "API"]}


@register("release_filter", " UNION ALL ".join(f"SELECT '{n}' AS returns, c_custkey AS dataset FROM customer WHERE c_nationkey % 3 <= {min(cat.LABELS[x] for x in r)}" for n, r in _RETURNS.items()))
def release_filter(spark, d):
    """Datasets usable by return labels, of a catalog with a dataset a customer, labelled by nation."""
    c, out = table(spark, d, "customer").select(F.col("c_custkey").alias("dataset"), (F.col("c_nationkey") % 3).alias("label")), None
    for name, returns in _RETURNS.items():
        one = cat.release_filter(c, returns).select(F.lit(name).alias("returns"), "dataset")
        out = one if out is None else out.unionByName(one)
    return out


_SUBSETS = {i: [x for bit, x in enumerate(cat.LABELS) if i >> bit & 1] for i in range(1, 8)}


@register("release_kind_rule", "SELECT '+' || returns AS returns, api_may_join, joins, count(*)::BIGINT AS requests FROM (SELECT CASE WHEN k % 2 = 1 THEN 'RAW+' ELSE '' END || CASE WHEN k // 2 % 2 = 1 THEN 'MD+' ELSE '' END || CASE WHEN k >= 4 THEN 'API+' ELSE '' END AS returns, f AS api_may_join, k % 2 = 1 OR (k = 4 AND f) AS joins FROM (SELECT o_orderkey % 7 + 1 AS k, o_custkey % 2 = 1 AS f FROM orders)) GROUP BY ALL")
def release_kind_rule(spark, d):
    """Requests by return labels, the option that an API request may join, and whether they may; an order is a request."""
    returns = F.element_at(F.array(*[F.array(*map(F.lit, x)) for x in _SUBSETS.values()]), (F.col("o_orderkey") % 7 + 1).cast("int"))
    rows = table(spark, d, "orders").select(returns.alias("returns"), (F.col("o_custkey") % 2 == 1).alias("api_may_join"))
    rows = rows.withColumn("joins", cat.joins_allowed(F.col("returns"), F.col("api_may_join")))
    text = F.concat(F.lit("+"), F.array_join("returns", "+"), F.lit("+"))
    return rows.groupBy(text.alias("returns"), "api_may_join", "joins").agg(F.count("*").alias("requests"))


@register("shape_estimate", "SELECT 'events' AS dataset, 'raw' AS mode, (SELECT count(*) FROM customer LEFT JOIN events ON c_custkey = user_id)::BIGINT AS rows, 3::INTEGER AS cols UNION ALL SELECT 'events', 'weight', (SELECT count(*) FROM customer)::BIGINT, 3")
def shape_estimate(spark, d):
    """Rows and columns of a join from key counts alone."""
    user = table(spark, d, "customer").groupBy(F.col("c_custkey").alias("key")).agg(F.count("*").alias("c"))
    cand = table(spark, d, "events").groupBy(F.col("user_id").alias("key")).agg(F.count("*").alias("c")).withColumns({"dataset": F.lit("events"), "p": F.lit(1)})
    out = [shape.estimate(user, cand, ["key"], 2, m).withColumn("mode", F.lit(m)) for m in ("raw", "weight")]
    return out[0].unionByName(out[1]).select("dataset", "mode", "rows", "cols")


@register("budget_filter", "SELECT 'orders' AS dataset, 'weight' AS mode, (SELECT count(*) FROM lineitem)::BIGINT AS rows, 6 AS cols, true AS fits UNION ALL SELECT 'lines', 'weight', (SELECT sum(n * n) FROM (SELECT count(*) AS n FROM lineitem GROUP BY l_orderkey))::BIGINT, 5, false UNION ALL SELECT 'orders', 'mean', (SELECT count(*) FROM lineitem)::BIGINT, 6, true UNION ALL SELECT 'lines', 'mean', (SELECT count(*) FROM lineitem)::BIGINT, 5, true")
def budget_filter(spark, d):
    """Candidates by the shape of their training table, taken from sketches, and whether its predicted training fits.

    The cost model is fitted on timings of one cell a second, and the time left is that of six cells a row.
    """
    from augspark.search.cost import CostModel

    c = cat.Corpus(spark)
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("orderkey"), "o_totalprice", F.col("o_custkey").cast("double").alias("cust"))
    c.upload(o, "orders", "RAW", ["orderkey"], ["o_totalprice", "cust"])
    c.upload(table(spark, d, "lineitem").select(F.col("l_orderkey").alias("orderkey"), "l_tax"), "lines", "RAW", ["orderkey"], ["l_tax"])
    rows = lines(spark, d).withColumn("y", F.col("l_extendedprice"))
    req, n, out = Request(rows, LINE, "y", {"l_orderkey": "orderkey"}, model="any"), rows.count(), None
    grid = [(int(n * k), cols) for k in (0.5, 1, 2, 4, 8) for cols in (4, 5, 6) for _ in range(10)]
    model = CostModel(spark.createDataFrame([("any", r, k, float(r)) for r, k in grid], "family string, rows long, cols int, seconds double"), trainings=1, safety=1.0, trees=60)
    for mode in ("weight", "mean"):
        s = Search(c, cost=model, mode=mode)
        plan = s.open(req)
        some = s.candidates(req, plan)
        able = s.affordable(req, plan, some, 2.0 * n * model.factor)
        names = spark.createDataFrame([(i, x.dataset.name, mode, i in able) for i, x in enumerate(some)], "cid int, dataset string, mode string, fits boolean")
        one = s.shapes(plan, some).join(names, "cid").select("dataset", "mode", "rows", "cols", "fits")
        out = one if out is None else out.unionByName(one)
    return out


@register("cost_model_predict")
def cost_model_predict(spark, d):
    """A cost model from timings that grow with the number of cells, of the orders of each status and priority and of their
    months as tables of 2 to 20 columns; predictions over-estimate."""
    from augspark.search.cost import CostModel

    o = table(spark, d, "orders").withColumn("month", F.date_format("o_orderdate", "yyyy-MM"))
    sizes = o.groupingSets([["o_orderstatus", "o_orderpriority"], ["month"]], "o_orderstatus", "o_orderpriority", "month").agg(F.count("*").alias("rows"))
    timings = sizes.select(F.lit("linear").alias("family"), "rows", F.explode(F.array(*map(F.lit, (2, 5, 10, 20)))).alias("cols")).withColumn("seconds", 0.01 + F.col("rows") * F.col("cols") * 1e-6)
    return CostModel(timings, trainings=5).predict(timings).withColumn("over", F.col("predicted_s") >= 5 * F.col("seconds")).select("rows", "cols", "predicted_s", "over")


@register("cost_calibration")
def cost_calibration(spark, d):
    """Seconds of a training on all orders with two columns and on all lines with four."""
    from augspark.search.cost import calibrate_on

    return calibrate_on([(table(spark, d, "orders"), ["o_orderkey", "o_custkey"], "o_totalprice"), (table(spark, d, "lineitem"), [*LINE, "l_linenumber"], "l_extendedprice")])


@register("upload_catalog")
def upload_catalog(spark, d):
    return corpus(spark, d).catalog()


@register("candidates_for_request", "SELECT * FROM (VALUES ('part', 'vertical', 'l_partkey'), ('orders', 'vertical', 'l_orderkey')) AS t(dataset, kind, key) UNION ALL SELECT 'supplier', 'vertical', 'l_suppkey'")
def candidates_for_request(spark, d):
    """Candidates offered to a request that returns raw data."""
    s = Search(corpus(spark, d), order="any")
    return spark.createDataFrame([(x.dataset.name, x.kind, x.key) for x in s.candidates(request(spark, d))], "dataset string, kind string, key string")


def zipf_sql(alpha: float) -> str:
    return f"""ranks AS (SELECT r, sum(pow(r, {-alpha}::DOUBLE)) OVER (ORDER BY r) / sum(pow(r, {-alpha}::DOUBLE)) OVER () AS cum FROM range(1, 21) AS t(r)),
    req AS (SELECT seq, ('0x' || substr(md5(seq::VARCHAR || ':{alpha}'), 1, 13))::UBIGINT::DOUBLE / 4503599627370496::DOUBLE AS u FROM range(1, 51) AS t(seq)),
    users AS (SELECT seq, (SELECT min(r) FROM ranks WHERE round(cum, 12) >= round(u, 12)) - 1 AS usr FROM req),
    requests AS (SELECT seq::INTEGER AS seq, usr::INTEGER AS usr, (usr // 2)::INTEGER AS schema_no FROM users)"""


ALPHAS = (0.0, 1.0, 2.0, 3.0, 5.0, 7.0)


def zipf(spark, alpha: float):
    """50 requests of 20 users: ranks by inverse distribution of a hashed uniform; two users share a schema."""
    ranks = spark.range(1, 21).select(F.col("id").alias("r"))
    weight = F.pow("r", F.lit(-alpha))
    cum = ranks.withColumn("cum", F.round(F.sum(weight).over(Window.orderBy("r")) / F.sum(weight).over(Window.partitionBy()), 12))  # 20 rows
    u = F.conv(F.substring(F.md5(F.concat(F.col("id").cast("string"), F.lit(f":{alpha}"))), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))
    seq = spark.range(1, 51).select(F.col("id").cast("int").alias("seq"), F.round(u, 12).alias("u"))
    hit = seq.join(F.broadcast(cum), F.col("cum") >= F.col("u")).groupBy("seq").agg((F.min("r") - 1).cast("int").alias("usr"))
    return hit.withColumn("schema_no", F.floor(F.col("usr") / 2).cast("int"))


@register("zipf_requests", " UNION ALL ".join(f"(WITH {zipf_sql(a)} SELECT {a}::DOUBLE AS alpha, seq, usr, schema_no FROM requests)" for a in ALPHAS))
def zipf_requests(spark, d):
    out = None
    for a in ALPHAS:
        one = zipf(spark, a).select(F.lit(a).alias("alpha"), "seq", "usr", "schema_no")
        out = one if out is None else out.unionByName(one)
    return out


_LRU = """, prev AS (SELECT *, max(seq) OVER (PARTITION BY schema_no ORDER BY seq ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last, lag(usr) OVER (PARTITION BY schema_no ORDER BY seq) AS before FROM requests),
    dist AS (SELECT p.seq, p.usr, p.schema_no, p.before, CASE WHEN p.last IS NULL THEN NULL ELSE (SELECT count(DISTINCT schema_no) FROM requests q WHERE q.seq > p.last AND q.seq < p.seq) END AS between_n FROM prev p)
    SELECT {a}::DOUBLE AS alpha, seq, CASE WHEN between_n IS NULL OR between_n >= 5 THEN 'miss' WHEN before = usr THEN 'hit' ELSE 'failed_trial' END AS outcome FROM dist"""


def replay(requests, schemas: int = 5, plans: int = 1) -> list[tuple[int, str]]:
    """Outcome of each (seq, user, schema) against a cache whose plans help only the user they were found for."""
    cache, out = PlanCache(schemas, plans), []
    for seq, user, schema in requests:
        got, _ = cache.trial(str(schema), lambda plan, user=user: 1.0 if plan == user else 0.0)
        out.append((seq, got))
        if got != "hit":
            cache.put(str(schema), f"user{user}", user)
    return out


_SESSIONS = f"""WITH a AS (SELECT unnest({list(ALPHAS)}::DOUBLE[]) AS alpha), ranks AS (SELECT alpha, r, round(sum(pow(r, -alpha)) OVER (PARTITION BY alpha ORDER BY r) / sum(pow(r, -alpha)) OVER (PARTITION BY alpha), 12) AS cum FROM a, range(1, 21) AS t(r)),
    cells AS (SELECT alpha, r, cum, coalesce(lag(cum) OVER (PARTITION BY alpha ORDER BY r), -1.0) AS low FROM ranks),
    req AS (SELECT o_custkey AS cust, o_orderkey AS seq, alpha, round(('0x' || substr(md5(o_orderkey::VARCHAR || ':' || alpha::VARCHAR), 1, 13))::UBIGINT::DOUBLE / 4503599627370496::DOUBLE, 12) AS u FROM orders, a),
    requests AS (SELECT q.alpha, cust, seq, r - 1 AS usr, (r - 1) // 2 AS schema_no FROM req q JOIN cells c ON q.alpha = c.alpha AND u <= cum AND u > low),
    prev AS (SELECT *, lag(seq) OVER w AS last, lag(usr) OVER w AS before FROM requests WINDOW w AS (PARTITION BY alpha, cust, schema_no ORDER BY seq)),
    dist AS (SELECT p.alpha, p.cust, p.seq, any_value(p.usr) AS usr, any_value(p.before) AS before, any_value(p.last) AS last, count(DISTINCT q.schema_no) AS between_n FROM prev p LEFT JOIN requests q ON q.alpha = p.alpha AND q.cust = p.cust AND q.seq > p.last AND q.seq < p.seq GROUP BY 1, 2, 3)
    SELECT alpha, seq, CASE WHEN last IS NULL OR between_n >= 5 THEN 'miss' WHEN before = usr THEN 'hit' ELSE 'failed_trial' END AS outcome FROM dist"""


@register("cache_lru_trace", _SESSIONS)
def cache_lru_trace(spark, d):
    """Hits, failed trials and misses by skew: a customer's orders are the requests that meet one cache, each by one of 20
    users whose ranks are drawn by a hash of the order."""
    out = None
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey")
    for a in ALPHAS:
        ranks = spark.range(1, 21).select(F.col("id").alias("r"), F.round(F.sum(F.pow("id", F.lit(-a))).over(Window.orderBy("id")) / F.sum(F.pow("id", F.lit(-a))).over(Window.partitionBy()), 12).alias("cum"))  # 20 rows
        cuts = [r["cum"] for r in ranks.orderBy("r").collect()]
        u = F.round(F.conv(F.substring(F.md5(F.concat(F.col("o_orderkey").cast("string"), F.lit(f":{a}"))), 1, 13), 16, 10).cast("double") / F.lit(float(2**52)), 12)
        usr = sum((F.when(u > c, 1).otherwise(0) for c in cuts), F.lit(0))
        one = o.select(F.lit(a).alias("alpha"), "o_custkey", "o_orderkey", usr.alias("usr"))
        out = one if out is None else out.unionByName(one)

    kept = out.groupBy("alpha", "o_custkey").agg(F.array_sort(F.collect_list(F.struct("o_orderkey", "usr"))).alias("log"))

    @F.udf("array<string>")
    def outcomes(log):
        return [got for _, got in replay((seq, user, user // 2) for seq, user in log)]

    both = F.inline(F.arrays_zip(F.col("log.o_orderkey").alias("seq"), outcomes("log").alias("outcome")))
    return kept.select("alpha", both)


STUDY: dict = {}


def cache_study(spark, d, alpha: float):
    """(alpha, seq, user, outcome, seconds, cv_r2, plain_s) of 50 real requests with a cache of 5 schemas and 1 plan each;
    plain_s is what the same user's request took without a cache."""
    from augspark import workloads

    key = (spark.sparkContext.applicationId, d)
    if key not in STUDY:
        study = workloads.CacheStudy(spark, d)
        STUDY.clear()
        STUDY[key] = study, {}, {}
    study, plain, done = STUDY[key]
    if alpha not in done:
        sequence = [(r["seq"], r["usr"]) for r in sorted(zipf(spark, alpha).collect(), key=lambda r: r["seq"])]  # 50 rows
        rows = study.run(sequence, PlanCache(5, 1))
        for user in {u for _, u in sequence} - set(plain):
            plain[user] = study.run([(0, user)], None)[0][3]
        done[alpha] = [(alpha, seq, user, got, float(s), float(r), float(plain[user])) for seq, user, got, s, r in rows]
    return spark.createDataFrame(done[alpha], "alpha double, seq int, user int, outcome string, seconds double, cv_r2 double, plain_s double")


@register("cache_study_outcomes", f"WITH {zipf_sql(7.0)}{_LRU.format(a=7.0)}")
def cache_study_outcomes(spark, d):
    """Outcomes of real searches at the strongest skew: what the replayed cache says."""
    return cache_study(spark, d, 7.0).select("alpha", "seq", "outcome")


@register("cache_savings")
def cache_savings(spark, d):
    """Measured share of search time saved by the cache at the strongest skew, and mean seconds by outcome."""
    rows = cache_study(spark, d, 7.0)
    mean = lambda o: F.avg(F.when(F.col("outcome") == o, F.col("seconds")))
    return rows.groupBy("alpha").agg((1 - F.sum("seconds") / F.sum("plain_s")).alias("saved"), mean("hit").alias("hit_s"), mean("failed_trial").alias("failed_s"), mean("miss").alias("miss_s"), F.avg("plain_s").alias("plain_s"))


@register("cache_trial_gain", f"WITH {_cv_sql('r', {'all': [*LINE, 'part', 'supplier', 'orders']})} SELECT 'hit' AS outcome, round(cv_r2, 3) AS cv_r2 FROM r")
def cache_trial_gain(spark, d):
    """A resampled request profits from the plan that an earlier one left in the cache."""
    cache, c, req = PlanCache(), corpus(spark, d), request(spark, d)
    Search(c).run(req, cache=cache)
    again = replace(req, train=req.train.filter(F.abs(F.hash("l_partkey", "l_suppkey", "l_orderkey")) % 5 > 0))
    got = Search(c).run(again, cache=cache)
    return spark.createDataFrame([(got.cached, round(got.cv_r2, 3))], "outcome string, cv_r2 double")


@register("cached_resample", "SELECT * FROM (VALUES ('cache', 'hit', true), ('none', 'miss', false)) AS t(cache, outcome, starts_high)")
def cached_resample(spark, d):
    """A resampled request under half the budget: with the cached plan it starts where the first request ended."""
    from augspark import workloads

    return workloads.cached_resample(spark, d).select("cache", "outcome", (F.col("first_r2") > 0.9).alias("starts_high"))


PLAN = [Step("vertical", "part", "l_partkey", 0.3, 0.3), Step("vertical", "supplier", "l_suppkey", 0.3, 0.6)]


@register("materialize_plan", "SELECT l_orderkey, l_linenumber, p_retailprice AS part__p_retailprice, s_acctbal AS supplier__s_acctbal FROM lineitem LEFT JOIN part ON l_partkey = p_partkey LEFT JOIN supplier ON l_suppkey = s_suppkey")
def materialize_plan(spark, d):
    from augspark.search.materialize import apply

    df = lines(spark, d).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    return apply(PLAN, df, corpus(spark, d, False), KEYS).select("l_orderkey", "l_linenumber", "part__p_retailprice", "supplier__s_acctbal")


@register("score_batch", "SELECT l_orderkey, l_linenumber, round(5 + 2 * p_retailprice + 0.5::DOUBLE * l_quantity, 4) AS prediction FROM lineitem JOIN part ON l_partkey = p_partkey")
def score_batch(spark, d):
    from augspark.serve.scorer import Scorer

    s = Scorer([5.0, 2.0, 0.5], ["p_retailprice", "l_quantity"], [("l_partkey", table(spark, d, "part").select("p_partkey", "p_retailprice"), "p_partkey")], {"p_retailprice": 1000.0})
    return s.score(lines(spark, d)).select("l_orderkey", "l_linenumber", F.round("prediction", 4).alias("prediction"))


def _ivm(name: str, where: str):
    return register(name, f"SELECT l_suppkey, {sql_gram(LINE)} FROM lineitem WHERE {where} GROUP BY 1")


@_ivm("ivm_insert", "true")
def ivm_insert(spark, d):
    df = lines(spark, d)
    stored = build.by_key(df.filter("l_linenumber <= 5"), LINE, ["l_suppkey"], exact=True)
    return maintain.apply(stored, [maintain.delta(df.filter("l_linenumber > 5"), LINE, ["l_suppkey"], exact=True)], 3, ["l_suppkey"]).select("l_suppkey", *gram.flat(LINE))


@_ivm("ivm_delete", "l_linenumber > 2")
def ivm_delete(spark, d):
    df = lines(spark, d)
    stored = build.by_key(df, LINE, ["l_suppkey"], exact=True)
    return maintain.apply(stored, [maintain.delta(df.filter("l_linenumber <= 2"), LINE, ["l_suppkey"], "delete", True)], 3, ["l_suppkey"]).select("l_suppkey", *gram.flat(LINE))


@register("ivm_update", "SELECT l_suppkey, count(*)::DOUBLE AS c, round(sum(CAST(CASE WHEN l_linenumber = 1 THEN l_quantity + 1 ELSE l_quantity END AS DECIMAL(18,2)))::DOUBLE, 4) AS s_l_quantity FROM lineitem GROUP BY 1")
def ivm_update(spark, d):
    """An update is a delete and an insert."""
    df = lines(spark, d)
    stored, old = build.by_key(df, ["l_quantity"], ["l_suppkey"], exact=True), df.filter("l_linenumber = 1")
    new = old.withColumn("l_quantity", F.col("l_quantity") + 1)
    deltas = [maintain.delta(old, ["l_quantity"], ["l_suppkey"], "delete", True), maintain.delta(new, ["l_quantity"], ["l_suppkey"], exact=True)]
    return maintain.apply(stored, deltas, 1, ["l_suppkey"]).select("l_suppkey", F.col("g.c").alias("c"), F.round(F.col("g.s")[0], 4).alias("s_l_quantity"))


@register("omniscient_gap")
def omniscient_gap(spark, d):
    """R² of the engine and of a model on all truly useful tables; the difference is the gap."""
    from augspark.baselines import omniscient

    _, a = answer(spark, d, delta=0.001)
    truth = [("l_partkey", table(spark, d, "part"), "p_partkey", ["p_retailprice"]), ("l_suppkey", table(spark, d, "supplier"), "s_suppkey", ["s_acctbal"]), ("l_orderkey", table(spark, d, "orders"), "o_orderkey", ["o_totalprice"])]
    best = omniscient(planted(spark, d), truth, LINE, "y").first()["cv_r2"]
    return spark.createDataFrame([(a.cv_r2, best, best - a.cv_r2)], "engine double, omniscient double, gap double")


@register("omniscient_r2", f"WITH {_cv_sql('r', {'all': ['part', 'supplier', 'orders']})} SELECT round(cv_r2, 4) AS cv_r2 FROM r")
def omniscient_r2(spark, d):
    from augspark.baselines import omniscient

    truth = [("l_partkey", table(spark, d, "part"), "p_partkey", ["p_retailprice"]), ("l_suppkey", table(spark, d, "supplier"), "s_suppkey", ["s_acctbal"]), ("l_orderkey", table(spark, d, "orders"), "o_orderkey", ["o_totalprice"])]
    return omniscient(planted(spark, d), truth, [], "y").select(F.round("cv_r2", 4).alias("cv_r2"))


@register("exhaustive_small", f"WITH {_cv_sql('r', {'part': ['part'], 'supplier': ['supplier'], 'orders': ['orders'], 'part+supplier': ['part', 'supplier'], 'part+orders': ['part', 'orders'], 'supplier+orders': ['supplier', 'orders'], 'part+supplier+orders': ['part', 'supplier', 'orders']})} SELECT dataset AS subset, round(cv_r2, 4) AS cv_r2 FROM r")
def exhaustive_small(spark, d):
    """Every subset of three candidates, the optimum that greedy search is held against."""
    from augspark.baselines import exhaustive, injection_join
    from augspark.cluster import materialize

    t = {"part": ("l_partkey", table(spark, d, "part"), "p_partkey", ["p_retailprice"]), "supplier": ("l_suppkey", table(spark, d, "supplier"), "s_suppkey", ["s_acctbal"]), "orders": ("l_orderkey", table(spark, d, "orders"), "o_orderkey", ["o_totalprice"])}
    joined = injection_join(planted(spark, d), list(t.values()))
    names = {n: f"j{i}_{t[n][3][0]}" for i, n in enumerate(t)}
    whole = [*names.values(), "y"]
    folds = materialize(build.total(joined, whole, "fold"), "exhaustive")

    def of(subset):
        at = [whole.index(names[n]) for n in subset] + [3]
        g = F.col("g")
        return folds.select("fold", gram.element(g["c"], [g["s"][i] for i in at], [g["q"][gram.at(at[i], at[j], 4)] for i, j in gram.pairs(len(at))]).alias("g")), len(at) - 1

    return spark.createDataFrame([("+".join(s), round(r, 4)) for s, r in exhaustive(of, list(t)) if s], "subset string, cv_r2 double")


_HOLED = "SELECT l_suppkey, l_linenumber, l_quantity, CASE WHEN l_orderkey % 4 = 0 THEN NULL ELSE l_discount END AS l_discount FROM lineitem"


@register("upload_maintained", f"SELECT l_suppkey, count(*)::DOUBLE AS c, round(sum(l_quantity) / count(*), 6) AS s_l_quantity, round(sum(coalesce(l_discount, 0.05::DOUBLE)) / count(*), 6) AS s_l_discount, round(sum(l_quantity * coalesce(l_discount, 0.05::DOUBLE)) / count(*) + 1.3e-9::DOUBLE, 6) AS q FROM ({_HOLED}) WHERE l_linenumber > 1 GROUP BY 1")
def upload_maintained(spark, d):
    """Sketches of a table with missing values after an upload, an insert and a delete: those of the table as it is then."""
    rows = table(spark, d, "lineitem").select("l_suppkey", "l_linenumber", "l_quantity", F.when(F.col("l_orderkey") % 4 != 0, F.col("l_discount")).alias("l_discount"))
    part = lambda where: rows.filter(where).drop("l_linenumber")
    c = cat.Corpus(spark)
    c.upload(part("l_linenumber <= 4"), "lines", "RAW", ["l_suppkey"], ["l_quantity", "l_discount"], fill={"l_quantity": 0.0, "l_discount": 0.05})
    c.change("lines", part("l_linenumber > 4"), "insert")
    dataset = c.change("lines", part("l_linenumber = 1"), "delete")
    g = F.col("g")
    return dataset.by_key["l_suppkey"].select(F.col("l_suppkey").cast("long").alias("l_suppkey"), g["c"].alias("c"), F.round(g["s"][0] / g["c"], 6).alias("s_l_quantity"), F.round(g["s"][1] / g["c"], 6).alias("s_l_discount"), F.round(g["q"][1] / g["c"] + TIE, 6).alias("q"))


@register("upload_roles", "SELECT 'l_orderkey' AS name, 'key' AS role UNION ALL SELECT 'l_partkey', 'key' UNION ALL SELECT 'l_quantity', 'feature' UNION ALL SELECT 'l_tax', 'feature'")
def upload_roles(spark, d):
    """Keys and features that a table's profile and types give it."""
    keys, features = cat.Corpus(spark).roles(table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity", "l_tax", F.lit(1).alias("one")).drop("one"), None, None)
    return spark.createDataFrame([(k, "key") for k in keys] + [(f, "feature") for f in features], "name string, role string")


@register("store_scans", "SELECT * FROM (VALUES (20, 1), (200, 1)) AS t(candidates, scans)")
def store_scans(spark, d):
    """Scans of the sketch store in the plan that scores a round, by the number of candidates."""
    part = table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), *[(F.hash("p_partkey", F.lit(i)) % 100).cast("double").alias(f"x{i}") for i in range(200)])
    rows = []
    for n in (20, 200):
        c = cat.Corpus(spark)
        c.upload_columns(part, "partkey", [f"x{i}" for i in range(n)])
        s = Search(c, pair_share=0.0)
        req = Request(planted(spark, d), LINE, "y", {"l_partkey": "partkey"})
        plan = s.open(req)
        text = s.score(plan, s.candidates(req, plan), req)._jdf.queryExecution().optimizedPlan().toString()
        rows.append((n, len([x for x in text.splitlines() if "Relation [" in x and "sid#" in x])))
    return spark.createDataFrame(rows, "candidates int, scans int")
