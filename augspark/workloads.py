"""The experiment workloads: requests, corpora and studies over the given tables.

Every study returns rows of plain values and takes its sizes and budgets as parameters. ``python -m augspark.workloads
STUDY SF_DIR`` runs one at full size and prints its rows.
"""

from __future__ import annotations

import hashlib
import math
import sys
import time
from collections.abc import Sequence
from dataclasses import replace
from typing import NamedTuple

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from augspark import baselines, measures
from augspark.catalog import Corpus
from augspark.cluster import materialize, table
from augspark.modelsearch.search import HostedSimulator, ModelSearch
from augspark.ring import gram
from augspark.search.cache import PlanCache
from augspark.search.cost import CostModel, calibrate
from augspark.search.engine import Search, schema_of
from augspark.search.request import Answer, Request
from augspark.serve.scorer import of_plan
from augspark.serve.service import Service
from augspark.sketch import build

BUDGETS = (120.0, 240.0, 360.0, 480.0, 600.0)
USEFUL = (0, 1, 5, 10, 50, 100)
CONFIGS = ("broad", "trees", "online+broad", "engine+broad", "engine+trees", "forest+broad", "engine+hosted")
#: A score this far below search alone doesn't count as worse: runs differ by as much.
TOLERANCE = 0.01
#: Test rows of a request in the leave-one-out study below which its scores say nothing.
LEAST_TEST = 50
LINE = ["l_quantity", "l_discount", "l_tax"]
LINE_KEYS = {"l_partkey": "partkey", "l_suppkey": "suppkey", "l_orderkey": "orderkey"}


def uniform(name: str, key: str):
    """A number in [0, 1) fixed by a name and a key column."""
    return hashed(F.concat(F.lit(f"{name}:"), F.col(key).cast("string")))


def hashed(text):
    """A number in [0, 1) fixed by a text column."""
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


def fold_of(*columns: str, folds: int = 10):
    return F.pmod(F.xxhash64(*columns), F.lit(folds)).cast("int")


# the corpus and the six requests


def planted_lines(spark: SparkSession, d: str) -> DataFrame:
    """Lines with a target planted in part, supplier and orders, whose columns are then dropped."""
    base = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", *LINE, ((F.col("l_orderkey") + 3 * F.col("l_linenumber")) % 10).cast("int").alias("fold"))
    part = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_retailprice")
    supplier = table(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"), "s_acctbal")
    orders = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_totalprice")
    y = 10 * (F.col("p_retailprice") - 950) + F.lit(0.1) * F.col("s_acctbal") + F.lit(0.002) * F.col("o_totalprice")
    return base.join(part, "l_partkey").join(supplier, "l_suppkey").join(orders, "l_orderkey").withColumn("y", y).drop("p_retailprice", "s_acctbal", "o_totalprice")


def dimensions(spark: SparkSession, d: str, corpus: Corpus | None = None) -> Corpus:
    """The dimension tables and rollups that requests may join, under corpus key names."""
    c = corpus or Corpus(spark)
    c.upload(table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), "p_retailprice"), "part", "RAW", ["partkey"], ["p_retailprice"])
    c.upload(table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), F.col("p_size").cast("double").alias("p_size")), "size", "RAW", ["partkey"], ["p_size"])
    c.upload(table(spark, d, "supplier").select(F.col("s_suppkey").alias("suppkey"), "s_acctbal"), "supplier", "RAW", ["suppkey"], ["s_acctbal"])
    c.upload(table(spark, d, "orders").select(F.col("o_orderkey").alias("orderkey"), F.col("o_custkey").alias("custkey"), "o_totalprice"), "orders", "RAW", ["orderkey", "custkey"], ["o_totalprice"])
    c.upload(table(spark, d, "customer").select(F.col("c_custkey").alias("custkey"), F.col("c_nationkey").alias("nationkey"), "c_acctbal"), "customer", "RAW", ["custkey", "nationkey"], ["c_acctbal"])
    feed = table(spark, d, "events").groupBy(F.col("user_id").alias("custkey")).agg(F.avg("value").alias("spent"), F.count("*").cast("double").alias("visits"))
    c.upload(feed, "feed", "RAW", ["custkey"], ["spent", "visits"])
    nation = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nationkey")).agg(F.avg("c_acctbal").alias("wealth"))
    c.upload(nation, "nation", "RAW", ["nationkey"], ["wealth"])
    return c


class Task(NamedTuple):
    """A request's rows, its features and keys, whether it is a classification, and the dataset it may not see."""

    name: str
    rows: DataFrame
    features: list[str]
    keys: dict[str, str]
    classes: bool
    lineage: str | None = None

    @property
    def task(self) -> str:
        return "class" if self.classes else "regression"


def median_of(df: DataFrame, column: str) -> float | None:
    """The exact median of a numeric column in two passes: values near it are counted between two approximate quantiles."""
    x = F.col(column).cast("double")
    n, ends = df.agg(F.count(x), F.percentile_approx(x, [0.4998, 0.5002], 20_000)).first()
    if not n:
        return None
    near = df.filter(x <= ends[1]).groupBy(F.when(x >= ends[0], x).alias("x")).count().collect()  # values between the ends
    below = sum(r["count"] for r in near if r["x"] is None)
    at, found = below, []
    for r in sorted((r for r in near if r["x"] is not None), key=lambda r: r["x"]):
        found += [r["x"] for k in ((n - 1) // 2, n // 2) if at <= k < at + r["count"]]
        at += r["count"]
    if len(found) < 2:  # the quantiles missed it
        return df.agg(F.percentile(x, F.lit(0.5))).first()[0]
    return (found[0] + found[1]) / 2


def six(spark: SparkSession, d: str, names: Sequence[str] | None = None) -> list[Task]:
    """Three regressions and three classifications, small to large; the last has no useful augmentation. names: only these."""
    line = planted_lines(spark, d)
    wanted = lambda n: names is None or n in names
    whole = materialize(line.drop("l_linenumber"), "lines") if wanted("d5") else line.drop("l_linenumber")  # the median takes two passes: joined once
    median = median_of(whole, "y") if wanted("d5") else None
    acct = table(spark, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_acctbal")
    orders = table(spark, d, "orders").join(acct, "o_custkey")
    small = orders.select("o_custkey", (F.col("o_totalprice") / 1000).alias("price"), (F.col("c_acctbal") / 100 + F.col("o_orderkey") % 17).alias("y"), (F.col("o_orderkey") % 10).cast("int").alias("fold"))
    feed = table(spark, d, "events").groupBy("user_id").agg(F.avg("value").alias("v"))
    churn = table(spark, d, "customer").join(feed, F.col("c_custkey") == F.col("user_id"), "left")
    churn = churn.select("c_custkey", F.col("c_nationkey").cast("double").alias("nation"), (F.coalesce("v", F.lit(0.0)) > 50).cast("int").alias("y"), (F.col("c_custkey") % 10).cast("int").alias("fold"))
    flag = table(spark, d, "lineitem").select("l_partkey", "l_suppkey", *LINE, (F.col("l_returnflag") == "R").cast("int").alias("y"), ((F.col("l_orderkey") + 3 * F.col("l_linenumber")) % 10).cast("int").alias("fold"))
    every = [
        Task("d1", small, ["price"], {"o_custkey": "custkey"}, False),
        Task("d2", line.filter("l_linenumber <= 2").drop("l_linenumber"), LINE, LINE_KEYS, False),
        Task("d3", whole, LINE, LINE_KEYS, False),
        Task("d4", churn, ["nation"], {"c_custkey": "custkey"}, True),
        Task("d5", whole.withColumn("y", (F.col("y") > median).cast("int")), LINE, LINE_KEYS, True),
        Task("d6", flag, LINE, {"l_partkey": "partkey", "l_suppkey": "suppkey"}, True),
    ]
    return [t for t in every if wanted(t.name)]


def request_bytes(spark: SparkSession, d: str) -> dict[str, int]:
    """Bytes of the six training tables as ``size_class`` counts them; those made of lines are counted in one pass."""
    tasks = {t.name: t.rows for t in six(spark, d, ("d1", "d2", "d3", "d4", "d6"))}
    both = planted_lines(spark, d).agg(F.count_if(F.col("l_linenumber") <= 2).alias("d2"), F.count("*").alias("d3")).first()
    rows = {"d1": tasks["d1"].count(), "d2": both["d2"], "d3": both["d3"], "d4": tasks["d4"].count(), "d5": both["d3"], "d6": tasks["d6"].count()}
    return {n: rows[n] * 8 * len(tasks["d3" if n == "d5" else n].columns) for n in rows}  # d5 has d3's rows and columns


def split(rows: DataFrame, held: int = 5) -> tuple[DataFrame, DataFrame]:
    """80/20 by hash of the whole row: (train, test)."""
    mark = F.pmod(F.xxhash64(*[F.col(c) for c in rows.columns]), F.lit(held))
    return rows.filter(mark > 0), rows.filter(mark == 0)


def size_class(rows: DataFrame) -> tuple[int, str]:
    """(bytes of the numbers and keys of a training table, its class: up to 1 MB, up to 10 MB, or above)."""
    size = rows.count() * 8 * len(rows.columns)
    return size, "small" if size <= 1 << 20 else "medium" if size <= 10 << 20 else "large"


def rate(task: Task, scored: DataFrame) -> float:
    """R² of a regression, accuracy of a classification, on scored test rows."""
    if task.classes:
        return float(measures.accuracy(scored.withColumn("y", F.col("y").cast("double")), "y", (F.col("prediction") >= 0.5).cast("double")).first()["accuracy"])
    return float(measures.r2(scored, "y", "prediction").first()["r2"])


def forest_features(task: Task, train: DataFrame, corpus: Corpus) -> tuple[DataFrame, list[str], list]:
    """injection-forest: all joins at once, and the features that most rounds of most rankers keep."""
    found = [(own, d.data, name, list(d.features)) for own, name in task.keys.items() for d in corpus.datasets.values() if name in d.keys and d.data is not None]
    joined = materialize(baselines.injection_join(train, found), "injection-join")
    names = [f"j{n}_{f}" for n, c in enumerate(found) for f in c[3]]
    votes = {r["feature"]: r["votes"] for r in baselines.injection_select(joined, [*task.features, *names], "y").collect()}
    return joined, [f for f in names if votes[f] >= 10], found


def attempt(task: Task, config: str, corpus: Corpus, budget_s: float, cost: CostModel | None = None, cache: PlanCache | None = None) -> tuple[float, float, float, float]:
    """(test score, search seconds, model seconds, dollars) of one request by one configuration."""
    train, test = split(task.rows)
    req = Request(train, task.features, "y", task.keys, "fold", budget_s, "any", ("RAW", "MD", "API"), task.lineage)
    how, _, final = config.rpartition("+")
    began = time.monotonic()
    if not how:
        found = ModelSearch(final, budget_s, task.task).run(train, task.features, "y")
        return rate(task, found.model.predict(test)), 0.0, found.seconds, measures.SMALL_VM_PER_10_MIN * found.seconds / 600
    if how == "forest":
        joined, chosen, found = forest_features(task, train, corpus)
        took = time.monotonic() - began
        got = ModelSearch(final, max(1.0, budget_s), task.task).run(joined, [*task.features, *chosen], "y")
        score = rate(task, got.model.predict(baselines.injection_join(test, found)))
        return score, took, got.seconds, measures.SMALL_VM_PER_10_MIN * (took + got.seconds) / 600
    hosted = final == "hosted"
    service = Service(corpus, cache, None if hosted else cost, final, "fixed" if hosted else "cost", budget_s / 2, task.task, online=how == "online")
    r = service.answer(req)
    price = HostedSimulator().bill(r.model_s) if hosted else measures.SMALL_VM_PER_10_MIN * (r.search_s + r.model_s) / 600
    return rate(task, r.api.score(test)), r.search_s, r.model_s, price


def cost_model(spark: SparkSession, rows: Sequence[int] = (200, 2000, 20_000), cols: Sequence[int] = (2, 8)) -> CostModel:
    """A cost model calibrated on this cluster, on random tables of a grid of shapes."""
    return CostModel(calibrate(spark, [(r, c) for r in rows for c in cols]))


def six_requests(spark: SparkSession, d: str, budget_s: float = 600.0, runs: int = 10, configs: Sequence[str] = CONFIGS, names: Sequence[str] | None = None) -> DataFrame:
    """(request, task, size, config, run, score, search_s, model_s, cost) of the six requests."""
    corpus, out = dimensions(spark, d), []
    for task in six(spark, d, names):
        if names is None or task.name in names:
            kind = size_class(task.rows)[1]
            for config in configs:
                for run in range(runs):
                    out.append((task.name, task.task, kind, config, run, *attempt(task, config, corpus, budget_s)))
    return spark.createDataFrame(out, "request string, task string, size string, config string, run int, score double, search_s double, model_s double, cost double")


def vary_budget(spark: SparkSession, d: str, budgets: Sequence[float] = BUDGETS, names: Sequence[str] | None = None, final: str = "broad") -> DataFrame:
    """(request, budget_s, alone, engine, seconds, held) of the six requests: search alone and the engine under the same budgets."""
    corpus, cost, out = dimensions(spark, d), cost_model(spark), []
    for task in six(spark, d, names):
        for b in budgets:
            alone = attempt(task, final, corpus, b)
            engine = attempt(task, f"engine+{final}", corpus, b, cost)
            out.append((task.name, float(b), alone[0], engine[0], engine[1] + engine[2], engine[1] + engine[2] <= b + LATENCY_S))
    return spark.createDataFrame(out, "request string, budget_s double, alone double, engine double, seconds double, held boolean")


#: What one job may take to notice that it is cancelled, and a first model to be fitted whatever the budget.
LATENCY_S = 6.0


# leave one out


def views(spark: SparkSession, d: str) -> dict[str, tuple[DataFrame, list[str], str]]:
    """Derived datasets over the given tables: name -> (rows with key and features, key names, base table)."""
    line, orders, events = table(spark, d, "lineitem"), table(spark, d, "orders"), table(spark, d, "events")
    out = {
        "orders": (orders.select(F.col("o_orderkey").alias("orderkey"), F.col("o_custkey").alias("custkey"), "o_totalprice", F.year("o_orderdate").cast("double").alias("o_year")), ["orderkey", "custkey"], "orders"),
        "customer": (table(spark, d, "customer").select(F.col("c_custkey").alias("custkey"), "c_acctbal", F.col("c_nationkey").cast("double").alias("c_nation")), ["custkey"], "customer"),
        "part": (table(spark, d, "part").select(F.col("p_partkey").alias("partkey"), "p_retailprice", F.col("p_size").cast("double").alias("p_size")), ["partkey"], "part"),
        "supplier": (table(spark, d, "supplier").select(F.col("s_suppkey").alias("suppkey"), "s_acctbal", F.col("s_nationkey").cast("double").alias("s_nation")), ["suppkey"], "supplier"),
    }
    for key, column in (("orderkey", "l_orderkey"), ("partkey", "l_partkey"), ("suppkey", "l_suppkey")):
        own = line.groupBy(F.col(column).alias(key))
        out[f"amount_by_{key}"] = (own.agg(F.sum("l_extendedprice").alias("amount"), F.avg("l_tax").alias("tax")), [key], f"amount_{key}")
        out[f"volume_by_{key}"] = (own.agg(F.count("*").cast("double").alias("lines"), F.sum("l_quantity").alias("quantity")), [key], f"volume_{key}")
    own = orders.groupBy(F.col("o_custkey").alias("custkey"))
    out["orders_by_custkey"] = (own.agg(F.count("*").cast("double").alias("orders"), F.avg("o_totalprice").alias("average")), ["custkey"], "orders_count")
    out["spent_by_custkey"] = (own.agg(F.sum("o_totalprice").alias("spent"), F.max("o_totalprice").alias("largest")), ["custkey"], "orders_spent")
    feed = events.groupBy(F.col("user_id").alias("custkey"))
    out["visits_by_custkey"] = (feed.agg(F.count("*").cast("double").alias("visits"), F.max("value").alias("top")), ["custkey"], "events_visits")
    out["values_by_custkey"] = (feed.agg(F.sum("value").alias("total"), F.avg("value").alias("mean")), ["custkey"], "events_values")
    return out


def leave_one_out(spark: SparkSession, d: str, budget_s: float = 60.0, only: Sequence[str] | None = None) -> DataFrame:
    """(dataset, alone, engine, steps): each dataset is the request once, its first feature the target, all others its corpus.

    Scores are null where fewer than LEAST_TEST rows are left for testing, on which they would be chance.
    """
    corpus, found, out = Corpus(spark), views(spark, d), []
    for name, (df, keys, _) in found.items():
        corpus.upload(df, name, "RAW", keys, [c for c in df.columns if c not in keys], lineage=name)
    for name, (df, keys, _) in found.items():
        if only is not None and name not in only:
            continue
        numbers = [c for c in df.columns if c not in keys]
        train, test = split(df.withColumn("fold", fold_of(*keys)))
        req = Request(train, numbers[1:], numbers[0], {k: k for k in keys}, "fold", budget_s, lineage=name)
        search = Search(corpus, pair_share=0.0)
        answer = search.run(req)
        alone = unaugmented(search, req)
        enough = test.count() >= LEAST_TEST
        score = lambda s: measures.r2(s.score(test), numbers[0], "prediction").first()["r2"] if enough else None  # noqa: B023, E731
        out.append((name, score(alone), score(of_plan(search, answer)), len(answer.plan)))
    return spark.createDataFrame(out, "dataset string, alone double, engine double, steps int")


def unaugmented(search: Search, req: Request):
    """The scorer of the request's proxy without any augmentation."""
    plan = search.open(replace(req, keys={}))  # its total alone is read
    row = search.base(plan, req)
    return of_plan(search, Answer(theta=list(row["theta"]), feature_names=list(req.features), fill=plan.fill))


# the controlled study


def synthetic(spark: SparkSession, d: str, useful: int, shape: str = "linear", domain: int = 200, budget_s: float = 600.0, delta: float = 0.02) -> DataFrame:
    """(useful, shape, base, engine, omniscient, gap, found): 100 candidates of which ``useful`` predict a planted target.

    Rows have ten keys; the target sums ten features (or their squares), one a key. The first is public and splits the
    rows into eleven parts: the first trains, the others are unions. For each other feature there are ten joins, blends of
    it and noise by a correlation of min(1, 1/Exp(10)). Validation and test rows are uniform samples of all rows.
    """
    keys = [f"j{i}" for i in range(1, 11)]
    line = table(spark, d, "lineitem").select(F.monotonically_increasing_id().alias("n"), F.concat_ws(":", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").alias("row"))
    rows = line.select("row", *[F.floor(uniform(k, "row") * domain).cast("int").alias(k) for k in keys])
    for i, k in enumerate(keys, 1):  # a feature is a function of its key: hashed once a value, not once a row
        rows = rows.join(F.broadcast(spark.range(domain).select(F.col("id").cast("int").alias(k)).withColumn(f"f{i}", uniform(f"f{i}", k))), k)  # domain bounds it
    term = (lambda c: F.col(c)) if shape == "linear" else (lambda c: F.col(c) * F.col(c))
    rows = rows.withColumn("y", sum((term(f"f{i}") for i in range(1, 11)), F.lit(0.0)))
    rows = materialize(rows.select("row", *keys, "f1", "y", F.least(F.floor(F.col("f1") * 11), F.lit(10)).cast("int").alias("part"), F.floor(uniform("use", "row") * 10).cast("int").alias("use")), "synthetic")
    train, valid, test = rows.filter("part = 0 and use >= 2"), rows.filter("use = 1"), rows.filter("use = 0")

    kinds = [("union", i, 0) for i in range(1, 11)] + [("join", i, c) for i in range(2, 11) for c in range(10)]
    order = sorted(range(len(kinds)), key=lambda i: hash_number(f"pick:{i}"))
    chosen = {kinds[i] for i in order[:useful]}
    corpus = Corpus(spark)
    noise = lambda n: uniform(f"random {n}", "row")
    unions = rows.filter("part > 0 and use >= 2")
    random_f, random_y, lures = noise("f1"), noise("y") * 10, [i for i in range(1, 11) if ("union", i, 0) not in chosen]
    lure = F.col("part").isin(lures) if lures else F.lit(False)
    unions = unions.select(*keys, "part", F.when(lure, random_f).otherwise(F.col("f1")).alias("f1"), F.when(lure, random_y).otherwise(F.col("y")).alias("y"))
    corpus.upload_partitions(unions, "part", ["f1", "y"], keys, prefix="part")
    values = spark.range(domain).select(F.col("id").cast("int").alias("k"))
    joins = {}
    for i in range(2, 11):
        cells = []
        for c in range(10):
            u = max(hash_number(f"correlation:{i}:{c}"), 1e-12)
            phi = min(1.0, 1.0 / max(1e-9, -10.0 * math.log(u)))
            own = uniform(f"f{i}", "k") * phi + uniform(f"blend {i} {c}", "k") * (1 - phi) if ("join", i, c) in chosen else uniform(f"lure {i} {c}", "k")
            cells.append(own.alias(f"a{i}_{c}"))
        joins[i] = values.select(F.col("k").alias(f"j{i}"), *cells)
    corpus.upload_tables([(df, f"j{i}", [f"a{i}_{c}" for c in range(10)]) for i, df in joins.items()])
    corpus.compact()  # every round reads it
    req = Request(train, ["f1"], "y", {k: k for k in keys}, None, budget_s, validation=valid)
    search = Search(corpus, delta=delta, pair_share=0.0)
    answer = search.run(req)
    engine = float(measures.r2(of_plan(search, answer).score(test), "y", "prediction").first()["r2"])
    base = float(measures.r2(unaugmented(search, req).score(test), "y", "prediction").first()["r2"])
    best = omniscient_test(train, unions, joins, chosen, test, keys)
    hits = sum((("union", int(s.dataset.removeprefix("part")), 0) if s.kind == "horizontal" else ("join", int(s.dataset[1:].split("_")[0]), int(s.dataset.split("_")[1]))) in chosen for s in answer.plan)
    return spark.createDataFrame([(useful, shape, base, engine, best, best - engine, hits, len(answer.plan))], "useful int, shape string, base double, engine double, omniscient double, gap double, hits int, steps int")


def omniscient_test(train: DataFrame, unions: DataFrame, joins: dict[int, DataFrame], chosen: set, test: DataFrame, keys: list[str]) -> float:
    """Test R² of a linear model on all truly useful unions and joins."""
    from augspark.assess import solve
    from augspark.serve.scorer import linear

    parts = [i for kind, i, _ in chosen if kind == "union"]
    whole = train.select("f1", "y", *keys)
    whole = whole.unionByName(unions.filter(F.col("part").isin(parts)).select("f1", "y", *keys)) if parts else whole
    names = ["f1"]
    for i, df in joins.items():
        own = [f"a{i}_{c}" for kind, n, c in sorted(chosen) if kind == "join" and n == i]
        if own:
            whole, test = whole.join(df.select(f"j{i}", *own), f"j{i}"), test.join(df.select(f"j{i}", *own), f"j{i}")
            names += own
    theta = solve.ridge(gram.wide_matrix(whole, [*names, "y"]), len(names), 1e-6)
    return float(measures.r2(test, "y", linear(theta, names)).first()["r2"])


def hash_number(text: str) -> float:
    return int(hashlib.md5(text.encode()).hexdigest()[:13], 16) / 2**52


# the request cache


class CacheStudy:
    """20 users of 300 candidates each; users 2i and 2i + 1 share a schema, so each meets the other's plan.

    A user's target is the sum of two of the own candidates, so two joins make the proxy perfect.
    """

    def __init__(self, spark: SparkSession, d: str, users: int = 20, candidates: int = 300, domain: int = 400) -> None:
        self.spark, self.users, self.corpus = spark, users, Corpus(spark)
        keys = table(spark, d, "lineitem").select(F.monotonically_increasing_id().alias("n"), (F.col("l_partkey") % domain).cast("int").alias("k"), F.col("l_quantity").alias("q"), "l_orderkey")
        self.requests = {}
        every = spark.range(users).select(F.col("id").alias("u")).crossJoin(spark.range(candidates).select(F.col("id").alias("c"))).crossJoin(spark.range(domain).select(F.col("id").alias("k")))  # the parameters bound it
        name = F.concat(F.lit("u"), F.col("u").cast("string"), F.lit("_c"), F.col("c").cast("string"))
        self.corpus.upload_long(every.select(name.alias("name"), F.concat(F.lit("schema"), F.floor(F.col("u") / 2).cast("string")).alias("key_name"), F.col("k").alias("key_value"), hashed(F.concat_ws(":", name, F.col("k").cast("string"))).alias("value")))
        for u in range(users):
            key = f"schema{u // 2}"
            part = lambda c, u=u: hashed(F.concat_ws(":", F.lit(f"u{u}_c{c % candidates}"), F.col("k").cast("string")))
            rows = keys.filter(F.col("l_orderkey") % users == u).select(F.col("k").alias(key), F.col("q").alias(f"q{u // 2}"), (part(7 * u) + part(11 * u + 3)).alias("y"), fold_of("l_orderkey", "k").alias("fold"))
            self.requests[u] = Request(materialize(rows, f"user{u}"), [f"q{u // 2}"], "y", {key: key}, "fold", 600.0)

    def run(self, sequence: Sequence[tuple[int, int]], cache: PlanCache | None) -> list[tuple[int, int, str, float, float]]:
        """(seq, user, outcome, seconds, R²) of requests (seq, user) in order."""
        out = []
        for seq, user in sequence:
            answer = Search(self.corpus, pair_share=0.0).run(self.requests[user], cache=cache)
            out.append((seq, user, answer.cached or "miss", answer.seconds, answer.cv_r2))
        return out


def cached_resample(spark: SparkSession, d: str, budget_s: float = 60.0) -> DataFrame:
    """(cache, outcome, first_r2, cv_r2, seconds): a resampled request under half the budget, with and without the plan that
    the first request left in the cache. first_r2 is the proxy's score when the rounds begin."""
    corpus, cache, rows = dimensions(spark, d), PlanCache(), planted_lines(spark, d).drop("l_linenumber")
    own = [F.col(c) for c in rows.columns]
    first = Request(rows.filter(F.pmod(F.xxhash64(*own), F.lit(3)) > 0), LINE, "y", LINE_KEYS, "fold", budget_s)
    again = replace(first, train=rows.filter(F.pmod(F.xxhash64(*own, F.lit(1)), F.lit(3)) > 0), budget_s=budget_s / 2)
    Search(corpus).run(first, cache=cache)
    out = []
    for name, used in (("cache", cache), ("none", None)):
        a = Search(corpus).run(again, cache=used)
        start = [r for _, n, r in a.trace if n == 0][-1]
        out.append((name, a.cached or "miss", float(start), float(a.cv_r2), float(a.seconds)))
    assert schema_of(first) == schema_of(again)
    return spark.createDataFrame(out, "cache string, outcome string, first_r2 double, cv_r2 double, seconds double")


# unions only


def grid_rows(spark: SparkSession, d: str) -> DataFrame:
    """Rows in an 8 x 8 grid, with a target whose slope and offset depend on the cell."""
    cell = lambda c, low, width: F.least(F.greatest(F.floor((F.col(c) - low) / width), F.lit(0)), F.lit(7))
    df = table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.col("l_quantity").alias("x"), (F.col("l_tax") * 100).alias("v"), (cell("l_quantity", 0, 6.5) * 8 + cell("l_extendedprice", 0, 15000)).cast("int").alias("cell"))
    return df.withColumn("z", (F.col("cell") % 7) * 0.5 * F.col("v") + (F.col("cell") % 5) * 3.0)


def grid_study(spark: SparkSession, d: str, home: int = 9) -> DataFrame:
    """(method, cell, seconds, train_r2, test_r2): the one best union by the proxy and by novelty, for one cell's rows."""
    rows = grid_rows(spark, d).withColumn("u", F.pmod(F.xxhash64("l_orderkey", "l_linenumber", "l_partkey"), F.lit(8)))
    corpus = Corpus(spark)
    corpus.upload_partitions(rows.filter(F.col("cell") != home).select("cell", "v", "z"), "cell", ["v", "z"], prefix="cell")
    train, test = rows.filter((F.col("cell") == home) & (F.col("u") == 0)), rows.filter((F.col("cell") == home) & (F.col("u") == 1))
    req = Request(train.select("v", "z", "l_orderkey").withColumn("fold", fold_of("l_orderkey")), ["v"], "z", {}, "fold", 600.0)
    out = []
    for method in ("proxy", "novelty"):
        search = Search(corpus, ranker=method, delta=-1e9)
        began = time.monotonic()
        answer = search.run(req, max_rounds=1)
        took = time.monotonic() - began
        scorer = of_plan(search, answer)
        union = corpus.datasets[answer.plan[0].dataset].data.select("v", "z").unionByName(train.select("v", "z"))
        score = lambda df: float(measures.r2(scorer.score(df), "z", "prediction").first()["r2"])  # noqa: B023, E731
        out.append((method, int(answer.plan[0].dataset.removeprefix("cell")), took, score(union), score(test.select("v", "z"))))
    return spark.createDataFrame(out, "method string, cell int, seconds double, train_r2 double, test_r2 double")


STUDIES = {
    "six_requests": six_requests,
    "vary_budget": vary_budget,
    "leave_one_out": lambda spark, d: leave_one_out(spark, d, 600.0),
    "synthetic": lambda spark, d: union_all([synthetic(spark, d, n, s, 10_000) for s in ("linear", "square") for n in USEFUL]),
    "cached_resample": lambda spark, d: cached_resample(spark, d, 300.0),
    "grid_study": grid_study,
}


def union_all(frames: Sequence[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def main() -> None:
    spark = SparkSession.builder.config("spark.sql.session.timeZone", "UTC").getOrCreate()
    STUDIES[sys.argv[1]](spark, sys.argv[2]).show(1000, truncate=False)
    spark.stop()


if __name__ == "__main__":
    main()
