"""The methods the engine is compared with."""

from __future__ import annotations

import itertools
from collections.abc import Sequence

import numpy as np
from pyspark.ml.feature import VectorAssembler
from pyspark.ml.regression import LinearRegression, RandomForestRegressor
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from augspark.assess import crossval, vertical
from augspark.catalog import one_row_per_key
from augspark.cluster import materialize
from augspark.sketch import build

#: Rows of a broadcast sample of neighbours.
POOL_ROWS = 20_000


def online_factorized(train: DataFrame, features: Sequence[str], key: str, candidates: dict[str, tuple[DataFrame, str, Sequence[str]]], fold: str = "fold", mode: str = "weight", impute: str = "mean", exact: bool = False) -> DataFrame:
    """The engine's assessment without stored sketches: base rows of user and candidate are aggregated for each candidate."""
    out = None
    for name, (df, k, own) in candidates.items():
        user = build.by_key(train, features, [key], fold, exact).withColumnRenamed(key, "key").withColumnRenamed(fold, "fold")
        cand = build.by_key(df, own, [k], exact=exact).select(F.lit(name).alias("dataset"), F.col(k).alias("key"), "g")
        totals = build.total(train, features, fold, exact).withColumnRenamed(fold, "fold")
        one = vertical.batch(user, cand, totals, len(features), len(own), mode, impute)
        out = one if out is None else out.unionByName(one)
    return out


def materialised(train: DataFrame, key: str, right: DataFrame, right_key: str, own: Sequence[str], features: Sequence[str], fold: str = "fold") -> DataFrame:
    """Join rows, then aggregate: what the sketches stand for (one row a key on the right)."""
    means = one_row_per_key(right, right_key, own).withColumnRenamed(right_key, "_k")
    fill = means.agg(*[F.avg(c).alias(c) for c in own]).first().asDict()
    joined = train.join(means, F.col(key) == F.col("_k"), "left").fillna(fill)
    return build.total(joined, [*features, *own], fold)


def injection_join(train: DataFrame, candidates: Sequence[tuple[str, DataFrame, str, Sequence[str]]]) -> DataFrame:
    """All candidates, averaged per key, joined to the rows at once: (own key, table, its key, features)."""
    for n, (own, df, key, features) in enumerate(candidates):
        means = one_row_per_key(df, key, features).select(F.col(key).alias("_k"), *[F.col(f).alias(f"j{n}_{f}") for f in features])
        train = train.join(means, F.col(own) == F.col("_k"), "left").drop("_k")
    return train


def injection_select(joined: DataFrame, features: Sequence[str], target: str, frac: float = 0.2, rounds: int = 10, depth: int = 3, sample: float = 0.1, trees: int = 100, inject: bool = True, seed: int = 1) -> DataFrame:
    """(feature, votes): in how many rounds a feature beats every injected random column, by forest and by sparse regression."""
    spark, votes = joined.sparkSession, dict.fromkeys(features, 0)
    filled = joined.fillna(0.0, subset=list(features))
    filled = filled.filter(F.pmod(F.xxhash64(*[F.col(c) for c in filled.columns], F.lit(seed)), F.lit(1000)) < int(1000 * sample)) if sample < 1 else filled
    means = filled.agg(*[F.stddev_samp(f).alias(f) for f in features]).first().asDict()
    base = materialize(filled.select(target, *[(F.col(f).cast("double") / (means[f] or 1.0)).alias(f) for f in features]), "injection")
    for r in range(rounds if inject else 1):
        noise = [f"_noise{i}" for i in range(max(1, round(frac * len(features))))] if inject else []
        data = base.select("*", *[F.randn(seed=seed * 1000 + r * 50 + i).alias(n) for i, n in enumerate(noise)])
        columns = [*features, *noise]
        x = VectorAssembler(inputCols=columns, outputCol="x").transform(data)
        forest = RandomForestRegressor(featuresCol="x", labelCol=target, numTrees=trees, maxDepth=depth, seed=seed + r).fit(x).featureImportances.toArray()
        sparse = np.abs(LinearRegression(featuresCol="x", labelCol=target, elasticNetParam=1.0, regParam=0.05, standardization=True).fit(x).coefficients.toArray())
        for weights in (forest, sparse):
            bar = max(weights[len(features) :], default=0.0)
            for f, w in zip(features, weights, strict=False):
                votes[f] += bool(w > bar)
    return spark.createDataFrame([(f, v) for f, v in votes.items()], "feature string, votes int")


def _distance(a: Sequence[Column], b: Sequence[Column]) -> Column:
    out = F.lit(0.0)
    for x, y in zip(a, b, strict=True):
        out = out + (x - y) * (x - y)
    return out


def neighbours(queries: DataFrame, pool: DataFrame, features: Sequence[str], k: int = 3) -> DataFrame:
    """The k nearest pool rows of each query row by squared distance, ties by id; both tables are bounded samples with an id.

    The pool is broadcast: more than POOL_ROWS rows are refused, ``neighbours_all`` takes them.
    """
    if pool.limit(POOL_ROWS + 1).count() > POOL_ROWS:
        raise ValueError(f"a pool of more than {POOL_ROWS} rows is no sample")
    q = queries.select(F.col("id").alias("qid"), *[F.col(f).cast("double").alias(f"q_{f}") for f in features])
    p = pool.select(*[c for c in pool.columns if c not in features], *[F.col(f).cast("double").alias(f"p_{f}") for f in features])
    both = q.join(F.broadcast(p), F.col("id") != F.col("qid"))  # at most POOL_ROWS rows
    far = _distance([F.col(f"q_{f}") for f in features], [F.col(f"p_{f}") for f in features])
    rank = F.row_number().over(Window.partitionBy("qid").orderBy("d", "id"))
    return both.withColumn("d", F.round(far, 8)).withColumn("n", rank).filter(F.col("n") <= k)


def neighbours_all(queries: DataFrame, pool: DataFrame, features: Sequence[str], k: int = 3) -> DataFrame:
    """``neighbours`` (qid, id, other pool columns) for tables of any size whose features take few distinct values together.

    Equal points are compared once, and a point sends only its k + 1 smallest ids: a later one can't be among the k
    nearest of any row, itself left out. Pairs are formed of distinct points, not of rows.
    """
    f = [F.col(x).cast("double") for x in features]
    points = pool.groupBy(*[c.alias(f"p_{x}") for c, x in zip(f, features, strict=True)]).agg(F.slice(F.sort_array(F.collect_set("id")), 1, k + 1).alias("ids"))
    asked = queries.select(*[c.alias(f"q_{x}") for c, x in zip(f, features, strict=True)]).distinct()
    far = F.round(_distance([F.col(f"q_{x}") for x in features], [F.col(f"p_{x}") for x in features]), 8)
    pairs = asked.crossJoin(F.broadcast(points)).select(*[f"q_{x}" for x in features], far.alias("d"), F.explode("ids").alias("id"))
    by_point = [f"q_{x}" for x in features]
    near = pairs.withColumn("n", F.row_number().over(Window.partitionBy(*by_point).orderBy("d", "id"))).filter(F.col("n") <= k + 1)
    near = near.groupBy(*by_point).agg(F.sort_array(F.collect_list(F.struct("n", "id"))).alias("near"))
    own = queries.select(F.col("id").alias("qid"), *[c.alias(f"o_{x}") for c, x in zip(f, features, strict=True)])
    met = own.join(near, [F.col(f"o_{x}").eqNullSafe(F.col(f"q_{x}")) for x in features])
    left = F.slice(F.filter("near", lambda e: e["id"] != F.col("qid")), 1, k)
    found = met.select("qid", F.explode(left).alias("e")).select("qid", F.col("e.id").alias("nid"))
    return found.join(pool.drop(*features), F.col("nid") == F.col("id")).drop("nid")


def novelty(user: DataFrame, other: DataFrame, features: Sequence[str], k: int = 3, near=neighbours) -> DataFrame:
    """How well 3-NN tells a candidate's rows from the user's (samples with unique ids): accuracy, leaving each row itself out."""
    pool = user.withColumn("origin", F.lit(0)).unionByName(other.withColumn("origin", F.lit(1)))
    voted = near(pool, pool.select("id", "origin", *features), features, k).groupBy("qid").agg((F.sum("origin") * 2 > k).cast("int").alias("vote")).join(pool.select(F.col("id").alias("qid"), "origin"), "qid")
    return voted.agg(F.avg((F.col("vote") == F.col("origin")).cast("double")).alias("novelty"))


def knn_regress(queries: DataFrame, pool: DataFrame, features: Sequence[str], target: str, k: int = 3, near=neighbours) -> DataFrame:
    return near(queries, pool.select("id", target, *features), features, k).groupBy("qid").agg(F.avg(target).alias("prediction"))


def exhaustive(folds_of, candidates: Sequence[str], max_len: int | None = None) -> list[tuple[tuple[str, ...], float]]:
    """Every subset of candidates with its score; only for tiny corpora. folds_of(subset) gives (fold, g) and target place."""
    out = []
    for n in range((max_len or len(candidates)) + 1):
        for subset in itertools.combinations(candidates, n):
            sketch, target = folds_of(subset)
            got = crossval.score(sketch.withColumn("dataset", F.lit("+".join(subset) or "-")), target).first()
            out.append((subset, got["cv_r2"]))
    return out


def omniscient(train: DataFrame, truth: Sequence[tuple[str, DataFrame, str, Sequence[str]]], features: Sequence[str], target: str, fold: str = "fold") -> DataFrame:
    """Joins every truly useful table and cross-validates one model: (dataset, cv_r2, theta)."""
    joined = injection_join(train, truth)
    new = [f"j{n}_{f}" for n, t in enumerate(truth) for f in t[3]]
    g = build.total(joined.fillna(0.0, subset=new), [*features, *new, target], fold).withColumnRenamed(fold, "fold").withColumn("dataset", F.lit("omniscient"))
    return crossval.score(g, len(features) + len(new))
