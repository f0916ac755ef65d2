"""Connected components over an edge table, by alternating star contractions on DataFrames.

Each round rewires every node to the smallest node of its neighbourhood, first from the larger side and then from the
smaller one, until all edges point from a node to its component's smallest node. Minima are partial aggregates, so a hub
that holds a third of all edges is one row per task. The joins back send a hub's rows to many tasks: the groups above a
size that at most a few thousand groups can exceed are broadcast, the rest meet by a shuffle. Every round is written to
shared storage, which cuts the lineage and survives lost executors.

Defined results: edges with a null end and loops (u = u) are no edges; repeated edges count once; an empty table has no
nodes; names are longs and ties don't arise, since a component is named by its smallest node.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.cluster import drop_path, materialize, scratch_path
from augspark.llm.text import column, fresh

#: At most so many groups are broadcast in ``join_groups``; a group of fewer rows than LEAST_HOT is never hot.
HOT_GROUPS = 5_000
LEAST_HOT = 100


def join_groups(rows: DataFrame, key: str, groups: DataFrame, size: str, total: int, spread: Column, salts: int = 1024) -> DataFrame:
    """Inner join of rows with groups (one row a value of ``key``) that no large group sends to one task.

    ``size`` names the column of groups with the number of rows of a group, ``total`` is that of all rows. A group above
    max(LEAST_HOT, total / HOT_GROUPS) is hot: there are fewer than HOT_GROUPS, they are broadcast and their rows are
    dealt out by ``spread``. The columns of groups follow those of rows; ``key`` and ``size`` are not repeated.
    """
    bar = max(LEAST_HOT, total // HOT_GROUPS)
    more = [c for c in groups.columns if c not in (key, size)]
    hk, ck, cs, hot_as, cold_as, salt = fresh([*rows.columns, *groups.columns], "_hk", "_ck", "_cs", "_hot", "_cold", "_salt")
    own = F.struct(*[column(c) for c in more])
    hot = groups.filter(column(size) > bar).select(column(key).alias(hk), own.alias(hot_as))
    no_salt = (F.pmod(F.xxhash64(column(key)), F.lit(1)) - 1).cast("int")  # always -1; as a literal it would leave the join's keys
    cold = groups.filter(column(size) <= bar).select(column(key).alias(ck), no_salt.alias(cs), own.alias(cold_as))
    marked = rows.join(F.broadcast(hot), F.col(key) == F.col(hk), "left")
    dealt = F.when(F.col(hk).isNull(), F.lit(-1)).otherwise(F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    met = marked.withColumn(salt, dealt).join(cold, (F.col(key) == F.col(ck)) & (F.col(salt) == F.col(cs)), "left")
    found = F.coalesce(hot_as, cold_as)
    return met.filter(found.isNotNull()).select(*[column(c) for c in rows.columns], *[found[c].alias(c) for c in more])


def _large_star(edges: DataFrame, n: int) -> DataFrame:
    """At most as many rows as edges; the small star that follows removes repeats."""
    both = edges.select("u", "v").unionAll(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.count("*").alias("n"), F.min("v").alias("m")).select("u", "n", F.least("u", "m").alias("m"))
    return join_groups(both.filter("v > u"), "u", low, "n", 2 * n, F.col("v")).select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v")


def _small_star(edges: DataFrame, n: int) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = down.groupBy("u").agg(F.count("*").alias("n"), F.min("v").alias("m"))
    moved = join_groups(down, "u", low, "n", n, F.col("v")).select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u != v")
    return moved.unionAll(low.select("u", F.col("m").alias("v"))).distinct()


def _summary(edges: DataFrame):
    return edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()


def connected(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(u, v) pairs of longs -> (node, root): every node of an edge that isn't its component's smallest, and that one."""
    spark = edges.sparkSession
    path = scratch_path(spark, "stars")
    now = materialize(edges.filter("u != v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), path=path)
    seen = _summary(now)
    for _ in range(max_rounds):
        if not seen[0]:
            break
        new = scratch_path(spark, "stars")
        now = materialize(_small_star(_large_star(now, seen[0]), seen[0]), path=new)
        drop_path(spark, path)
        path, was, seen = new, seen, _summary(now)
        if tuple(was) == tuple(seen):
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root"))
