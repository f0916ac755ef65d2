"""Mixing sources to target weights with DataFrame functions only.

The sizes of all sources are aggregated first (partial sums before the shuffle, so a source that holds a third of all
rows is one row per task). Targets follow from the weights by capped proportional sharing, each document is emitted
``floor(rate)`` times, and once more with probability ``rate - floor(rate)`` decided by a hash of seed and doc_id.

Defined results: a null text has size 0; null is one source, ordered last; an empty table gives an empty mix; repeated
rows and rows with equal doc_id share one draw; a null doc_id draws by its text; extra columns of any name are carried
along, but ``plan_copies`` replaces columns that have the names it adds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from augspark.cluster import materialize
from augspark.llm.text import WORD, column, fresh

WEIGHTS = (5, 2, 1)
SHARE = 1.5
CAP = 2
SEED = 20
#: A table of at most this many sources is broadcast; a larger one is joined on salted keys.
BROADCAST_SOURCES = 50_000
SALTS = 32
#: Sources that one task ranks.
RANKED_ROWS = 50_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def positions(sizes: DataFrame, parts: int) -> DataFrame:
    """sizes with ``position``, from 0 by code point of the source, null last: ranks in ranges plus the ranges' offsets."""
    ranged = sizes.repartitionByRange(parts, F.col("source").asc_nulls_last()).withColumn("_p", F.spark_partition_id())
    ranged = materialize(ranged, "ranged-sources")
    counts = ranged.groupBy("_p").agg(F.count("*").alias("_n"))
    ahead = Window.orderBy("_q").rowsBetween(Window.unboundedPreceding, -1)  # a row a range
    offsets = counts.withColumnRenamed("_p", "_q").withColumn("_before", F.coalesce(F.sum("_n").over(ahead), F.lit(0))).drop("_n")
    inside = Window.partitionBy("_p").orderBy(F.col("source").asc_nulls_last())
    return ranged.join(F.broadcast(offsets), F.col("_p") == F.col("_q")).withColumn("position", F.row_number().over(inside) - 1 + F.col("_before")).drop("_p", "_q", "_before")


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, cap: int = CAP, count: int | None = None) -> DataFrame:
    """(source, source_size) -> the same with weight and target.

    All open sources share what the full ones leave, by weight. A level (target a weight) fills the sources whose cap
    it reaches, which raises the level of the others; it only rises, so it settles after a few sums over the sources.
    """
    count = sizes.count() if count is None else count
    slot = F.pmod("position", F.lit(len(weights))).cast("int") + 1
    t = positions(sizes, -(-max(1, count) // RANKED_ROWS)).select("source", "source_size", F.element_at(F.array(*[F.lit(int(w)) for w in weights]), slot).cast("long").alias("weight"))
    t = materialize(t.withColumn("_cap", F.lit(cap) * F.col("source_size")), "weighed-sources")
    size, every = t.agg(F.sum("source_size"), F.sum("weight")).first()
    caps, left = 0, every or 0
    level = float(share) * (size or 0) / left if left else 0.0
    while left:
        full = F.col("_cap") <= F.lit(level) * F.col("weight")
        now, gone = t.agg(F.sum(F.when(full, F.col("_cap"))), F.sum(F.when(full, F.col("weight")))).first()
        if (now or 0, every - (gone or 0)) == (caps, left):
            break
        caps, left = now or 0, every - (gone or 0)
        level = (float(share) * size - float(caps)) / float(left) if left else 0.0
    target = F.least(F.col("_cap").cast("double"), F.lit(level) * F.col("weight")) if left else F.col("_cap").cast("double")
    return t.select("source", "source_size", "weight", target.alias("target"))


def uniform(doc_id: Column, text: Column, seed: int) -> Column:
    """A number in [0, 1) fixed by seed and document: the first 52 bits of an MD5."""
    name = F.concat(F.lit(f"{seed}:"), F.coalesce(doc_id.cast("string"), text, F.lit("")))
    return F.conv(F.substring(F.md5(name), 1, 13), 16, 10).cast("double") / F.lit(float(2**52))


ADDED = ("mix_size", "mix_source_size", "mix_target", "mix_rate", "mix_copies")


def _planned(docs: DataFrame, names: list[str], weights=WEIGHTS, share: float = SHARE, cap: int = CAP, seed: int = SEED) -> DataFrame:
    """docs and, by the given names, what ADDED lists."""
    size, of_source, target, rate, copies = names
    own, salt, salt_of = fresh([*docs.columns, *names], "_source", "_salt", "_salt_of")
    sizes = materialize(docs.select("source", word_count(F.col("text")).alias("size")).groupBy("source").agg(F.sum("size").alias("source_size")), "source-sizes")
    count = sizes.count()
    targets = source_targets(sizes, weights, share, cap, count).select(F.col("source").alias(own), F.col("source_size").alias(of_source), F.col("target").alias(target))
    sized = docs.withColumn(size, word_count(F.col("text")))
    if count <= BROADCAST_SOURCES:
        joined = sized.join(F.broadcast(targets), F.col("source").eqNullSafe(F.col(own)), "left")
    else:
        salted = sized.withColumn(salt, F.pmod(F.xxhash64("doc_id", "text"), F.lit(SALTS)))
        spread = targets.withColumn(salt_of, F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = salted.join(spread, F.col("source").eqNullSafe(F.col(own)) & (F.col(salt) == F.col(salt_of)), "left").drop(salt, salt_of)
    rated = joined.drop(own).withColumn(rate, F.when(F.col(of_source) > 0, F.col(target) / F.col(of_source)).otherwise(F.lit(0.0)))
    whole = F.floor(rate)
    drawn = (uniform(F.col("doc_id"), F.col("text"), seed) < F.col(rate) - whole).cast("int")
    return rated.withColumn(copies, (whole + drawn).cast("int"))


def plan_copies(docs: DataFrame, **how) -> DataFrame:
    """docs with mix_size, mix_source_size, mix_target, mix_rate and mix_copies: how often the mix emits each row."""
    return _planned(docs.drop(*ADDED), list(ADDED), **how)


def mix(docs: DataFrame, **how) -> DataFrame:
    """The mix itself: the rows of docs, each as often as planned, with the columns of docs."""
    names = fresh(docs.columns, *ADDED)
    (copy,) = fresh([*docs.columns, *names], "_copy")
    planned = _planned(docs, names, **how).filter(F.col(names[-1]) > 0)
    return planned.withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(names[-1])))).select(*[column(c) for c in docs.columns])
