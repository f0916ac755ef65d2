"""The rows of a plan: left joins and unions, with missing partners left null for the model search."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.catalog import Corpus, Dataset
from augspark.search.engine import clash_free
from augspark.search.request import Step


def means(d: Dataset, via: str) -> DataFrame:
    """(_k, the dataset's features by their names in a plan): per-key means, read off the sketches."""
    new = clash_free(d.name, d.features)
    return d.store.read(via, [d.sid]).select(F.col("key_value").alias("_k"), *[(F.col("g.s")[i] / F.col("g.c")).alias(n) for i, n in enumerate(new)])


def carry(rows: DataFrame, d: Dataset, key: str, via: str) -> DataFrame:
    """rows with the keys that a join on ``via`` brings, under their names in a plan."""
    for other in d.carried.get(via, ()):
        if f"{d.name}__{other}" not in rows.columns:
            fixed = d.fixed_by(via, other).select(F.col(via).alias("_k2"), F.col(other).alias(f"{d.name}__{other}"))
            rows = rows.join(fixed, F.col(f"`{key}`").cast("string") == F.col("_k2"), "left").drop("_k2")
    return rows


def apply(plan: Sequence[Step], rows: DataFrame, corpus: Corpus, keys: dict[str, str], unions: bool = True, fanout: str = "mean") -> DataFrame:
    """rows with the plan's columns (and, with fanout 'weight', one row a partner and its weight).

    A dataset whose rows its provider keeps is joined by the means of its sketches, and can't be unioned here.
    """
    for step in plan:
        d = corpus.datasets[step.dataset]
        if step.kind == "horizontal":
            if unions:
                if d.data is None:
                    raise ValueError(f"{d.name} has no rows here; its provider must add them")
                own = dict(step.mapping) or {c: c for c in rows.columns}
                own |= {k: keys[k] for k in keys if keys[k] in d.data.columns}
                rows = rows.unionByName(d.data.select(*[F.col(f"`{v}`").alias(c) for c, v in own.items() if c in rows.columns and v in d.data.columns]), allowMissingColumns=True)
            continue
        via = step.via or keys.get(step.key) or step.key.removeprefix(step.key.split("__")[0] + "__")
        new = clash_free(d.name, d.features)
        if fanout == "mean" or d.data is None:
            rows = rows.join(means(d, via), F.col(f"`{step.key}`").cast("string") == F.col("_k"), "left").drop("_k")
        else:
            counts = d.data.groupBy(via).agg(F.count("*").alias("_n")).withColumnRenamed(via, "_k2")
            right = d.data.select(F.col(via).alias("_k"), *[F.col(f).alias(n) for f, n in zip(d.features, new, strict=True)]).join(counts, F.col("_k") == F.col("_k2")).drop("_k2")
            weight = (F.col("weight") if "weight" in rows.columns else F.lit(1.0)) / F.coalesce("_n", F.lit(1))
            rows = rows.join(right, F.col(f"`{step.key}`").cast("string") == F.col("_k").cast("string"), "left").withColumn("weight", weight).drop("_k", "_n")
        rows = carry(rows, d, step.key, via)
    return rows
