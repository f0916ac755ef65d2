"""Horizontal candidates: their stored totals are added to the user's; no row is read."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from augspark.assess.crossval import ADDED


def batch(user: DataFrame, candidates: DataFrame) -> DataFrame:
    """User (fold, g) and candidate totals (dataset, g) -> (dataset, fold, g) of all unions at once.

    The user's few fold rows are broadcast: one row a fold, whatever the size of the tables.
    """
    datasets = candidates.select("dataset")
    own = datasets.crossJoin(F.broadcast(user.select("fold", "g")))
    return own.unionByName(candidates.select("dataset", F.lit(ADDED).alias("fold"), "g"))
