"""Shared pieces of the text operators."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

#: A word is a run of anything but space, tab, line feed, vertical tab, form feed and carriage return.
WORD = r"[^\x20\x09-\x0D]+"
GAP = r"[\x20\x09-\x0D]+"


def words(text: Column) -> Column:
    """All words of a text, in order; a null text has none."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), GAP), "")


def let(value: Column, body) -> Column:
    """``body(value)`` with the value computed once a row, however often the body uses it."""
    return F.transform(F.array(value), body)[0]


def fresh(taken: Iterable[str], *names: str) -> list[str]:
    """The names, each with as many underscores in front as keep it apart from those taken, whatever their case."""
    known, out = {t.lower() for t in taken}, []
    for name in names:
        while name.lower() in known:
            name = "_" + name
        known.add(name.lower())
        out.append(name)
    return out


def column(name: str) -> Column:
    """A column by its literal name, dots and back-ticks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Lower the rows of an Arrow batch, a run-time setting of the session that stays lowered.

    Spark itself bounds a batch's bytes (spark.sql.execution.arrow.maxBytesPerBatch); fewer rows bound what a Python
    worker keeps of results while a batch runs.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key)) > rows:
        spark.conf.set(key, rows)
