"""Re-use of sketches over rounds: the sketches of an extended plan from those of the plan before."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.ring import gram


def extend(plan: DataFrame, added: DataFrame, on: Sequence[str], by: Sequence[str], m: int, p: int) -> DataFrame:
    """Sketch of plan by ``on`` (and more) and of the added table by ``on`` (and more) -> the inner join's sketch by ``by``.

    A key new in the added table comes from its composite sketch; a key of the plan needs the plan's composite sketch.
    """
    both = plan.withColumnRenamed("g", "_a").join(added.withColumnRenamed("g", "_b"), list(on))
    return gram.sum_elements(both.withColumn("g", gram.multiply(F.col("_a"), F.col("_b"), m, p)), m + p, by)


def extend_left(plan: DataFrame, added: DataFrame, on: Sequence[str], by: Sequence[str], m: int, p: int, default: Column) -> DataFrame:
    """The same of a left join: what has no partner stays, with the default element in the partner's place.

    ``added`` has weight 1 a value of ``on``, over all its rows together. Values of ``by`` that only ``added`` has are
    null for the rest, which is then in no sketch of that key.
    """
    both = plan.withColumnRenamed("g", "_a").join(added.withColumnRenamed("g", "_b"), list(on), "left")
    partner = F.coalesce(F.col("_b"), default)
    out = gram.sum_elements(both.withColumn("g", gram.multiply(F.col("_a"), partner, m, p)), m + p, by)
    for name in by:
        out = out.filter(F.col(name).isNotNull()) if name in added.columns and name not in on else out
    return out


def extend_linear(plan: DataFrame, added: DataFrame, on: Sequence[str], by: Sequence[str], m: int, p: int, u: Sequence[float]) -> DataFrame:
    """The same of sketches without pair sums; u are the values that stand for a missing partner."""
    both = plan.withColumnRenamed("g", "_a").join(added.withColumnRenamed("g", "_b"), list(on), "left")
    a, b = F.col("_a"), F.coalesce(F.col("_b"), constant(u))
    out = gram.sum_linear(both.withColumn("g", gram.linear(a["c"] * b["c"], [a["s"][i] * b["c"] for i in range(m)] + [b["s"][i] * a["c"] for i in range(p)])), m + p, by)
    for name in by:
        out = out.filter(F.col(name).isNotNull()) if name in added.columns and name not in on else out
    return out


def constant(values: Sequence[float]) -> Column:
    """The element of weight 1 that stands for rows without partner."""
    u = [F.lit(float(v)) for v in values]
    return gram.element(F.lit(1.0), u, [u[i] * u[j] for i, j in gram.pairs(len(u))])


class PlanMemo:
    """Sketches of plans, or of parts of them, by canonical name: the order of joins that don't depend on each other doesn't
    matter. At most ``size`` are held; the least recently used goes first."""

    def __init__(self, size: int | None = None) -> None:
        self.known, self.size = OrderedDict(), size

    @staticmethod
    def canonical(steps: Sequence[tuple[str, str, Sequence[str]]]) -> str:
        return "|".join(sorted(f"{kind}:{dataset}:{','.join(keys)}" for kind, dataset, keys in steps))

    def get(self, steps, make):
        name = self.canonical(steps)
        if name not in self.known:
            self.known[name] = make()
        self.known.move_to_end(name)
        while self.size is not None and len(self.known) > self.size:
            self.known.popitem(last=False)
        return self.known[name]
