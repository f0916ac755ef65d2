"""Plans of earlier requests by training schema, least recently used out first at both levels."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


class PlanCache:
    """At most ``schemas`` schemas of at most ``plans`` plans each."""

    def __init__(self, schemas: int = 5, plans: int = 1) -> None:
        self.schemas, self.plans, self.held = schemas, plans, OrderedDict()

    def get(self, schema: str) -> list:
        """Plans of a schema, the latest used first; looking doesn't count as use."""
        return list(reversed(self.held.get(schema, OrderedDict()).values()))

    def put(self, schema: str, name: str, plan) -> None:
        if not self.schemas or not self.plans:
            return
        own = self.held.pop(schema, OrderedDict())
        own.pop(name, None)
        own[name] = plan
        while len(own) > self.plans:
            own.popitem(last=False)
        self.held[schema] = own
        while len(self.held) > self.schemas:
            self.held.popitem(last=False)

    def trial(self, schema: str, gain: Callable[[object], float], delta: float = 0.02) -> tuple[str, object | None]:
        """('hit', plan) for the first plan that gains at least delta, which then counts as used; else failed_trial or miss."""
        found = self.held.get(schema)
        if not found:
            return "miss", None
        for name, plan in list(reversed(found.items())):
            if gain(plan) >= delta:
                self.put(schema, name, plan)
                return "hit", plan
        return "failed_trial", None

    def snapshot(self, spark: SparkSession) -> DataFrame:
        rows = [(i, s, j, n) for i, (s, own) in enumerate(self.held.items()) for j, n in enumerate(own)]
        return spark.createDataFrame(rows, "schema_age int, schema string, plan_age int, plan string")
