"""A cached plan is assessed on the request that asks."""

from dataclasses import replace

from pyspark.sql import functions as F

from augspark.queries import searching
from augspark.search.cache import PlanCache
from augspark.search.engine import Search, schema_of
from augspark.search.request import Step


def test_plan_is_assessed_on_own_rows(spark):
    d = "/root/testdata/sf0.001"
    c, req, cache = searching.corpus(spark, d), searching.request(spark, d), PlanCache()
    cache.put(schema_of(req), "p", [Step("vertical", "part", "l_partkey", 0.3, 0.3, "partkey")])
    useless = replace(req, train=req.train.withColumn("y", F.rand(seed=3)))
    assert Search(c).run(useless, cache=cache).cached == "failed_trial"
    got = Search(c).run(req, cache=cache)
    assert got.cached == "hit" and got.plan[0].dataset == "part" and {s.dataset for s in got.plan} == {"part", "supplier", "orders"}
    assert Search(c).run(replace(req, returns=("MD",)), cache=cache).cached == "failed_trial"
