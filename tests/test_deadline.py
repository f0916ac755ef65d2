"""A budget that ends between two jobs."""

import time

import pytest
from augspark.search.deadline import Deadline


def test_jobs_after_the_end_are_cancelled_too(spark):
    with Deadline(spark, 0.1) as watch:
        time.sleep(1.0)
        with pytest.raises(Exception, match="(?i)cancel"):
            spark.range(20_000_000_000).selectExpr("sum(xxhash64(id) % 7)").collect()
    assert watch.expired
    time.sleep(1.0)
    assert spark.range(10).count() == 10  # what comes after is left alone
