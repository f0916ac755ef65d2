"""The six requests are built one by one, and their sizes are counted without any median."""

from augspark import workloads
from pyspark.sql import functions as F


def test_median_of(spark):
    for values in ([3.0], [1.0, 2.0], [5.0, 5.0, 5.0, 1.0], [float(i * 37 % 1001) for i in range(1001)], [float(i * 37 % 1000) for i in range(1000)]):
        df = spark.createDataFrame([(v,) for v in [*values, None]], "v double")
        assert workloads.median_of(df, "v") == df.agg(F.percentile("v", F.lit(0.5))).first()[0]
    assert workloads.median_of(spark.createDataFrame([], "v double"), "v") is None


def test_request_alone(spark, sf_dir, monkeypatch):
    """A request needs no other request's median."""
    monkeypatch.setattr(workloads, "median_of", lambda *_: 1 / 0)
    assert [t.name for t in workloads.six(spark, sf_dir, ("d1",))] == ["d1"]
    assert workloads.request_bytes(spark, sf_dir)["d5"] == spark.read.parquet(f"{sf_dir}/lineitem.parquet").count() * 64
