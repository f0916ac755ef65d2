"""Queries over all ids: neighbours by brute force, and one result for each id that has one."""

from pyspark.sql import functions as F

from augspark import baselines
from augspark.queries import registry


def test_neighbours_of_all_rows(spark):
    rows = [(i * 7 % 211, float(i % 5), float(i * i % 3), float(i)) for i in range(211)] + [(1000, 40.0, 1.0, 5.0)]
    df = spark.createDataFrame(rows, "id long, a double, b double, y double")
    want = {}
    for i, a, b, _ in rows:
        near = sorted(((a - p) ** 2 + (b - q) ** 2, j) for j, p, q, _ in rows if j != i)[:3]
        want[i] = sorted(j for _, j in near)
    got = baselines.neighbours_all(df, df, ["a", "b"]).groupBy("qid").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    assert {r["qid"]: r["ids"] for r in got.collect()} == want


def test_no_id_is_left_out(spark, sf_dir):
    run = lambda name: registry.queries()[name](spark, sf_dir)
    read = lambda name: spark.read.parquet(f"{sf_dir}/{name}.parquet")
    assert run("join_lateral").count() == read("orders").join(read("customer"), F.col("o_custkey") == F.col("c_custkey")).select("o_custkey").distinct().count()
    assert run("knn_regress").count() == read("lineitem").select("l_orderkey", "l_linenumber").distinct().count()
    assert 0 <= run("novelty_rank").first()["novelty"] <= 1
    assert {r["a"] for r in run("cosine_topk").collect()} == {r["vec_id"] for r in read("embeddings").filter("vec_id % 100 = 0").collect()}
