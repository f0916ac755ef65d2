"""The request of large lines needs their median: the tables that lines are made of are joined once, not again for each pass."""

from augspark import workloads


def test_median_reads_written_lines(spark, sf_dir, monkeypatch):
    seen = []
    median_of = workloads.median_of
    monkeypatch.setattr(workloads, "median_of", lambda df, column: seen.append(df) or median_of(df, column))
    (task,) = workloads.six(spark, sf_dir, ("d5",))
    joined = workloads.planted_lines(spark, sf_dir)
    for df in (*seen, task.rows):
        assert "Join" not in df._jdf.queryExecution().optimizedPlan().toString()
    assert median_of(joined, "y") == median_of(*seen, "y")
    assert task.rows.count() == joined.count() and task.rows.columns == joined.drop("l_linenumber").columns
