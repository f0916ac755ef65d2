"""Registered queries of the engine run: those with SQL are compared with DuckDB, the others written as Parquet."""

import os

import oracle
import pytest

from augspark.queries import registry

QUERIES, ORACLES = registry.queries(), registry.oracle_sql()
#: Studies of minutes, of which smaller forms or other sizes run by default; AUGSPARK_FULL=1 runs these too.
LONG = {"cache_study_outcomes", "cache_savings", "vary_budget", "budget_held", *(f"synthetic_linear_{n}" for n in (0, 1, 10, 50, 100)), "synthetic_square_100"}
if os.environ.get("AUGSPARK_FULL"):
    LONG = set()


@pytest.mark.parametrize("name", sorted(set(ORACLES) - LONG))
def test_matches_sql(spark, sf_dir, name):
    assert oracle.differences(spark, sf_dir, QUERIES[name], ORACLES[name]) is None


def scores_hold(rows):
    """The study ends no worse than it began, and near a model on all useful candidates."""
    (r,) = rows
    assert r["gap"] <= 0.05 and r["engine"] >= r["base"] - 0.01


def engine_wins(rows):
    by = {(r["request"], r["config"]): r["score"] for r in rows}
    assert all(by[name, "engine+trees"] >= score - 0.1 for (name, config), score in by.items() if config == "trees")


CHECKS = {
    "grid_outcome": lambda rows: {r["method"]: r["test_r2"] for r in rows}["proxy"] > {r["method"]: r["test_r2"] for r in rows}["novelty"],
    "omniscient_gap": lambda rows: abs(rows[0]["gap"]) <= 0.01,
    "incremental_equals_full": lambda rows: all(r["difference"] < 1e-6 for r in rows),
    "cost_model_predict": lambda rows: all(r["over"] for r in rows),
    "cache_savings": lambda rows: rows[0]["saved"] > 0.3 and rows[0]["hit_s"] < rows[0]["plain_s"],
    "leave_one_out": lambda rows: len(rows) == 14 and max(r["engine"] - r["alone"] for r in rows if r["alone"] is not None) > 0.3,
    "six_requests": engine_wins,
    "answer_request_any": lambda rows: rows[0]["r2"] > 0.8 and rows[0]["plan"] == "orders+part+supplier",
}


@pytest.mark.parametrize("name", sorted(set(QUERIES) - set(ORACLES) - LONG))
def test_runs_without_sql(spark, sf_dir, name):
    columns, rows = oracle.stored(spark, QUERIES[name](spark, sf_dir))
    check = CHECKS.get(name) or (scores_hold if name.startswith("synthetic_") else lambda rows: None)
    assert columns and check(rows) is not False


def test_late_rows_are_dropped(spark, sf_dir):
    rows = QUERIES["stream_late_data"](spark, sf_dir).collect()
    assert all(r["start"].day > 20 for r in rows)


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())
