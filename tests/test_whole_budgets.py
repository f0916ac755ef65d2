"""The study of budgets runs every request under every published budget; runs are recorded, not made."""

import pytest

from augspark import workloads
from augspark.queries import evaluation, registry


@pytest.fixture
def runs(monkeypatch):
    """(request, configuration, budget) of each run; the engine oversteps the smallest budget."""
    made = []

    def attempt(task, config, corpus, budget_s, *_):
        made.append((task.name, config, budget_s))
        return 0.5, budget_s / 2, budget_s / 2 + (60.0 if budget_s == 120 else 0.0), 0.0

    monkeypatch.setattr(workloads, "attempt", attempt)
    monkeypatch.setattr(workloads, "dimensions", lambda *_: None)
    monkeypatch.setattr(workloads, "cost_model", lambda *_: None)
    monkeypatch.setattr(evaluation, "RUNS", {})
    return made


EVERY = {(f"d{i}", config, 60.0 * b) for i in range(1, 7) for b in (2, 4, 6, 8, 10) for config in ("broad", "engine+broad")}


def test_held_counts_every_request_and_budget(spark, sf_dir, runs):
    held = {r["held"]: r["requests"] for r in registry.queries()["budget_held"](spark, sf_dir).collect()}
    assert held == {True: 24, False: 6} and set(runs) == EVERY and len(runs) == 60


def test_a_row_for_every_request_and_budget(spark, sf_dir, runs):
    rows = registry.queries()["vary_budget"](spark, sf_dir).collect()
    assert {(r["request"], "broad", r["budget_s"]) for r in rows} == {e for e in EVERY if e[1] == "broad"} and len(rows) == 30
    assert set(runs) == EVERY and len(runs) == 60
