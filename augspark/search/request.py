"""A user's request and its answer."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from augspark.catalog import LABELS


@dataclass(frozen=True)
class Request:
    """Training rows with features, target, join keys and fold; budget in seconds.

    keys maps own columns to corpus key names; a discovery index finds what own columns join, whatever the names. Without
    ``fold``, or where no such column is there, rows are dealt into ten folds by hash. ``validation`` rows take the place
    of folds: the training rows are then scored on them alone.
    """

    train: DataFrame
    features: Sequence[str]
    target: str
    keys: dict[str, str]
    fold: str | None = "fold"
    budget_s: float = 600.0
    model: str = "linear"
    returns: Sequence[str] = ("RAW",)
    lineage: str | None = None
    validation: DataFrame | None = None

    def __post_init__(self) -> None:
        if self.model not in ("linear", "any"):
            raise ValueError("model is linear or any")
        if not self.returns or set(self.returns) - set(LABELS):
            raise ValueError(f"returns is a non-empty subset of {sorted(LABELS)}")
        if self.budget_s < 0:
            raise ValueError("budget can't be negative")
        if self.target in self.features:
            raise ValueError("the target can't be a feature")
        wanted = {*self.features, self.target, *self.keys}
        missing = wanted - set(self.train.columns)
        if self.validation is not None:
            missing |= wanted - set(self.validation.columns)
        if missing:
            raise ValueError(f"columns missing in the training table: {sorted(missing)}")


@dataclass(frozen=True)
class Step:
    kind: str
    dataset: str
    key: str | None
    gain: float
    cv_r2: float
    via: str | None = None
    mapping: tuple[tuple[str, str], ...] = ()


@dataclass
class Answer:
    """What a search found. keys are the request's with those that joins brought; seconds, and predicted model seconds."""

    plan: list[Step] = field(default_factory=list)
    base_r2: float = 0.0
    cv_r2: float = 0.0
    theta: list[float] = field(default_factory=list)
    feature_names: list[str] = field(default_factory=list)
    trace: list[tuple[float, int, float]] = field(default_factory=list)
    stopped: str = ""
    cached: str = ""
    scored: int = 0
    rounds: int = 0
    seconds: float = 0.0
    predicted_s: float = 0.0
    keys: dict[str, str] = field(default_factory=dict)
    fill: dict[str, float] = field(default_factory=dict)
    reused: int = 0
    rescanned: int = 0


def trace_table(spark: SparkSession, answer: Answer) -> DataFrame:
    """(seconds, round, cv_r2) of a search: the score of its plan over time."""
    return spark.createDataFrame([(float(t), int(n), float(r)) for t, n, r in answer.trace], "seconds double, round int, cv_r2 double")
