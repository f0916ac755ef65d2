"""Quality classifier: a factorisation machine over hashed words, structure statistics and metadata.

score = sigmoid(bias + w.x + pairwise), with the pairwise term of rank k in linear time by the sum-of-squares identity
0.5 * sum_f ((sum_i v_if x_i)^2 - sum_i (v_if x_i)^2).

Features: log counts of hashed lower-cased words scaled to unit length, statistics of the text's structure, and, where
the table has it, the stored length as metadata. doc_id, lang, source and labels are never inputs of a score.

Training uses a bounded sample of labelled rows (``SAMPLE_ROWS``, the smallest hashes of their ids): the bound is a
parameter; everything else reads all rows. Rows whose crc32(doc_id as text) mod 5 is 0 are held out.

Defined results: a null or empty text is scored from its (zero) features; a null doc_id is not held out and never
trains; repeated rows get equal scores; an empty table gives an empty table; without usable labels all scores are 0.5;
repeated labels of a document count once if they agree and not at all if they differ; extra columns are carried along, but
a column that has the name of the result (``quality_score``) is replaced.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.llm.text import small_batches

BUCKETS = 4096
FACTORS = 8
SAMPLE_ROWS = 8000
FOLDS = 5
CUT = 0.3
_SYMBOLS = b"#*$%&|<>"
_UPPER, _DIGITS = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789"
_SENTENCE = b".!?,"
STATS = 14


def statistics(raw: bytes, words: list[bytes], stored: float) -> np.ndarray:
    """Structure of a text, each about 0 to 1; the last is metadata: the stored length (0 if unknown)."""
    n, size = max(1, len(words)), max(1, len(raw))
    distinct = len(set(words))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    count = lambda chars: size - len(raw.translate(None, chars)) if raw else 0
    grams = len(words) - 3
    repeats = 1 - len(set(zip(words, words[1:], words[2:], words[3:], strict=False))) / grams if grams > 0 else 0.0
    symbols, upper = count(_SYMBOLS), count(_UPPER)
    return np.array(
        [
            np.log1p(len(words)) / 10,
            min(1.0, len(words) / 20),
            min(1.0, (len(raw) - len(words)) / n / 12),
            distinct / n,
            repeats,
            1 - len(set(lines)) / max(1, len(lines)),
            min(1.0, len(lines) / n * 5),
            min(1.0, symbols / n),
            float(symbols > 0),
            min(1.0, 4 * upper / size),
            min(1.0, 10 * count(_DIGITS) / size),
            min(1.0, 10 * count(_SENTENCE) / size),
            min(1.0, 4 * raw.count(b"|") / n),
            min(1.0, np.log1p(max(0.0, stored)) / 15),
        ],
        dtype=np.float32,
    )


def features(text: str | None, stored: float, buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(bucket numbers, values, statistics) of a whole text."""
    raw = (text or "").encode("utf-8")
    cased = raw.split()
    words = [w.lower() for w in cased]
    hashed = np.fromiter(map(zlib.crc32, words), np.int64, len(words)) % buckets
    at, counts = np.unique(hashed, return_counts=True)
    values = np.log1p(counts).astype(np.float32)
    return at, values / max(1e-6, float(np.sqrt((values**2).sum()))), statistics(raw, cased, stored)


@dataclass(frozen=True)
class Machine:
    """bias, linear weights and factors; words first, then statistics."""

    bias: float
    w: np.ndarray
    v: np.ndarray

    def score(self, x: np.ndarray) -> np.ndarray:
        z = self.bias + x @ self.w + 0.5 * ((x @ self.v) ** 2 - (x**2) @ (self.v**2)).sum(axis=1)
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(x: np.ndarray, y: np.ndarray, factors: int = FACTORS, epochs: int = 8, batch: int = 256, rate: float = 0.02, decay: float = 1e-4, seed: int = 5) -> Machine:
    """Adam on the logistic loss; x holds one row a document."""
    draw = np.random.default_rng(seed)
    d = x.shape[1]
    p = [np.float32(np.log((y.mean() + 1e-3) / (1 - y.mean() + 1e-3))).reshape(1), np.zeros(d, np.float32), draw.normal(0, 0.02, (d, factors)).astype(np.float32)]
    m, s, step = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
    for _ in range(epochs):
        order = draw.permutation(len(y))
        for at in range(0, len(y), batch):
            rows = order[at : at + batch]
            xb, step = x[rows], step + 1
            inner = xb @ p[2]
            z = p[0] + xb @ p[1] + 0.5 * (inner**2 - (xb**2) @ (p[2] ** 2)).sum(axis=1)
            err = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[rows]) / len(rows)
            grads = [err.sum().reshape(1), xb.T @ err + decay * p[1], xb.T @ (err[:, None] * inner) - ((xb**2).T @ err)[:, None] * p[2] + decay * p[2]]
            for i, g in enumerate(grads):
                m[i] = 0.9 * m[i] + 0.1 * g
                s[i] = 0.999 * s[i] + 0.001 * g**2
                p[i] = (p[i] - rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(s[i] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return Machine(float(p[0][0]), p[1], p[2])


def _dense(rows: list[tuple[np.ndarray, np.ndarray, np.ndarray]], buckets: int) -> np.ndarray:
    x = np.zeros((len(rows), buckets + STATS), np.float32)
    for i, (at, values, stats) in enumerate(rows):
        x[i, at] = values
        x[i, buckets:] = stats
    return x


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string")) % FOLDS == 0, F.lit(False))


def _stored(docs: DataFrame) -> Column:
    return F.coalesce(F.col("n_chars").try_cast("double"), F.lit(0.0)) if "n_chars" in docs.columns else F.lit(0.0)


def train(docs: DataFrame, labels: DataFrame, sample_rows: int = SAMPLE_ROWS, buckets: int = BUCKETS, **how) -> Machine:
    """Fit on the labelled rows outside the held-out fold; only the sample's features reach the driver."""
    agreed = labels.filter("quality in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.min("quality").alias("y"), F.max("quality").alias("_y")).filter("y = _y").select("doc_id", "y")
    chosen = agreed.filter(~held_out(F.col("doc_id"))).orderBy(F.xxhash64(F.col("doc_id").cast("string")), "doc_id").limit(sample_rows)

    @F.pandas_udf("struct<at:array<short>,values:array<float>,stats:array<float>>")
    def extract(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
        for texts, stored in batches:
            got = [features(t, c, buckets) for t, c in zip(texts, stored, strict=True)]
            yield pd.DataFrame({"at": [g[0].astype(np.int16) for g in got], "values": [g[1] for g in got], "stats": [g[2] for g in got]})

    known = docs.select("doc_id", "text", _stored(docs).alias("_n")).join(F.broadcast(chosen), "doc_id")  # sample_rows bounds the broadcast
    got = known.select("doc_id", "y", extract("text", "_n").alias("f")).select("doc_id", "y", "f.*").toPandas()
    got = got.sort_values("doc_id", kind="stable").drop_duplicates("doc_id")
    if not len(got) or got["y"].nunique() < 2:
        flat = 0.0 if not len(got) else (20.0 if got["y"].iloc[0] else -20.0)
        return Machine(flat, np.zeros(buckets + STATS, np.float32), np.zeros((buckets + STATS, 1), np.float32))
    x = _dense([(np.asarray(a, np.int64), np.asarray(b, np.float32), np.asarray(c, np.float32)) for a, b, c in zip(got["at"], got["values"], got["stats"], strict=True)], buckets)
    return fit(x, got["y"].to_numpy(np.float32), **how)


def score(docs: DataFrame, machine: Machine, out: str = "quality_score") -> DataFrame:
    """docs with a score from 0 to 1 of each whole text."""
    small_batches(docs.sparkSession)
    buckets = len(machine.w) - STATS

    @F.pandas_udf("double")
    def scored(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for texts, stored in batches:
            parts = []
            for at in range(0, len(texts), 256):
                rows = [features(t, c, buckets) for t, c in zip(texts[at : at + 256], stored[at : at + 256], strict=True)]
                parts.append(machine.score(_dense(rows, buckets)))
            yield pd.Series(np.concatenate(parts) if parts else [], dtype="float64")

    return docs.withColumn(out, scored(F.col("text"), _stored(docs)))
