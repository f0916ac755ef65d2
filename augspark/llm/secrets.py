"""Secret scans: fixed patterns, and character Markov models compared by log-likelihood ratio.

Two first-order character models are trained from labelled samples, one of random strings and one of ordinary
identifiers and words. Every run of ``MIN_RUN`` or more key characters that the fixed patterns leave, also a rest beside
one of their spans, is scored by the mean log-likelihood ratio a character, and is reported (kind ``markov``) above a
threshold that falls with its length: mean and deviation of ordinary samples' scores, the deviation over the root of the
length.

Defined results: a null or empty text has no spans; texts are scanned whole; spans count code points, end exclusive;
repeated rows give the same spans; an empty table gives an empty table; extra columns are carried along, but ``scan``
replaces a column that has the name of its result and ``redact`` the text.
"""

from __future__ import annotations

import itertools
import math
import random
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.llm.text import small_batches

KINDS = ("assign", "access", "hex", "markov")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
#: Greedy runs, so a minimum in the pattern equals dropping short matches.
ACCESS = re.compile(r"AKIA[A-Z0-9]{14,}")
HEX = re.compile(r"[0-9a-f]{16,}")
MIN_RUN = 16
RUN = re.compile(r"[A-Za-z0-9+/_=-]{%d,}" % MIN_RUN)
#: Deviations that a run must lie above ordinary samples.
DEVIATIONS = 4.0
SPANS = "array<struct<kind:string,start:int,end:int>>"

ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
_CODE = np.full(128, len(ALPHABET), dtype=np.int16)
_CODE[[ord(c) for c in ALPHABET]] = np.arange(len(ALPHABET))
#: Ordinary identifiers are joined from such words by default.
WORDS = (
    "the of and to in for is on that by this with you it not or be are from at as your all have new more an was we will home can us about if page my has search free but our one other do no "
    "information time they site he up may what which their news out use any there see only so his when contact here business who web also now help get view online first been would how were "
    "services some these click its like service than find price date back top people list name just over state year day into email two health world next used go work last most products music "
    "buy data make them should product system post her city add policy number such please available copyright support message after best software then good video well where info rights public "
    "books high school through each links she review years order very privacy book items company read group need many user said does set under general research university january mail full map "
    "reviews program life know games way days management part could great united hotel real item international center value index count buffer handle client server request response config parse"
).split()


#: Ordinary words of other languages are joined from such beginnings, vowels and ends.
ONSETS = "b c d f g h j k l m n p r s t v w z bl br ch cl cr dr fl fr gl gr kl kr pf ph pl pr qu sch sh sk sl sp st str th tr tw zw".split() + [""] * 6
VOWELS = "a e i o u ai au ei eu ie oi ou aux eux eau ui y ee oo".split()
ENDS = "n r s t l m d x ch ng nd rt st pf tz ck ss ll nn ns rs".split() + [""] * 14


@dataclass(frozen=True)
class MarkovPair:
    """Per pair of neighbouring characters, log p(random) - log p(ordinary); first row: of the first character.

    ``mean`` and ``deviation`` are of ordinary samples' scores, the deviation at length 1.
    """

    ratio: np.ndarray
    mean: float = 0.0
    deviation: float = 0.0

    def score(self, text: str) -> float:
        """Mean log-likelihood ratio a character, above 0 where the random model fits better."""
        at = _CODE[np.frombuffer(text.encode("ascii", "replace"), dtype=np.uint8) & 127]
        return float((self.ratio[-1, at[0]] + self.ratio[at[:-1], at[1:]].sum()) / len(at))

    def threshold(self, length: int, deviations: float = DEVIATIONS) -> float:
        return max(0.0, self.mean + deviations * self.deviation / math.sqrt(length))

    def secret(self, text: str) -> bool:
        return self.score(text) > self.threshold(len(text))


def default_samples(n: int = 4000, seed: int = 7) -> list[tuple[str, int]]:
    """Labelled samples made by rule: (string, 1 random or 0 ordinary identifier)."""
    draw, out = random.Random(seed), []
    alphabets = ("0123456789abcdef", ALPHABET[:62], ALPHABET[:64], "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", "abcdefghijklmnopqrstuvwxyz0123456789")
    for i in range(n):
        letters = alphabets[i % len(alphabets)]
        out.append(("".join(draw.choice(letters) for _ in range(draw.randint(20, 64))), 1))
        parts = [draw.choice(WORDS) for _ in range(draw.randint(3, 9))]
        style = i % 4
        name = "_".join(parts) if style == 0 else "-".join(parts) if style == 1 else "/".join(parts) if style == 2 else parts[0] + "".join(p.title() for p in parts[1:])
        name = name.upper() if draw.random() < 0.15 else name
        out.append((name + (str(draw.randint(1, 2030)) if draw.random() < 0.3 else ""), 0))
        made = "".join(draw.choice(ONSETS) + draw.choice(VOWELS) + draw.choice(ENDS) for _ in range(draw.randint(1, 6)))
        made = made.upper() if i % 7 == 0 else made.capitalize() if i % 3 == 0 else made
        out.append((made + (str(draw.randint(0, 2030)) if i % 10 == 0 else ""), 0))
    return out


def train(samples: Iterable[tuple[str, int]] | None = None, smooth: float = 0.5) -> MarkovPair:
    """Fit both models, and the spread of the ordinary samples' scores."""
    samples = [(t, label) for t, label in (default_samples() if samples is None else samples) if t]
    size = len(ALPHABET) + 1
    counts = np.full((2, size + 1, size), smooth)
    for text, label in samples:
        at = _CODE[np.frombuffer(text.encode("ascii", "replace"), dtype=np.uint8) & 127]
        counts[label, size, at[0]] += 1
        np.add.at(counts[label], (at[:-1], at[1:]), 1)
    p = np.log(counts / counts.sum(axis=2, keepdims=True))
    pair = MarkovPair(p[1] - p[0])
    ordinary = [(pair.score(t), len(t)) for t, label in samples if not label and len(t) >= MIN_RUN // 2]
    if not ordinary:
        return pair
    scores, sizes = np.array(ordinary).T
    mean = float(scores.mean())
    return MarkovPair(pair.ratio, mean, float(((scores - mean) * np.sqrt(sizes)).std()))


def find_spans(text: str, pair: MarkovPair) -> list[tuple[str, int, int]]:
    """All spans of a text, by start and then by kind."""
    found = [("assign", m.start(), m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 12]
    found += [("access", m.start(), m.end()) for m in ACCESS.finditer(text)]
    found += [("hex", m.start(), m.end()) for m in HEX.finditer(text)]
    taken: list[list[int]] = []  # base spans merged where they touch
    for a, b in sorted((a, b) for _, a, b in found):
        if taken and a <= taken[-1][1]:
            taken[-1][1] = max(taken[-1][1], b)
        else:
            taken.append([a, b])
    more, n = [], 0
    for m in RUN.finditer(text):
        at = m.start()
        while n < len(taken) and taken[n][1] <= at:
            n += 1
        inside = itertools.takewhile(lambda t: t[0] < m.end(), itertools.islice(taken, n, None))
        for a, b in [*inside, [m.end(), m.end()]]:  # what lies before each span, and what follows the last
            if a - at >= MIN_RUN and pair.secret(text[at:a]):
                more.append(("markov", at, a))
            at = max(at, b)
    return sorted(found + more, key=lambda x: (x[1], KINDS.index(x[0]), x[2]))


def scanner(pair: MarkovPair):
    @F.pandas_udf(SPANS)
    def scan(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in texts:
            yield pd.Series([[{"kind": k, "start": a, "end": b} for k, a, b in find_spans(t or "", pair)] for t in batch], dtype=object)

    return scan


def scan(docs: DataFrame, samples: Iterable[tuple[str, int]] | None = None, text: str = "text", out: str = "secret_spans") -> DataFrame:
    """docs with the secrets of each whole text as spans (kind, start, end)."""
    small_batches(docs.sparkSession)
    return docs.withColumn(out, scanner(train(samples))(F.col(text)))


def count_kind(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")


def describe(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def redact(docs: DataFrame, samples: Iterable[tuple[str, int]] | None = None, mark: str = "[SECRET]") -> DataFrame:
    """docs with every span replaced by a mark, overlapping spans by one; a text without spans stays as it is."""
    small_batches(docs.sparkSession)
    pair = train(samples)

    @F.pandas_udf("string")
    def clean(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in texts:
            yield pd.Series([_redacted(t, pair, mark) if t else t for t in batch], dtype=object)

    return docs.withColumn("text", clean(F.col("text")))


def _redacted(text: str, pair: MarkovPair, mark: str) -> str:
    out, at = [], 0
    for _, start, end in find_spans(text, pair):
        if start >= at:
            out += [text[at:start], mark]
        at = max(at, end)
    return "".join([*out, text[at:]]) if out else text
