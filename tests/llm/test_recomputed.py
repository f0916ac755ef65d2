"""Operators against plain recomputation: features, naive Bayes, ids of long texts, policies."""

import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from test_operators import base_spans, documents, slow_rule

from augspark.llm import bpe, quality, rules, secrets, urls


def test_quality_features_by_hand(spark):
    for r in documents(spark, "/root/testdata/sf0.001").collect():
        text = r["text"] or ""
        words = [w.lower() for w in re.findall(r"[^\x20\x09-\x0D]+", text, re.ASCII)]
        raw = [re.sub("[A-Z]", lambda m: m[0].lower(), w).encode() for w in re.findall(r"[^\x20\x09-\x0D]+", text)]
        counts = Counter(zlib.crc32(w) % quality.BUCKETS for w in raw)
        norm = math.sqrt(sum(math.log1p(n) ** 2 for n in counts.values()))
        at, values, stats = quality.features(text, float(len(text)))
        assert dict(zip(at.tolist(), values.tolist(), strict=True)) == pytest.approx({b: math.log1p(n) / max(1e-6, norm) for b, n in counts.items()}, rel=1e-5)
        size, lines = max(1, len(text.encode())), [x for x in text.encode().split(b"\n") if x.strip()]
        symbols = sum(text.count(c) for c in "#*$%&|<>")
        grams = list(zip(raw_cased := text.encode().split(), raw_cased[1:], raw_cased[2:], raw_cased[3:], strict=False))
        want = [
            math.log1p(len(words)) / 10, min(1, len(words) / 20), min(1, (len(text.encode()) - len(words)) / max(1, len(words)) / 12), len(set(raw_cased)) / max(1, len(words)),
            1 - len(set(grams)) / len(grams) if grams else 0.0, 1 - len(set(lines)) / max(1, len(lines)), min(1, len(lines) / max(1, len(words)) * 5), min(1, symbols / max(1, len(words))), float(symbols > 0),
            min(1, 4 * sum("A" <= c <= "Z" for c in text) / size), min(1, 10 * sum("0" <= c <= "9" for c in text) / size), min(1, 10 * sum(c in ".!?," for c in text) / size), min(1, 4 * text.count("|") / max(1, len(words))), min(1, math.log1p(len(text)) / 15),
        ]
        assert stats.tolist() == pytest.approx(want, rel=1e-5, abs=1e-6)


def test_bayes_verdicts_by_hand(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    got = urls.judge(pages).collect()
    decided = {(r["host"], r["path"]): (slow_rule(r["url"])[3] == "block", r["url_words"]) for r in got if slow_rule(r["url"])[3]}
    counts, docs = {True: Counter(), False: Counter()}, Counter()
    for blocked, words in decided.values():
        counts[blocked].update(words)
        docs[blocked] += 1
    known = set(counts[True]) | set(counts[False])
    size = {b: sum(c.values()) + len(known) for b, c in counts.items()}
    for r in got:
        score = math.log(docs[True] / docs[False]) + sum(math.log((counts[True][w] + 1) / size[True]) - math.log((counts[False][w] + 1) / size[False]) for w in r["url_words"] if w in known)
        assert r["block_score"] == pytest.approx(score, abs=1e-9)
        assert r["verdict"] == (slow_rule(r["url"])[3] or ("block" if score > 0 else "allow"))


def test_ids_of_long_texts_match_by_match(spark):
    enc = bpe.encoding(bpe.rank_path())
    long = [r["text"] for r in documents(spark, "/root/testdata/sf0.1").filter("length(text) > 10000").limit(40).collect()]
    assert len(long) >= 5
    for text in [*long, " ".join(long[:5]), "\n\n".join(long[:5]) + "   \t" * 300]:
        assert bpe.encode_text(enc, text) == [i for m in bpe._pattern().finditer(text) for i in enc._encode_single_piece(m[0])]


def test_policies_read_the_same_bits(spark):
    ledger = rules.ledger(documents(spark, "/root/testdata/sf0.01"))
    kept = {p: {r["doc_id"] for r in rules.apply_policy(ledger, p).filter("kept").collect()} for p in rules.POLICIES}
    assert kept["strict"] <= kept["v1"] <= kept["base"] and len(kept["v1"]) > 0
    bits = {r["doc_id"]: r["failed"] for r in ledger.collect()}
    for p, names in rules.POLICIES.items():
        assert kept[p] == {d for d, b in bits.items() if not b & (rules.mask(names) | rules.mask(rules.BASE))}
    assert np.bitwise_or.reduce(list(bits.values())) > 0


def test_markov_spans_by_masking(spark):
    """What fixed patterns leave: their characters are blanked, and the runs of the rest are scored one pair at a time."""
    pair, draw = secrets.train(), random.Random(11)

    def ratio(run):
        codes = [secrets.ALPHABET.index(c) for c in run]
        total = pair.ratio[-1, codes[0]] + sum(pair.ratio[a, b] for a, b in zip(codes, codes[1:], strict=False))
        return total / len(run)

    def slow(text):
        base = base_spans(text)
        masked = list(text)
        for _, a, b in base:
            masked[a:b] = "\0" * (b - a)
        runs = [m.span() for m in re.finditer(r"[A-Za-z0-9+/_=-]{16,}", "".join(masked))]
        hits = [("markov", a, b) for a, b in runs if ratio(text[a:b]) > max(0.0, pair.mean + 4.0 * pair.deviation / math.sqrt(b - a))]
        return sorted([*base, *hits], key=lambda s: (s[1], secrets.KINDS.index(s[0]), s[2]))

    pieces = ["token=", " ", "\n", "abcdef0123456789", "AKIA", "QWERTYUIOP1234", "international_business_account", "x", "é"]
    found = 0
    for _ in range(1500):
        keys = ["".join(draw.choice(secrets.ALPHABET[:62]) for _ in range(draw.randint(8, 40))) for _ in range(2)]
        text = "".join(draw.choice([*pieces, *keys]) for _ in range(draw.randint(1, 10)))
        got = secrets.find_spans(text, pair)
        assert got == slow(text), text
        found += sum(k == "markov" for k, _, _ in got)
    assert found > 300
    for r in documents(spark, "/root/testdata/sf0.001").collect():
        assert secrets.find_spans(r["text"] or "", pair) == slow(r["text"] or "")
