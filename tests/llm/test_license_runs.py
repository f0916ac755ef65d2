"""Licences that begin or end inside a line, by brute force over all runs of words."""

import random

from augspark.llm import licenses

KNOWN = licenses.Templates.of()


def names(text):
    return [(m[0], text[m[1] : m[2]]) for m in licenses.find_licenses(text, KNOWN)]


def test_licences_inside_lines():
    assert names("Copyright 2020 A. Released under the MIT License.") == [("MIT", "Released under the MIT License.")]
    assert names("This tool was written last year. Released under the MIT License. It is old.") == [("MIT", "Released under the MIT License")]
    prose = "some words of prose " * 200
    assert names(prose + licenses._MIT + " " + prose) == [("MIT", licenses._MIT.rstrip("."))]
    assert names(prose + licenses._MIT.replace("free of charge", "gratis").replace("\"", "") + prose)[0][0] == "MIT"


def test_best_run_by_brute_force():
    draw = random.Random(6)
    vocabulary = "released licensed under the mit license cc by nc 4 0 a b".split()
    for _ in range(150):
        words = [draw.choice(vocabulary) for _ in range(30)]
        text = "x " + " ".join(words) + " x"
        runs = [licenses.bigrams(licenses.normal(text)[i:j]) for i in range(32) for j in range(i + 2, min(32, i + 30) + 1)]
        best = max(licenses.dice(r, g) for r in runs for g in KNOWN.grams)
        got = licenses.find_licenses(text, KNOWN)
        assert bool(got) == (best >= KNOWN.threshold)
        assert all(abs(max(licenses.dice(licenses.bigrams(licenses.normal(text[a:b])), g) for n, g in zip(KNOWN.names, KNOWN.grams, strict=True) if n == name) - d) < 1e-12 for name, a, b, d in got)
