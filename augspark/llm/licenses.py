"""License scans: runs of words compared to licence templates by Dice coefficient over word bigrams.

Texts and templates are normalised to lower-case words of letters and digits. Dice is 2 |A and B| / (|A| + |B|) over
bigram multisets (a single word counts as one bigram with an empty end). Since |A and B| is at most the smaller size, a
run whose size is outside [t / (2 - t), (2 - t) / t] times a template's can't reach t: such templates are not compared.
Runs begin and end at any word, with a bigram that the template has: one without it at an end only lowers Dice. Of
overlapping matches of a template the best stays, then of those of all templates (longer, then earlier, then smaller name
on ties); a match inside a longer one of the same licence goes first. A match with all words of a line has its
punctuation too.

Defined results: a null or empty text has no match; whole texts are scanned; a licence over several lines is found as
one run; repeated rows match alike; an empty table gives an empty table; extra columns are carried along, but a column
that has the name of the result (``license_matches``) is replaced.
"""

from __future__ import annotations

import bisect
import functools
import itertools
import math
import re
from collections import Counter
from collections.abc import Iterator, Mapping
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.llm.text import small_batches

THRESHOLD = 0.8
MATCHES = "array<struct<license:string,start:int,end:int,dice:double>>"
_WORD = re.compile(r"[^\W_]+")

_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_BSD_END = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_BSD_2 = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
_BSD_3 = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."""

#: Texts and notices of public licences, by (name, text).
TEMPLATES: tuple[tuple[str, str], ...] = (
    ("MIT", _MIT),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("ISC", _ISC),
    ("BSD-2-Clause", f"{_BSD_2} {_BSD_END}"),
    ("BSD-3-Clause", f"{_BSD_2} {_BSD_3} {_BSD_END}"),
    ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"),
    ("Apache-2.0", """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."""),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("GPL-3.0", """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."""),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
)


def normal(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def bigrams(words: list[str]) -> Counter:
    return Counter(zip(words, words[1:], strict=False)) if len(words) > 1 else Counter([(w, "") for w in words])


def dice(a: Counter, b: Counter) -> float:
    size = sum(a.values()) + sum(b.values())
    few, many = (a, b) if len(a) <= len(b) else (b, a)
    return 2 * sum(min(n, many[g]) for g, n in few.items() if g in many) / size if size else 0.0


@dataclass(frozen=True)
class Templates:
    """Normalised templates with their sizes in bigrams, and every bigram of any of them."""

    names: tuple[str, ...]
    grams: tuple[Counter, ...]
    sizes: tuple[int, ...]
    known: frozenset
    threshold: float

    @staticmethod
    def of(templates=TEMPLATES, threshold: float = THRESHOLD) -> Templates:
        items = templates.items() if isinstance(templates, Mapping) else templates
        named = [(n, g) for n, t in items if (g := bigrams(normal(t)))]
        return Templates(tuple(n for n, _ in named), tuple(g for _, g in named), tuple(sum(g.values()) for _, g in named), frozenset(x for _, g in named for x in g), threshold)

    def candidates(self, size: int) -> list[int]:
        """Templates that a run of so many bigrams can match at all."""
        return [i for i, s in enumerate(self.sizes) if 2 * min(s, size) / (s + size) >= self.threshold]

    def longest(self, t: int) -> int:
        """Bigrams of the longest run that can match a template."""
        return int(self.sizes[t] * (2 - self.threshold) / self.threshold + 1e-9)

    @functools.cached_property
    def having(self) -> dict[tuple[str, str], list[int]]:
        """The templates with a bigram."""
        out: dict[tuple[str, str], list[int]] = {}
        for t, grams in enumerate(self.grams):
            for g in grams:
                out.setdefault(g, []).append(t)
        return out

    @functools.cached_property
    def single(self) -> bool:
        return any(not g[1] for g in self.known)


def find_licenses(text: str, templates: Templates) -> list[tuple[str, int, int, float]]:
    """(name, start, end, dice) of the matches in a text, by start; code points, end exclusive."""
    words: list[str] = []
    spans: list[tuple[int, int]] = []
    for m in _WORD.finditer(text):
        for w in normal(m[0]):  # lower case can split a word
            words.append(w)
            spans.append(m.span())
    at: dict[int, list[int]] = {}  # of each template, the positions of bigrams that it shares
    for i, g in enumerate(zip(words, words[1:], strict=False)):
        for t in templates.having.get(g, ()):
            at.setdefault(t, []).append(i)
    if templates.single:
        for i, w in enumerate(words):
            for t in templates.having.get((w, ""), ()):
                at.setdefault(t, []).append(i)
    near = []
    for t, shared in at.items():
        last = 0 if (words[shared[0]], "") in templates.grams[t] else 1  # words of a bigram after its first
        own = [(d, *_whole_lines(text, spans[i][0], spans[j + last][1]), templates.names[t]) for d, i, j in _windows(words, shared, templates, t)]
        near += _best(own)
    return [(n, a, b, d) for d, a, b, n in sorted(_best([x for x in near if not any(x[3] == y[3] and y[1] <= x[1] and x[2] <= y[2] and y[2] - y[1] > x[2] - x[1] for y in near)]), key=lambda x: (x[1], x[2]))]


def _windows(words: list[str], shared: list[int], templates: Templates, t: int) -> Iterator[tuple[float, int, int]]:
    """(dice, first, last) of runs between shared bigrams that reach the threshold with a template."""
    grams, size, most = templates.grams[t], templates.sizes[t], templates.longest(t)
    need = max(1, math.ceil(templates.threshold * size / (2 - templates.threshold) - 1e-9))  # fewer common bigrams can't reach it
    for k, i in enumerate(shared):
        if k + need > len(shared) or shared[k + need - 1] - i >= most:
            continue
        seen: Counter = Counter()
        common = 0
        for j in itertools.islice(shared, k, None):
            if j - i >= most:
                break
            g = (words[i], "") if (words[i], "") in grams else (words[j], words[j + 1])
            seen[g] += 1
            common += seen[g] <= grams[g]
            d = 2 * common / (size + j - i + 1)
            if d >= templates.threshold:
                yield d, i, j


def _whole_lines(text: str, start: int, end: int) -> tuple[int, int]:
    """A run that has all words of its first or last line takes the line's other characters too."""
    low = text.rfind("\n", 0, start) + 1
    high = text.find("\n", end)
    high = len(text) if high < 0 else high
    return start if _WORD.search(text, low, start) else low, end if _WORD.search(text, end, high) else high


def _best(found: list[tuple[float, int, int, str]]) -> list[tuple[float, int, int, str]]:
    """Of overlapping (dice, start, end, name) the best: longer, then earlier, then smaller name on ties."""
    kept: list[tuple[float, int, int, str]] = []
    starts: list[tuple[int, int]] = []
    for x in sorted(found, key=lambda x: (-x[0], x[1] - x[2], x[1], x[3])):
        k = bisect.bisect(starts, (x[1], x[2]))
        if (k == 0 or starts[k - 1][1] <= x[1]) and (k == len(starts) or x[2] <= starts[k][0]):
            starts.insert(k, (x[1], x[2]))
            kept.append(x)
    return kept


def scan(docs: DataFrame, templates=TEMPLATES, threshold: float = THRESHOLD, text: str = "text", out: str = "license_matches") -> DataFrame:
    """docs with the licences found in each whole text as spans (license, start, end, dice)."""
    small_batches(docs.sparkSession)
    known = Templates.of(templates, threshold)

    @F.pandas_udf(MATCHES)
    def matched(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in texts:
            yield pd.Series([[{"license": n, "start": a, "end": b, "dice": d} for n, a, b, d in find_licenses(t or "", known)] for t in batch], dtype=object)

    return docs.withColumn(out, matched(F.col(text)))


def describe(matches: Column) -> Column:
    """license:start:end of each match, comma-joined."""
    return F.array_join(F.transform(matches, lambda m: F.concat_ws(":", m["license"], m["start"].cast("string"), m["end"].cast("string"))), ",")
