"""URL filters: host and path rules first, then naive Bayes over segmented names.

A rule (host, path, verdict) fits its host and all subdomains where the url's path starts with the rule's; the longest
rule wins. Urls without a rule are judged by multinomial naive Bayes over the words of host and path. Concatenated
names are first split by a unigram Viterbi pass, with word counts gathered from all pages' texts: every counted word
that occurs in some url's name takes part. The model learns from urls that rules decide (a bounded sample,
``SAMPLE_ROWS``, smallest hashes). Up to ``INLINE_WORDS`` needed words are sent to the tasks, more are joined; both give
the same rows.

Defined results: a null url or one without ``://`` has empty host and path, fits no rule and is judged by the prior;
equal urls are judged alike; urls are read whole; an empty table gives an empty table; without any decided urls the
verdict is allow; extra columns of any name are carried along, but columns named host, path, rule, verdict, url_words and block_score are
replaced. Numbers in urls count by their number of digits; names are split whole, whatever their length.
"""

from __future__ import annotations

import functools
import math
import re
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.cluster import materialize
from augspark.llm.components import join_groups
from augspark.llm.text import fresh

#: (verdict, host, path) of the contract's rules.
RULES = (
    ("allow", "org", "/"),
    ("block", "example.org", "/es/"),
    ("block", "example.org", "/en/1"),
    ("allow", "com", "/fr/"),
    ("block", "com", "/de/"),
)
#: Rule lists up to this length become one expression; longer ones are joined on host suffixes.
INLINE_RULES = 200
#: So many words that urls need are sent to every task; more meet the urls by joins.
INLINE_WORDS = 200_000
SAMPLE_ROWS = 40_000
#: Cost of a letter of an unknown word.
LETTER = 2.5
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_TOKEN = re.compile(r"[a-z]+|[0-9]+")


def host(url: Column) -> Column:
    found = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(found, UPPER, LOWER)


def path(url: Column) -> Column:
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*(/[^?#]*)", 1)


def parse(pages: DataFrame) -> DataFrame:
    return pages.withColumns({"host": host(F.col("url")), "path": path(F.col("url"))})


def _inline(parsed: DataFrame, rules) -> DataFrame:
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for says, h, p in sorted(rules, key=lambda r: (len(r[1]) + len(r[2]), r[1], r[2])):
        fits = ((F.col("host") == h) | F.col("host").endswith("." + h)) & F.col("path").startswith(p)
        rule, verdict = F.when(fits, F.lit(h + p)).otherwise(rule), F.when(fits, F.lit(says)).otherwise(verdict)
    return parsed.withColumns({"rule": rule, "verdict": verdict})


def _joined(parsed: DataFrame, rules: DataFrame) -> DataFrame:
    """rules (verdict, host, path): distinct hosts meet the rules of their suffixes; a url then tries those, longest first."""
    listed_as, best_as = fresh([*parsed.columns, "rule", "verdict"], "_rules", "_best")
    labels = F.split("host", r"\.")
    suffix = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    counts = materialize(parsed.groupBy("host").agg(F.count("*").alias("_n")), "hosts")
    own = rules.select(F.col("host").alias("_suffix"), F.col("path").alias("p"), F.col("verdict").alias("v"))
    fitting = F.struct((F.length("_suffix") + F.length("p")).alias("n"), F.concat("_suffix", "p").alias("rule"), "p", "v")
    listed = counts.select(F.col("host").alias("_h"), F.explode(suffix).alias("_suffix")).join(own, "_suffix").groupBy("_h").agg(F.collect_set(fitting).alias(listed_as))
    groups = counts.join(listed, F.col("host") == F.col("_h"), "left").select("host", "_n", listed_as)
    groups = groups.withColumn(listed_as, F.coalesce(listed_as, F.array().cast(groups.schema[listed_as].dataType)))
    total = counts.agg(F.sum("_n")).first()[0] or 0
    tried = join_groups(parsed, "host", groups, "_n", total, F.xxhash64("path", F.monotonically_increasing_id()))
    best = F.array_max(F.filter(listed_as, lambda r: F.col("path").startswith(r["p"])))
    return tried.withColumn(best_as, best).withColumns({"rule": F.col(f"{best_as}.rule"), "verdict": F.col(f"{best_as}.v")}).drop(listed_as, best_as)


def apply_rules(parsed: DataFrame, rules=RULES) -> DataFrame:
    """parsed with the longest fitting rule and its verdict, or nulls."""
    if isinstance(rules, DataFrame):
        return _joined(parsed, rules)
    if len(rules) <= INLINE_RULES:
        return _inline(parsed, rules)
    return _joined(parsed, parsed.sparkSession.createDataFrame([tuple(r) for r in rules], "verdict string, host string, path string"))


def visible_words(pages: DataFrame) -> DataFrame:
    """(word, n): the words of all pages' visible texts; counted before the shuffle, so frequent words are a row a task."""
    seen = F.regexp_replace(F.lower(F.coalesce("html", F.lit(""))), r"(?s)<(script|style)[^>]*>.*?</\1>|<[^>]*>", " ")
    each = pages.select(F.explode(F.regexp_extract_all(seen, F.lit("[a-z]+"), 0)).alias("word"))
    return each.groupBy("word").agg(F.count("*").alias("n"))


def runs(host: Column, path: Column) -> Column:
    """The letter and digit runs of a url: (p: is it the path's, run), in order."""
    found = lambda text, of_path: F.transform(F.regexp_extract_all(text, F.lit("[a-z]+|[0-9]+"), 0), lambda r: F.struct(F.lit(of_path).alias("p"), r.alias("run")))
    return F.concat(found(host, False), found(F.lower(path), True))


def letter_runs(parsed: DataFrame) -> DataFrame:
    """(run): the distinct letter runs of all urls."""
    both = F.concat(F.coalesce("host", F.lit("")), F.lit(" "), F.lower(F.coalesce("path", F.lit(""))))
    return parsed.select(F.explode(F.regexp_extract_all(both, F.lit("[a-z]+"), 0)).alias("run")).distinct()


def needed_words(parsed: DataFrame, words: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """((run, word, n), (word, n), all occurrences): the counted words that occur in a letter run of any url, by run and alone.

    No other word can be part of a split, so leaving them out changes no result. Both sides are distinct before they
    meet; pieces longer than the longest word are not formed.
    """
    counted = materialize(words, "page-words")
    total, longest = counted.agg(F.sum("n"), F.max(F.length("word"))).first()
    found = materialize(letter_runs(parsed), "letter-runs")
    cut = lambda i: F.transform(F.sequence(F.lit(1), F.least(F.length("run") - i + 1, F.lit(longest or 1))), lambda n: F.substring(F.col("run"), i, n))
    pieces = found.select("run", F.explode(F.array_distinct(F.flatten(F.transform(F.sequence(F.lit(1), F.length("run")), cut)))).alias("word"))
    by_run = materialize(pieces.join(counted, "word").select("run", "word", "n"), "words-of-runs")
    return by_run, by_run.select("word", "n").distinct(), int(total or 0)


class Segmenter:
    """Splits a name into its likeliest words; an unknown word of any length costs more the longer it is."""

    def __init__(self, counts: dict[str, int], total: int | None = None) -> None:
        total = max(1, sum(counts.values()) if total is None else total)
        self.cost = {w: math.log(total / n) for w, n in counts.items()}
        self.unknown = math.log(total) + 1
        self.longest = max(map(len, counts), default=1)
        self.split = functools.lru_cache(100_000)(self._split)

    def _split(self, name: str) -> tuple[str, ...]:
        best: list[tuple[float, int]] = [(0.0, 0)]
        lead = (0.0, 0)  # the cheapest start of an unknown word, less its letters' cost
        for end in range(1, len(name) + 1):
            found = (lead[0] + self.unknown + LETTER * end, lead[1])
            for start in range(max(0, end - self.longest), end):
                cost = self.cost.get(name[start:end])
                if cost is not None:
                    found = min(found, (best[start][0] + cost, start))
            best.append(found)
            lead = min(lead, (found[0] - LETTER * end, end))
        words, end = [], len(name)
        while end:
            words.append(name[best[end][1] : end])
            end = best[end][1]
        return tuple(reversed(words))

    def run_tokens(self, of_path: bool, run: str) -> list[str]:
        """The words of a run, told apart by host and path; numbers count by their number of digits."""
        mark = "p:" if of_path else "h:"
        return [f"{mark}#{len(run)}"] if run.isdigit() else [mark + w for w in self.split(run)]

    def tokens(self, host: str, path: str) -> list[str]:
        return [t for of_path, text in ((False, host), (True, path.lower())) for run in _TOKEN.findall(text) for t in self.run_tokens(of_path, run)]


@dataclass(frozen=True)
class Bayes:
    """Log-odds of block over allow: of the prior, of each known token, and of an unknown one."""

    prior: float
    odds: dict[str, float]

    def block(self, tokens: Iterable[str]) -> float:
        return self.prior + sum(self.odds.get(t, 0.0) for t in tokens)


def fit_bayes(examples: Iterable[tuple[list[str], bool]], smooth: float = 1.0) -> Bayes:
    counts, docs = (Counter(), Counter()), [0, 0]
    for tokens, blocked in examples:
        counts[blocked].update(tokens)
        docs[blocked] += 1
    if not all(docs):
        return Bayes(0.0 if not docs[1] else 1.0, {})
    known = counts[0].keys() | counts[1].keys()
    size = [sum(c.values()) + smooth * len(known) for c in counts]
    odds = {t: math.log((counts[1][t] + smooth) / size[1]) - math.log((counts[0][t] + smooth) / size[0]) for t in known}
    return Bayes(math.log(docs[1] / docs[0]), odds)


def decided_sample(judged: DataFrame, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """(host, path, blocked): a bounded sample of the distinct urls that rules decide, the smallest hashes."""
    decided = judged.filter("rule is not null").select("host", "path", (F.col("verdict") == "block").alias("blocked")).distinct()
    decided = decided.withColumn("h", F.xxhash64("host", "path"))
    share = min(1.0, 2.0 * sample_rows / max(1, decided.count()))
    return decided.filter(F.pmod("h", F.lit(1_000_000)) < int(1_000_000 * share) + 1).orderBy("h", "host", "path").limit(sample_rows)


def _by_word_table(judged: DataFrame, by_run: DataFrame, total: int, sample_rows: int, scored_as: str) -> DataFrame:
    """``judged`` with the struct (words, score), where the words are too many to be sent to every task.

    Each distinct run is split once with the words that occur in it; urls meet their runs' words by a join in which
    frequent runs are dealt out.
    """

    @F.pandas_udf("array<string>")
    def split(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for names, known in batches:
            yield pd.Series([list(Segmenter({k["word"]: k["n"] for k in own}, total).split(r)) for r, own in zip(names, known, strict=True)], dtype=object)

    known = by_run.groupBy("run").agg(F.collect_list(F.struct("word", "n")).alias("known"))  # bounded by a run's length
    every = letter_runs(judged).join(known.withColumnRenamed("run", "_r"), F.col("run") == F.col("_r"), "left")
    words = materialize(every.select("run", split("run", F.coalesce("known", F.array().cast("array<struct<word:string,n:bigint>>"))).alias("words")), "split-runs")
    urls = judged.select("host", "path").distinct()
    each = materialize(urls.select("host", "path", F.posexplode(runs(F.col("host"), F.col("path"))).alias("at", "r")).select("host", "path", "at", "r.p", "r.run"), "runs-of-urls")
    sizes = each.groupBy("run").agg(F.count("*").alias("size"))
    total_runs = each.count()
    mark = F.when(F.col("p"), F.lit("p:")).otherwise(F.lit("h:"))
    digits = each.filter(F.col("run").rlike("^[0-9]")).withColumn("words", F.array(F.concat(F.lit("#"), F.length("run").cast("string"))))
    letters = join_groups(each.filter(~F.col("run").rlike("^[0-9]")), "run", words.join(sizes, "run"), "size", total_runs, F.xxhash64("host", "path", "at"))
    told = digits.unionByName(letters).select("host", "path", "at", F.transform("words", lambda w: F.concat(mark, w)).alias("t"))
    gathered = told.groupBy("host", "path").agg(F.flatten(F.transform(F.array_sort(F.collect_list(F.struct("at", "t"))), lambda x: x["t"])).alias("words"))  # bounded by a url's length
    gathered = materialize(gathered, "tokens-of-urls")
    sample = decided_sample(judged, sample_rows).withColumnsRenamed({"host": "_h", "path": "_p"})
    rows = sample.join(gathered, (F.col("host") == F.col("_h")) & (F.col("path") == F.col("_p")), "left").orderBy("h", "_h", "_p").collect()
    bayes = fit_bayes((r["words"] or [], r["blocked"]) for r in rows)

    @F.pandas_udf("double")
    def block(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series([bayes.block(w) for w in batch], dtype="float64")

    (url, one, named, size) = fresh(judged.columns, "_url", "_one", "_named", "_size")
    name = F.to_json(F.struct("host", "path"))
    scored = gathered.select(name.alias(url), F.struct("words", block("words").alias("score")).alias(one))
    counts = judged.groupBy(name.alias(named)).agg(F.count("*").alias(size))
    groups = counts.join(scored, F.col(named) == F.col(url), "left").select(F.col(named).alias(url), size, F.coalesce(one, F.struct(F.array().cast("array<string>").alias("words"), F.lit(float(bayes.prior)).alias("score"))).alias(scored_as))
    keyed = judged.withColumn(url, name)
    return join_groups(keyed, url, groups, size, judged.count(), F.monotonically_increasing_id()).drop(url)


def judge(pages: DataFrame, rules=RULES, sample_rows: int = SAMPLE_ROWS, inline_words: int = INLINE_WORDS) -> DataFrame:
    """pages with host, path, rule, url_words (segmented tokens), block_score and verdict."""
    judged = apply_rules(parse(pages), rules)
    by_run, words, total = needed_words(judged, visible_words(pages))
    (scored_as,) = fresh([*judged.columns, "url_words", "block_score"], "_scored")
    if words.count() <= inline_words:
        counts = {r["word"]: r["n"] for r in words.collect()}
        segmenter = Segmenter(counts, total)
        bayes = fit_bayes((segmenter.tokens(r["host"], r["path"]), r["blocked"]) for r in decided_sample(judged, sample_rows).collect())

        @F.pandas_udf("struct<words:array<string>,score:double>")
        def scored(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.DataFrame]:
            own = Segmenter(counts, total)
            for hosts, paths in batches:
                found = [own.tokens(h, p) for h, p in zip(hosts, paths, strict=True)]
                yield pd.DataFrame({"words": found, "score": [bayes.block(w) for w in found]})

        out = judged.withColumn(scored_as, scored("host", "path"))
    else:
        out = _by_word_table(judged, by_run, total, sample_rows, scored_as)
    verdict = F.coalesce("verdict", F.when(F.col(f"{scored_as}.score") > 0, "block").otherwise("allow"))
    return out.withColumns({"url_words": F.col(f"{scored_as}.words"), "block_score": F.col(f"{scored_as}.score"), "verdict": verdict}).drop(scored_as)
