r"""Quality rules as a bitmask ledger, with DataFrame functions only.

Every rule is evaluated once; the ledger keeps its measurements and one failure bit per rule. A policy is a named mask
over those bits, so changing a policy or asking what each rule adds needs bitwise aggregation only, no text.

Words are ``[^\x20\x09-\x0D]+``. n_repeat_words counts the words that lie in any 8-word window occurring at least
twice in the text, the first occurrence included and overlaps counted once. Windows are compared by 64-bit hash chains
of their words, found by sorting inside the row: no shuffle, and n log n in the length of the text.

Defined results: a null or empty text has no words, all counts 0 and fails ``few_words``; repeated rows are judged
alike; an empty table gives an empty ledger; extra columns are carried along.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.llm.text import fresh, let, words

WINDOW = 8
SYMBOLS = r"[#*$%&|<>]"
SPACES = " \t\n\x0b\x0c\r"

#: Rules by bit: name and condition under which a text fails. Order is part of the stored format: append only.
RULES: tuple[tuple[str, str], ...] = (
    ("few_words", "n_words < 20"),
    ("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    ("many_symbols", "100 * n_symbols > 10 * n_words"),
    ("duplicate_lines", "100 * n_dup_lines > 30 * n_lines"),
    ("word_length", "n_words > 0 and (word_chars < 2 * n_words or word_chars > 15 * n_words)"),
    ("very_long", "n_words > 100000"),
)
BASE = ("few_words", "repeated_windows")
#: Versioned policies: the rules whose failure rejects a document. A rule outside a policy is measured but doesn't reject.
POLICIES: dict[str, tuple[str, ...]] = {"base": BASE, "v1": (*BASE, "many_symbols"), "strict": tuple(n for n, _ in RULES)}


def mask(names) -> int:
    bits = {name: 1 << i for i, (name, _) in enumerate(RULES)}
    return sum(bits[n] for n in set(names))


def _covered(windows: Column) -> Column:
    """Words covered by windows whose hash occurs at least twice; windows: one hash per start, in order."""
    by_hash = F.array_sort(F.transform(windows, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def starts(s: Column) -> Column:
        same = lambda x, i, j: (j >= 0) & (j < F.size(s)) & (F.get(s, j)["h"] == x["h"])
        twice = F.filter(s, lambda x, i: same(x, i, i - 1) | same(x, i, i + 1))
        return F.sort_array(F.transform(twice, lambda x: x["i"]))

    def length(p: Column) -> Column:
        gaps = F.transform(p, lambda x, i: F.least(F.lit(WINDOW), F.coalesce(F.get(p, i + 1) - x, F.lit(WINDOW))))
        return F.aggregate(gaps, F.lit(0).cast("long"), lambda a, x: a + x)

    return let(let(by_hash, starts), length)


def repeat_words(ws: Column) -> Column:
    def of_hashes(h: Column) -> Column:
        windows = F.transform(F.sequence(F.lit(0), F.size(h) - WINDOW), lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(WINDOW)]))
        found = let(windows, lambda w: F.when(F.size(F.array_distinct(w)) < F.size(w), _covered(w)).otherwise(F.lit(0).cast("long")))
        return F.when(F.size(h) > WINDOW, found).otherwise(F.lit(0).cast("long"))

    return let(F.transform(ws, lambda w: F.xxhash64(w)), of_hashes)


def ledger(docs: DataFrame) -> DataFrame:
    """docs with the measurements n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words and ``failed``.

    Columns of these names in docs are replaced; all others are carried along.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    lines = F.filter(F.split(text, "\n"), lambda x: F.btrim(x, F.lit(SPACES)) != "")
    measured = F.struct(
        let(words(F.col("text")), lambda w: F.struct(F.size(w).cast("long").alias("n_words"), F.length(F.array_join(w, "")).cast("long").alias("word_chars"), repeat_words(w).alias("n_repeat_words"))).alias("w"),
        let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"))).alias("l"),
        F.regexp_count(text, F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
    )
    (own,) = fresh(docs.columns, "_measured")
    out = docs.withColumn(own, measured).withColumns(
        {
            "n_words": F.col(f"{own}.w.n_words"),
            "word_chars": F.col(f"{own}.w.word_chars"),
            "n_symbols": F.col(f"{own}.n_symbols"),
            "n_lines": F.col(f"{own}.l.n_lines"),
            "n_dup_lines": F.col(f"{own}.l.n_dup_lines"),
            "n_repeat_words": F.col(f"{own}.w.n_repeat_words"),
        }
    )
    bits = F.lit(0).cast("long")
    for i, (_, fails) in enumerate(RULES):
        bits = bits.bitwiseOR(F.when(F.expr(fails), F.lit(1 << i)).otherwise(F.lit(0)).cast("long"))
    return out.withColumn("failed", bits).drop(own)


def apply_policy(ledger_rows: DataFrame, policy: str = "v1") -> DataFrame:
    """Adds base_failed and kept (columns of these names are replaced), decided from the stored bits alone."""
    hit = lambda names: F.col("failed").bitwiseAND(F.lit(mask(names)).cast("long")) != 0
    return ledger_rows.withColumn("base_failed", hit(BASE)).withColumn("kept", ~(hit(BASE) | hit(POLICIES[policy])))


def ablation(ledger_rows: DataFrame, policy: str = "v1") -> DataFrame:
    """Per rule of a policy: documents that fail it, and those that fail no other rule of the policy.

    One pass groups by the bits (at most 2^rules groups), then all rules are read off the counts.
    """
    counts = ledger_rows.groupBy(F.col("failed").bitwiseAND(F.lit(mask(POLICIES[policy])).cast("long")).alias("bits")).agg(F.count("*").alias("n"))
    rules = F.array(*[F.struct(F.lit(n).alias("rule"), F.lit(mask([n])).cast("long").alias("bit")) for n in POLICIES[policy]])
    each = counts.withColumn("r", F.explode(rules))
    return each.groupBy(F.col("r.rule").alias("rule")).agg(
        F.sum(F.when(F.col("bits").bitwiseAND(F.col("r.bit")) != 0, F.col("n")).otherwise(0)).alias("n_failed"),
        F.sum(F.when(F.col("bits") == F.col("r.bit"), F.col("n")).otherwise(0)).alias("n_only"),
    )
