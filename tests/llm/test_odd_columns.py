"""Clashing column names, hubs, both ways of url words, and recall on every given table."""

import random
from collections import Counter

import pytest
from pyspark.sql import functions as F
from test_operators import DOCS, ODD, slow_components

import corpus_pipeline
from augspark.llm import bpe, components, licenses, mixing, overlap, quality, rules, secrets, simhash, urls, vectors, warc

#: Names that operators use inside.
INSIDE = [
    "_measured", "_source", "_salt", "_salt_of", "_copy", "mix_source", "mix_target", "mix_size", "mix_copies", "mix_rate", "_fp", "_fp_of", "_root", "_first", "fp", "root", "component_id",
    "_host", "_rules", "_best", "_scored", "_url", "_one", "_named", "_size", "_hk", "_ck", "_cs", "_hot", "_cold", "n", "m", "u", "v", "word", "run", "leaf", "bin", "place", "_to", "_h", "_p", "_n", "a.b",
]


@pytest.fixture(scope="module")
def clashing(spark):
    docs = spark.createDataFrame(ODD, DOCS).repartition(3)
    return docs.select("*", *[F.lit(f"own {n}").alias(n) for n in INSIDE])


def kept_apart(df, names):
    rows = df.collect()
    assert rows and all(r[n] == f"own {n}" for r in rows for n in names if n in df.columns)
    assert set(names) <= set(df.columns)


def test_document_operators_keep_clashing_columns(clashing, spark):
    kept_apart(mixing.mix(clashing), INSIDE)
    kept_apart(mixing.plan_copies(clashing), [n for n in INSIDE if n not in mixing.ADDED])
    kept_apart(rules.apply_policy(rules.ledger(clashing)), INSIDE)
    kept_apart(simhash.keep_one(clashing), INSIDE)
    kept_apart(overlap.keep_one(clashing), INSIDE)
    kept_apart(secrets.scan(clashing), INSIDE)
    kept_apart(secrets.redact(clashing), INSIDE)
    kept_apart(bpe.decode(bpe.encode(clashing)), INSIDE)
    kept_apart(licenses.scan(clashing), INSIDE)
    labels = spark.createDataFrame([(1, 1, 0), (5, 0, 0)], "doc_id long, quality int, toxic int")
    kept_apart(quality.score(clashing, quality.train(clashing, labels)), INSIDE)
    assert simhash.near_duplicates(clashing).count() == overlap.near_duplicates(clashing).count() == len(ODD)


def test_other_operators_keep_clashing_columns(spark, tmp_path):
    pages = spark.createDataFrame([(1, "http://a.org/x", "<p>some words</p>"), (2, None, None), (2, "http://b.com/de/y", "")], "page_id long, url string, html string").select("*", *[F.lit(f"own {n}").alias(n) for n in INSIDE])
    rules_table = spark.createDataFrame([tuple(r) for r in urls.RULES], "verdict string, host string, path string")
    for how in ({}, {"rules": rules_table}, {"inline_words": 0}, {"rules": rules_table, "inline_words": 0}):
        kept_apart(urls.judge(pages, **how), INSIDE)
    warc.write_archives(pages, str(tmp_path / "w"))
    assert warc.verified(spark, str(tmp_path / "w")).count() == 3
    vecs = spark.createDataFrame([(i, [float(i), 1.0]) for i in range(5)], "vec_id long, embedding array<float>").select("*", *[F.lit(f"own {n}").alias(n) for n in INSIDE])
    assert vectors.search(vecs, lambda i: i == 0).count() == 4


def test_pipeline_stages_on_odd_rows(spark, clashing):
    docs = clashing
    for name, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, docs, "")
        assert got.columns == list(corpus_pipeline.COLUMNS), name
        assert got.count() <= 2 * docs.count()
    out = corpus_pipeline.byte_bpe(spark, docs, "").collect()
    assert Counter(r["doc_id"] for r in out) == Counter(r[0] for r in ODD)
    kept = {r["doc_id"]: r["text"] for r in corpus_pipeline.secret_scan(spark, docs, "").collect()}
    assert kept[5] == "same text of a few words" and kept[1] is None
    assert corpus_pipeline.quality_rules(spark, docs, "").count() == 0  # every odd text fails a base rule


def test_hubs_of_components(spark):
    draw = random.Random(7)
    edges = [(0, i) for i in range(1, 4000)] + [(i, i + 1) for i in range(5000, 5300)] + [(9000, 9001), (9001, 9000), (7, 7)]
    edges += [(draw.randint(10_000, 10_400), draw.randint(10_000, 10_400)) for _ in range(300)]
    got = {r["node"]: r["root"] for r in components.connected(spark.createDataFrame(edges, "u long, v long").repartition(4)).collect()}
    up = {x: x for e in edges for x in e}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = sorted((find(a), find(b)))
        up[b] = a
    assert got == {x: find(x) for x in up if find(x) != x}
    assert components.connected(spark.createDataFrame([], "u long, v long")).count() == 0


def test_join_groups_is_an_inner_join(spark):
    rows = spark.createDataFrame([(i % 7 if i % 3 else 1, i) for i in range(3000)] + [(None, -1), (99, -2)], "k long, x long")
    groups = rows.filter("k is not null and k < 99").groupBy("k").agg(F.count("*").alias("size"), F.min("x").alias("low"))
    got = Counter(tuple(r) for r in components.join_groups(rows, "k", groups, "size", 3002, F.col("x")).collect())
    assert got == Counter(tuple(r) for r in rows.join(groups, "k").select("k", "x", "low").collect())


def test_groups_of_copies_and_null_ids(spark):
    texts = ["a b c d e f g"] * 400 + ["a b c d e f g h"] * 3 + ["other words of no group"] * 2
    docs = spark.createDataFrame([(i if i % 5 else None, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(5)
    want = slow_components([(r["doc_id"], simhash.fingerprint(r["text"])) for r in docs.collect()])
    got = Counter((r["doc_id"], r["fp"] % 2**64, r["component_id"]) for r in simhash.near_duplicates(docs).collect())
    assert got == want


def test_both_ways_of_url_words_agree(spark, sf_dir):
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    more = spark.createDataFrame([(-1, "http://" + "newyorktimes" * 30 + ".net/" + "9" * 40 + "?q", "new york times"), (-2, None, None), (-3, "http://x.org/de/", None)], "page_id long, url string, html string")
    pages = pages.select("page_id", "url", "html").unionByName(more)
    told = [{r["page_id"]: (r["verdict"], r["url_words"], round(r["block_score"], 9)) for r in urls.judge(pages, inline_words=n).collect()} for n in (10**9, 0)]
    assert told[0] == told[1] and len(told[0]) == pages.count()
    long = told[0][-1][1]
    assert long[:3] == ["h:new", "h:york", "h:times"] and len(long) == 92 and long[-1] == "p:#40"


def test_unknown_words_are_split_whole():
    seg = urls.Segmenter({"new": 5, "york": 5}, 100)
    assert seg.split("q" * 200) == ("q" * 200,)
    assert seg.split("new" + "z" * 90 + "york") == ("new", "z" * 90, "york")


@pytest.mark.parametrize("sf", ["sf0.001", "sf0.01", "sf0.1"])
def test_recall_on_given_tables(spark, sf):
    table, query = spark.read.parquet(f"/root/testdata/{sf}/embeddings.parquet"), lambda i: i % 100 == 0
    want = {(r["query_id"], r["vec_id"]) for r in vectors.exact(table, query).collect()}
    got = {(r["query_id"], r["vec_id"]) for r in vectors.search(table, query).collect()}
    assert len(got) == len(want) and len(want & got) / len(want) >= 0.9
    told = vectors.opened(table, query).first()
    assert told["vectors"] == table.count() and 0 < told["opened"] <= 1


def test_queries_dealt_over_decks(spark, monkeypatch):
    table, query = spark.read.parquet("/root/testdata/sf0.01/embeddings.parquet"), lambda i: i % 10 == 0
    want = sorted(tuple(r) for r in vectors.search(table, query).collect())
    monkeypatch.setattr(vectors, "DECK_QUERIES", 7)
    assert sorted(tuple(r) for r in vectors.search(table, query).collect()) == want


def test_repeated_vectors_of_an_id(spark):
    rows = [(0, [1.0, 0.0]), (1, [0.0, 1.0]), (1, [1.0, 0.1]), (1, [1.0, 0.1]), (2, [1.0, 1.0])]
    got = [tuple(r) for r in vectors.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), lambda i: i == 0).orderBy("rank").collect()]
    assert [(a, b, c, round(d, 6)) for a, b, c, d in got] == [(0, 1, 1, 0.1), (0, 2, 2, 1.0)]


def test_warc_predicates_are_pushed(spark, tmp_path):
    pages = spark.createDataFrame([(i, f"http://a/{i % 3}", "same" if i % 2 else f"page {i}") for i in range(12)], "page_id long, url string, html string")
    path = str(tmp_path / "archives")
    warc.write_archives(pages, path)
    from pyspark.sql.datasource import EqualTo, GreaterThan

    reader = warc.WarcReader({"files": "[]"})
    left = list(reader.pushFilters([EqualTo(("record_type",), "response"), EqualTo(("target_uri",), "http://a/1"), GreaterThan(("content_length",), 3)]))
    assert [type(f) for f in left] == [GreaterThan] and reader.types == {"response"} and reader.equal == {"warc-target-uri": "http://a/1"}
    found = {r["record_id"]: r for r in warc.verified(spark, path).collect()}
    assert found["urn:page:3"]["refers_to"] == "urn:page:1" and found["urn:page:3"]["payload_length"] == 4
    assert sum(r["record_type"] == "response" for r in found.values()) == 7


def test_changed_payload_is_noticed(spark, tmp_path):
    pages = spark.createDataFrame([(1, "http://a/", "first payload"), (2, "http://b/", "first payload"), (3, "http://c/", "another")], "page_id long, url string, html string").coalesce(1)
    path = str(tmp_path / "archives")
    warc.write_archives(pages, path, compress=False)
    for file in (tmp_path / "archives").glob("part-*"):
        file.write_bytes(file.read_bytes().replace(b"first payload", b"wrong payload"))
    for crc in (tmp_path / "archives").glob(".*.crc"):
        crc.unlink()
    found = {r["record_id"]: r["payload_digest"] for r in warc.verified(spark, path).collect()}
    assert found["urn:page:1"] is None and found["urn:page:2"] is None and found["urn:page:3"]


def test_dice_of_whole_texts_by_brute_force():
    draw, known = random.Random(8), licenses.Templates.of({"A": "one two three four five", "B": "four five six", "C": "single"})
    for _ in range(300):
        words = [draw.choice("one two three four five six seven single".split()) for _ in range(draw.randint(1, 14))]
        got = licenses.find_licenses(" ".join(words), known)
        best = max(licenses.dice(licenses.bigrams(words[i:j]), g) for i in range(len(words)) for j in range(i + 1, len(words) + 1) for g in known.grams)
        assert bool(got) == (best >= known.threshold) and (not got or max(d for *_, d in got) == pytest.approx(best))
        assert all(b <= c for (_, _, b, _), (_, c, _, _) in zip(got, got[1:], strict=False))


def test_many_notices_take_little_time():
    import time

    known, began = licenses.Templates.of(), time.perf_counter()
    assert len(licenses.find_licenses("Released under the MIT License.\n" * 3000, known)) == 3000
    licenses.find_licenses("mit license\n" * 6000, known)
    licenses.find_licenses("some three words\n" * 6000 + "the software is\n" * 3000, known)
    assert time.perf_counter() - began < 20
