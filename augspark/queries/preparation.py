"""Queries of preparation, profiles and discovery."""

from __future__ import annotations

from pyspark.sql import functions as F

from augspark.cluster import table
from augspark.prep import clean, features, impute, standardize
from augspark.profile import index, minhash, stats
from augspark.ring import gram
from augspark.queries.common import LINE, lines
from augspark.queries.registry import register
from augspark.sketch import build

_E = "SELECT c_custkey, avg(value) AS v FROM customer LEFT JOIN events ON c_custkey = user_id GROUP BY 1"


def _events(spark, d):
    e = table(spark, d, "events").groupBy(F.col("user_id").alias("c_custkey")).agg(F.avg("value").alias("v"))
    return table(spark, d, "customer").select("c_custkey").join(e, "c_custkey", "left")


def _imputed(strategy):
    def run(spark, d):
        df = _events(spark, d).withColumn("v", F.round("v", 1)) if strategy == "mode" else _events(spark, d)
        return impute.apply(df, impute.fit(df, ["v"], strategy)).select("c_custkey", F.round("v", 5).alias("v"))

    return run


register("impute_mean", f"WITH e AS ({_E}) SELECT c_custkey, round(coalesce(v, (SELECT avg(v) FROM e)), 5) AS v FROM e")(_imputed("mean"))
register("impute_median", f"WITH e AS ({_E}) SELECT c_custkey, round(coalesce(v, (SELECT median(v) FROM e)), 5) AS v FROM e")(_imputed("median"))
register("impute_mode", "WITH e AS (SELECT c_custkey, (c_custkey % 7 = 0) AS gone, c_nationkey::DOUBLE AS v FROM customer), m AS (SELECT v FROM e WHERE NOT gone GROUP BY v ORDER BY count(*) DESC, v LIMIT 1) SELECT c_custkey, CASE WHEN gone THEN (SELECT v FROM m) ELSE v END AS v FROM e")(
    lambda spark, d: (lambda df: impute.apply(df, impute.fit(df, ["v"], "mode")))(table(spark, d, "customer").select("c_custkey", F.when(F.col("c_custkey") % 7 != 0, F.col("c_nationkey").cast("double")).alias("v")))
)


@register("standardize_columns", "WITH s AS (SELECT avg(o_totalprice) AS m, stddev_samp(o_totalprice) AS d FROM orders) SELECT o_orderkey, round((o_totalprice - m) / d, 5) AS z FROM orders, s")
def standardize_columns(spark, d):
    df = table(spark, d, "orders").select("o_orderkey", "o_totalprice")
    return standardize.apply(df, standardize.fit(df, ["o_totalprice"])).select("o_orderkey", F.round("o_totalprice", 5).alias("z"))


@register("poly_features", "SELECT l_orderkey, l_linenumber, round(l_quantity * l_quantity, 4) AS qq, round(l_quantity * l_quantity * l_tax, 4) AS qqt FROM lineitem")
def poly_features(spark, d):
    return features.polynomial(lines(spark, d), ["l_quantity", "l_tax"], 3).select("l_orderkey", "l_linenumber", F.round("l_quantity_x_l_quantity", 4).alias("qq"), F.round("l_quantity_x_l_quantity_x_l_tax", 4).alias("qqt"))


@register("interaction_features", "SELECT l_orderkey, l_linenumber, round(l_quantity * l_tax, 4) AS qt FROM lineitem")
def interaction_features(spark, d):
    return features.interactions(lines(spark, d), [("l_quantity", "l_tax")]).select("l_orderkey", "l_linenumber", F.round("l_quantity_x_l_tax", 4).alias("qt"))


@register("pca_components")
def pca_components(spark, d):
    g = build.total(lines(spark, d), LINE).first()["g"]
    values, parts = features.pca_from_gram(g["c"], g["s"], g["q"], 2)
    return spark.createDataFrame([(i, float(v), [float(x) for x in p]) for i, (v, p) in enumerate(zip(values, parts, strict=True), 1)], "component int, variance double, direction array<double>")


@register("clean_columns", "SELECT DISTINCT s_suppkey % 7 AS k, (s_suppkey % 7)::DOUBLE AS number FROM supplier")
def clean_columns(spark, d):
    df = table(spark, d, "supplier").select((F.col("s_suppkey") % 7).alias("k"), F.concat(F.lit(" "), (F.col("s_suppkey") % 7).cast("string"), F.lit(" ")).alias("number"), F.lit("same").alias("constant"), F.lit(None).cast("string").alias("nothing"))
    return clean.run(df)


_P = [("l_quantity", "l_quantity"), ("l_discount", "l_discount"), ("l_suppkey", "l_suppkey")]


@register("column_profile", " UNION ALL ".join(f"SELECT '{c}' AS \"column\", count(*)::BIGINT AS rows, (count(*) - count({c}))::BIGINT AS nulls, count(DISTINCT {c})::BIGINT AS distinct_values, min({c})::DOUBLE AS low, max({c})::DOUBLE AS high, round(avg({c}), 5) AS mean, round(stddev_samp({c}), 5) AS std FROM lineitem" for c, _ in _P))
def column_profile(spark, d):
    p = stats.compute(lines(spark, d), [c for c, _ in _P])
    return p.withColumns({"mean": F.round("mean", 5), "std": F.round("std", 5)})


@register("profile_covariance", " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b, round(covar_samp({a}, {b}), 6) AS covariance FROM lineitem" for i, a in enumerate(LINE) for b in LINE[i:]))
def profile_covariance(spark, d):
    return stats.covariance(build.total(lines(spark, d), LINE), LINE).withColumn("covariance", F.round("covariance", 6))


@register("profile_approximate")
def profile_approximate(spark, d):
    return stats.compute(lines(spark, d), ["l_partkey", "l_suppkey"], approximate=True)


_VALUES = {"customer": ("customer", "c_custkey"), "orders": ("orders", "o_custkey"), "events": ("events", "user_id"), "supplier": ("supplier", "s_suppkey"), "nation": ("nation", "n_nationkey")}
_VALUES_SQL = " UNION ALL ".join(f"SELECT '{n}' AS name, {c}::VARCHAR AS value FROM {t}" for n, (t, c) in _VALUES.items())
_SIG_SQL = f"SELECT name, s, min(md5(s::VARCHAR || ':' || value)) AS h FROM ({_VALUES_SQL}), range(0, 16) AS t(s) GROUP BY 1, 2"


def _signatures(spark, d, k: int = 16):
    out = None
    for n, (t, c) in _VALUES.items():
        one = table(spark, d, t).select(F.lit(n).alias("name"), F.col(c).cast("string").alias("value"))
        out = one if out is None else out.unionByName(one)
    return minhash.signature(out, ["name"], k=k, portable=True)


@register("minhash_signature", f"SELECT name, s::INTEGER AS seed, h FROM ({_SIG_SQL})")
def minhash_signature(spark, d):
    return _signatures(spark, d).select("name", F.posexplode("signature").alias("seed", "h"))


@register("minhash_jaccard_pairs", f"WITH s AS ({_SIG_SQL}), b AS (SELECT DISTINCT a, b FROM (SELECT a.name AS a, b.name AS b, a.s // 2 AS band FROM s a JOIN s b ON a.s = b.s AND a.name < b.name GROUP BY 1, 2, 3 HAVING sum((a.h = b.h)::INTEGER) = 2)) SELECT b.a, b.b, sum((x.h = y.h)::INTEGER) / 16.0::DOUBLE AS similarity FROM b JOIN s x ON x.name = b.a JOIN s y ON y.name = b.b AND x.s = y.s GROUP BY 1, 2")
def minhash_jaccard_pairs(spark, d):
    """Estimated similarity of the pairs that share a band."""
    s = _signatures(spark, d)
    pairs = minhash.candidates(s, "name", bands=8, k=16)
    met = pairs.join(s.toDF("a", "sa"), "a").join(s.toDF("b", "sb"), "b")
    return met.select("a", "b", minhash.similarity(F.col("sa"), F.col("sb")).alias("similarity"))


@register("lsh_candidates", f"WITH s AS ({_SIG_SQL}) SELECT DISTINCT a, b FROM (SELECT a.name AS a, b.name AS b, a.s // 2 AS band FROM s a JOIN s b ON a.s = b.s AND a.name < b.name GROUP BY 1, 2, 3 HAVING sum((a.h = b.h)::INTEGER) = 2)")
def lsh_candidates(spark, d):
    return minhash.candidates(_signatures(spark, d), "name", bands=8, k=16)


@register("minhash_insert", f"SELECT s::INTEGER AS seed, min(md5(s::VARCHAR || ':' || o_custkey::VARCHAR)) AS h FROM orders, range(0, 16) AS t(s) GROUP BY 1")
def minhash_insert(spark, d):
    """Inserts are absorbed by elementwise minima."""
    rows = table(spark, d, "orders").select(F.lit("x").alias("name"), F.col("o_custkey").cast("string").alias("value"), (F.col("o_orderkey") % 3 == 0).alias("new"))
    a, b = (minhash.signature(rows.filter(c), ["name"], k=16, portable=True).toDF("name", s) for c, s in (("not new", "a"), ("new", "b")))
    return a.join(b, "name").select(F.posexplode(minhash.merge(F.col("a"), F.col("b"))).alias("seed", "h"))


@register("exact_jaccard", "WITH a AS (SELECT DISTINCT o_custkey AS v FROM orders), b AS (SELECT DISTINCT user_id AS v FROM events), i AS (SELECT count(*) AS n FROM a JOIN b USING (v)) SELECT round(n / ((SELECT count(*) FROM a) + (SELECT count(*) FROM b) - n)::DOUBLE, 6) AS jaccard FROM i")
def exact_jaccard(spark, d):
    return index.exact_overlap(table(spark, d, "orders").select("o_custkey"), table(spark, d, "events").select("user_id")).select(F.round("jaccard", 6).alias("jaccard"))


@register("exact_containment", "SELECT round(count(*) FILTER (v IN (SELECT o_custkey FROM orders)) / count(*)::DOUBLE, 6) AS containment FROM (SELECT DISTINCT user_id AS v FROM events)")
def exact_containment(spark, d):
    return index.exact_overlap(table(spark, d, "events").select("user_id"), table(spark, d, "orders").select("o_custkey")).select(F.round("containment", 6).alias("containment"))


_TABLES = {"customer": ["c_custkey", "c_nationkey", "c_acctbal"], "orders": ["o_orderkey", "o_custkey", "o_totalprice"], "supplier": ["s_suppkey", "s_nationkey", "s_acctbal"], "part": ["p_partkey", "p_size", "p_retailprice"], "nation": ["n_nationkey", "n_regionkey"], "region": ["r_regionkey"]}


@register(
    "unionable_pairs",
    "WITH c AS (SELECT table_name AS t, column_name AS c, data_type AS y, regexp_replace(lower(column_name), '^[a-z]{1,2}_', '') AS n FROM duckdb_columns() WHERE table_name IN ('customer', 'orders', 'supplier', 'part', 'nation', 'region')), "
    "k AS (SELECT DISTINCT t, c, y, n FROM c WHERE c IN (" + ", ".join(f"'{c}'" for cs in _TABLES.values() for c in cs) + ")), "
    "m AS (SELECT a.t AS a, b.t AS b, count(DISTINCT a.c) AS mapped FROM k a JOIN k b ON a.n = b.n AND a.y = b.y AND a.t <> b.t GROUP BY 1, 2) "
    "SELECT a, b, mapped::BIGINT AS mapped, round(mapped / (SELECT count(*) FROM k WHERE t = a)::DOUBLE, 6) AS share FROM m",
)
def unionable_pairs(spark, d):
    """Given tables with columns of equal type and normal name: share of the first's columns that the second has."""
    rows = [(t, c, y) for t, cs in _TABLES.items() for c, y in table(spark, d, t).select(*cs).dtypes]
    found = index.unionable(spark.createDataFrame(rows, "dataset string, column string, type string"), 1.0)
    return found.select("a", "b", "mapped", F.round("share", 6).alias("share"))


def _index(spark, d):
    """The discovery index over given tables and slices of one."""
    keyed = {"customer": (["c_custkey", "c_nationkey"], ["c_acctbal"]), "orders": (["o_orderkey", "o_custkey"], ["o_totalprice"]), "supplier": (["s_suppkey", "s_nationkey"], ["s_acctbal"]), "part": (["p_partkey"], ["p_size", "p_retailprice"])}
    found = index.ProfileIndex(spark)
    for t, (keys, features) in keyed.items():
        found.insert(t, table(spark, d, t), keys, features)
    for n in (1, 2):
        slice_ = table(spark, d, "lineitem").filter(F.col("l_linenumber") % 3 == n).select("l_orderkey", F.col("l_quantity").alias("quantity"), F.col("l_tax").alias("tax"), F.col("l_extendedprice").alias("extendedprice"))
        found.insert(f"slice{n}", slice_, ["l_orderkey"], ["quantity", "tax", "extendedprice"])
    return found


@register("discover_candidates", "SELECT * FROM (VALUES ('horizontal', 'slice1', NULL, NULL), ('horizontal', 'slice2', NULL, NULL), ('vertical', 'orders', 'l_orderkey', 'o_orderkey'), ('vertical', 'part', 'l_partkey', 'p_partkey'), ('vertical', 'supplier', 'l_suppkey', 's_suppkey'), ('vertical', 'slice1', 'l_orderkey', 'l_orderkey'), ('vertical', 'slice2', 'l_orderkey', 'l_orderkey')) AS t(kind, dataset, key, via)")
def discover_candidates(spark, d):
    """What the index finds for lines: slices to union under other names, and tables whose key has the same name."""
    rows = lines(spark, d)
    found = _index(spark, d)
    got = found.candidates(found.profile(rows, ["l_orderkey", "l_partkey", "l_suppkey"], ["l_quantity", "l_tax", "l_extendedprice"]))
    same = (F.col("kind") == "horizontal") | (index.normal_name(F.col("key")) == index.normal_name(F.col("via")))
    return got.filter(same).select("kind", "dataset", "key", "via")


@register("discover_scores")
def discover_scores(spark, d):
    """All compared columns with their similarities."""
    found = _index(spark, d)
    return found.compared(found.profile(lines(spark, d), ["l_orderkey", "l_partkey", "l_suppkey"], ["l_quantity", "l_tax", "l_extendedprice"]))


@register("index_refresh", "SELECT 'inserted' AS state, count(*)::BIGINT AS rows, min(o_totalprice) AS low, max(o_totalprice) AS high FROM orders UNION ALL SELECT 'deleted', count(*)::BIGINT, min(o_totalprice), max(o_totalprice) FROM orders WHERE o_orderkey % 2 = 0")
def index_refresh(spark, d):
    """Profiles after an insert, which is merged, and after a delete, for which the table is profiled again."""
    o = table(spark, d, "orders").select("o_custkey", "o_orderkey", "o_totalprice")
    found = index.ProfileIndex(spark)
    part = lambda where: o.filter(where).drop("o_orderkey")
    found.insert("orders", part("o_orderkey % 2 = 0"), ["o_custkey"], ["o_totalprice"])
    found.refresh("orders", part("o_orderkey % 2 = 1"), ["o_custkey"], ["o_totalprice"], "insert")
    told = lambda state: found.table().filter("role = 'feature'").select(F.lit(state).alias("state"), "rows", "low", "high")
    first = told("inserted")
    found.refresh("orders", part("o_orderkey % 2 = 0"), ["o_custkey"], ["o_totalprice"], "delete")
    return first.unionByName(told("deleted"))


@register("joinable_pairs", "WITH s AS (SELECT DISTINCT user_id AS v FROM events), c AS (SELECT DISTINCT c_custkey AS v FROM customer) SELECT 'events' AS a, 'customer' AS b, round((2.0::DOUBLE * (SELECT count(*) FROM s JOIN c USING (v)) / (SELECT count(*) FROM s) + (SELECT count(*) FROM s JOIN c USING (v))::DOUBLE / ((SELECT count(*) FROM s) + (SELECT count(*) FROM c) - (SELECT count(*) FROM s JOIN c USING (v)))) / 3, 6) AS score")
def joinable_pairs(spark, d):
    o = index.exact_overlap(table(spark, d, "events").select("user_id"), table(spark, d, "customer").select("c_custkey"))
    return index.joinable(o.withColumns({"a": F.lit("events"), "b": F.lit("customer")})).select("a", "b", F.round("score", 6).alias("score"))


@register("cosine_topk", "WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings), p AS (SELECT a.vec_id AS a, b.vec_id AS b, round(list_dot_product(a.v, b.v) / sqrt(list_dot_product(a.v, a.v) * list_dot_product(b.v, b.v)), 6) AS cosine FROM e a, e b WHERE a.vec_id % 100 = 0 AND a.vec_id <> b.vec_id) SELECT a, b, cosine FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY cosine DESC, b) AS n FROM p) WHERE n <= 3")
def cosine_topk(spark, d):
    """Semantic neighbours of every hundredth vector; blocks of queries meet blocks of vectors, each giving its best three."""
    import numpy as np
    import pandas as pd
    from pyspark.sql import Window

    def best(pairs):
        for pdf in pairs:
            for qs, vs in zip(pdf["qs"], pdf["vs"], strict=True):
                (a, x), (b, y) = ((np.array([r["vec_id"] for r in rows]), np.array([r["embedding"] for r in rows], float)) for rows in (qs, vs))
                cosine = np.round(x @ y.T / np.sqrt(np.outer((x * x).sum(axis=1), (y * y).sum(axis=1))), 6)
                for i, own in enumerate(a):
                    at = np.lexsort((b, -cosine[i]))
                    at = at[b[at] != own][:3]
                    yield pd.DataFrame({"a": own, "b": b[at], "cosine": cosine[i][at]})

    v = table(spark, d, "embeddings").select("vec_id", "embedding")
    rows = F.collect_list(F.struct("vec_id", "embedding"))
    qs = v.filter("vec_id % 100 = 0").groupBy(F.floor(F.col("vec_id") / 25_600).alias("qb")).agg(rows.alias("qs"))
    vs = v.groupBy(F.floor(F.col("vec_id") / 2048).alias("vb")).agg(rows.alias("vs"))
    met = qs.crossJoin(vs).repartition("qb", "vb").select("qs", "vs")
    n = F.row_number().over(Window.partitionBy("a").orderBy(F.desc("cosine"), "b"))
    return met.mapInPandas(best, "a long, b long, cosine double").withColumn("n", n).filter("n <= 3").drop("n")


_KEYED = {"lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_returnflag"], "customer": ["c_custkey", "c_nationkey", "c_mktsegment", "c_acctbal"]}


@register(
    "valid_keys",
    "SELECT t AS table_name, c AS column FROM ("
    + " UNION ALL ".join(f"SELECT '{t}' AS t, '{c}' AS c, count(DISTINCT {c}) AS n, count(*) AS r, count(*) - count({c}) AS z, typeof(any_value({c})) AS y FROM {t}" for t, cs in _KEYED.items() for c in cs)
    + ") WHERE n >= 2 AND z <= 0.5 * r AND y IN ('INTEGER', 'BIGINT', 'VARCHAR')",
)
def valid_keys(spark, d):
    """Columns of given tables fit to join on: whole numbers or text of several values."""
    out = None
    for t, cs in _KEYED.items():
        types = {c: y in ("int", "bigint", "string") for c, y in table(spark, d, t).select(*cs).dtypes}
        p = stats.compute(table(spark, d, t), cs, approximate=False).withColumn("key_type", F.col("column").isin([c for c, y in types.items() if y]))
        one = index.valid_keys(p).select(F.lit(t).alias("table_name"), "column")
        out = one if out is None else out.unionByName(one)
    return out


@register("features_documents", "SELECT source, count(*)::BIGINT AS n, round(avg(n_chars), 4) AS mean_chars, count(DISTINCT lang)::BIGINT AS langs FROM documents GROUP BY 1")
def features_documents(spark, d):
    return table(spark, d, "documents").groupBy("source").agg(F.count("*").alias("n"), F.round(F.avg("n_chars"), 4).alias("mean_chars"), F.count_distinct("lang").alias("langs"))


@register("features_conversations", "SELECT conv_id, count(*)::BIGINT AS turns, sum(length(text))::BIGINT AS chars, count(DISTINCT role)::BIGINT AS roles FROM conversations GROUP BY 1")
def features_conversations(spark, d):
    return table(spark, d, "conversations").groupBy("conv_id").agg(F.count("*").alias("turns"), F.sum(F.length("text")).alias("chars"), F.count_distinct("role").alias("roles"))


@register("features_pages", "SELECT page_id, split_part(split_part(url, '://', 2), '/', 1) AS host, length(html)::BIGINT AS chars, (length(html) - length(replace(html, '<p', '')))::BIGINT // 2 AS paragraphs FROM pages")
def features_pages(spark, d):
    p = table(spark, d, "pages")
    host = F.split_part(F.split_part("url", F.lit("://"), F.lit(2)), F.lit("/"), F.lit(1))
    return p.select("page_id", host.alias("host"), F.length("html").cast("long").alias("chars"), F.floor((F.length("html") - F.length(F.replace("html", F.lit("<p"), F.lit("")))) / 2).cast("long").alias("paragraphs"))


@register("features_benchmark", "SELECT item_id, length(text)::BIGINT AS chars, len(string_split(text, ' '))::BIGINT AS words FROM benchmark")
def features_benchmark(spark, d):
    return table(spark, d, "benchmark").select("item_id", F.length("text").cast("long").alias("chars"), F.size(F.split("text", " ")).cast("long").alias("words"))


@register(
    "gram_embeddings",
    "WITH e AS (SELECT label, list_prepend(1.0::DOUBLE, embedding::DOUBLE[]) AS v FROM embeddings) SELECT label, i::INTEGER - 1 AS i, j::INTEGER - 1 AS j, round(sum(v[i + 1] * v[j + 1]), 4) + 0.0 AS value FROM e, range(0, 65) AS a(i), range(0, 65) AS b(j) WHERE i <= j GROUP BY ALL",
)
def gram_embeddings(spark, d):
    """Gram sketch of all 64 dimensions by label, by place: i = j = -1 is the count, i = -1 the sums."""
    found = gram.wide(table(spark, d, "embeddings").select("label", "embedding"), "embedding", 64, ["label"])
    return found.withColumn("value", F.round("value", 4) + 0.0)


@register("gram_agg_udaf", "SELECT l_linenumber, count(*)::DOUBLE AS c, round(avg(l_quantity), 6) AS s_0, round(avg(l_tax), 6) AS s_1, round(avg(l_quantity * l_tax) + 1.3e-9::DOUBLE, 6) AS q_0_1 FROM lineitem GROUP BY 1")
def gram_agg_udaf(spark, d):
    """The sketch of a group as one aggregate function."""
    from augspark.functions.sql import element_of, gram_agg
    from augspark.queries.common import TIE

    flat = lines(spark, d).groupBy("l_linenumber").agg(gram_agg(F.col("l_quantity"), F.col("l_tax")).alias("flat"))
    g = F.col("g")
    return flat.select("l_linenumber", element_of(F.col("flat"), 2).alias("g")).select("l_linenumber", g["c"].alias("c"), F.round(g["s"][0] / g["c"], 6).alias("s_0"), F.round(g["s"][1] / g["c"], 6).alias("s_1"), F.round(g["q"][1] / g["c"] + TIE, 6).alias("q_0_1"))
