"""Discovery: which tables can be unioned or joined with a request, from profiles only.

The index is one table with a row a column: counts, range, moments, a distinct-value sketch and a MinHash signature. It
is probed by a request's own profile: name tokens and signature bands are equi-join keys, so only columns that share one
of them are compared. Inserts merge profiles; deletes profile the changed table again.
"""

from __future__ import annotations

from collections.abc import Sequence
from typing import Protocol

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from augspark.cluster import scratch_path
from augspark.profile.minhash import BANDS, K, merge, similarity

PROFILE = "column string, role string, type string, rows long, nulls long, low double, high double, sum double, squares double, hll binary, signature array<bigint>"


class Discovery(Protocol):
    """Any source of candidates (kind, dataset, key, via, mapping, score) for a request's profile."""

    def profile(self, df: DataFrame, keys: Sequence[str], features: Sequence[str]) -> DataFrame: ...

    def candidates(self, profile: DataFrame, datasets: Sequence[str]) -> DataFrame: ...


def normal_name(name: Column) -> Column:
    """Lower case without table prefixes, separators and digits at the end."""
    return F.regexp_replace(F.regexp_replace(F.lower(name), r"^[a-z]{1,2}_", ""), r"[_\W]|\d+$", "")


def name_similarity(a: Column, b: Column) -> Column:
    return 1 - F.levenshtein(a, b) / F.greatest(F.length(a), F.length(b), F.lit(1))


def tokens(name: Column) -> Column:
    """What names are blocked by: the normal name and its parts of three letters or more."""
    parts = F.filter(F.split(F.lower(name), r"[_\W\d]+"), lambda t: F.length(t) >= 3)
    return F.array_distinct(F.concat(F.array(normal_name(name)), parts))


def unionable(schemas: DataFrame, least: float = 0.6) -> DataFrame:
    """(dataset, column, type) -> (a, b, mapped, share): the share of a's columns with a like-named column of equal type in b.

    Columns meet on (type, name token); a pair of datasets without such a column is never formed.
    """
    named = schemas.select("dataset", "column", "type", normal_name(F.col("column")).alias("n"), F.explode(tokens(F.col("column"))).alias("token"))
    left, right = named.toDF("a", "a_column", "type", "a_n", "token"), named.toDF("b", "b_column", "type", "b_n", "token")
    met = left.join(right, ["type", "token"]).filter((F.col("a") != F.col("b")) & (name_similarity(F.col("a_n"), F.col("b_n")) >= least))
    mapped = met.groupBy("a", "b").agg(F.count_distinct("a_column").alias("mapped"))
    sizes = schemas.groupBy(F.col("dataset").alias("a")).agg(F.count("*").alias("_n"))
    return mapped.join(sizes, "a").select("a", "b", "mapped", (F.col("mapped") / F.col("_n")).alias("share"))


def joinable(overlaps: DataFrame, least: float = 0.5) -> DataFrame:
    """(a, b, containment, jaccard) -> pairs whose values of a are mostly found in b, the best first by score."""
    return overlaps.withColumn("score", (2 * F.col("containment") + F.col("jaccard")) / 3).filter(F.col("containment") >= least)


def exact_overlap(left: DataFrame, right: DataFrame) -> DataFrame:
    """Two one-column tables -> (inter, only sizes, jaccard, containment of the left in the right)."""
    a, b = left.toDF("v").filter("v is not null").distinct().withColumn("x", F.lit(1)), right.toDF("v").filter("v is not null").distinct().withColumn("y", F.lit(1))
    both = a.join(b, "v", "full")
    n = both.agg(F.count_if(F.col("x").isNotNull() & F.col("y").isNotNull()).alias("inter"), F.count("x").alias("n_left"), F.count("y").alias("n_right"))
    return n.withColumn("jaccard", F.col("inter") / F.greatest(F.col("n_left") + F.col("n_right") - F.col("inter"), F.lit(1))).withColumn("containment", F.col("inter") / F.greatest(F.col("n_left"), F.lit(1)))


def valid_keys(profile: DataFrame, min_distinct: int = 2, max_share: float = 1.0, max_null_share: float = 0.5) -> DataFrame:
    """Columns fit to join on: whole-number or text values, several of them, not mostly missing."""
    share = F.col("distinct_values") / F.greatest(F.col("rows"), F.lit(1))
    return profile.filter((F.col("distinct_values") >= min_distinct) & (share <= max_share) & (F.col("nulls") <= max_null_share * F.col("rows")) & F.col("key_type"))


def cosine(a: Column, b: Column) -> Column:
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda t, v: t + v)
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def semantic(a: Column, b: Column) -> Column:
    """Cosine of two names as sets of letter triples."""
    grams = lambda n: F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(n) - 2, F.lit(1))), lambda i: F.substring(n, i, F.lit(3))))
    x, y = grams(a), grams(b)
    return F.size(F.array_intersect(x, y)) / F.sqrt(F.size(x) * F.size(y))


def profile_of(df: DataFrame, keys: Sequence[str], features: Sequence[str], k: int = K) -> DataFrame:
    """PROFILE rows of a table's columns: one pass with a partial aggregate a column."""
    kinds = {n: "number" if t in ("int", "bigint", "smallint", "tinyint", "float", "double") or t.startswith("decimal") else "date" if t.startswith(("date", "timestamp")) else "text" for n, t in df.dtypes}
    cells = []
    for role, names in (("key", keys), ("feature", features)):
        for n in names:
            number = F.col(n).cast("double") if kinds[n] == "number" else F.lit(None).cast("double")
            text = F.col(n).cast("string") if role == "key" or kinds[n] != "number" else number.cast("string")
            cells.append(F.struct(F.lit(n).alias("column"), F.lit(role).alias("role"), F.lit(kinds[n]).alias("type"), number.alias("x"), text.alias("v")))
    if not cells:
        return df.sparkSession.createDataFrame([], PROFILE)
    tall = df.select(F.explode(F.array(*cells)).alias("e")).select("e.*").withColumn("h", F.xxhash64("v"))  # a text is hashed once
    least = [F.min(F.xxhash64(F.lit(i), "h")).alias(f"_h{i}") for i in range(k)]
    x = F.col("x")
    got = tall.groupBy("column", "role", "type").agg(
        F.count("*").alias("rows"), F.count_if(F.col("v").isNull()).alias("nulls"), F.min(x).alias("low"), F.max(x).alias("high"), F.sum(x).alias("sum"), F.sum(x * x).alias("squares"), F.hll_sketch_agg("v").alias("hll"), *least
    )
    return got.select("column", "role", "type", "rows", "nulls", "low", "high", "sum", "squares", "hll", F.array(*[F.col(f"_h{i}") for i in range(k)]).alias("signature"))


def distinct_values(p: str = "") -> Column:
    return F.coalesce(F.hll_sketch_estimate(F.col(f"{p}hll")), F.lit(0)).cast("double")


def overlap(a: Column, b: Column, c: Column, d: Column) -> Column:
    """How much of the range a..b lies in c..d: 1 for a single value inside, null where a range is unknown."""
    inside = F.greatest(F.least(b, d) - F.greatest(a, c), F.lit(0.0))
    return F.when((a == b) & a.between(c, d), F.lit(1.0)).when(b > a, inside / (b - a)).when(b == a, F.lit(0.0))


class ProfileIndex:
    """The discovery index of a corpus. ``least`` is the smallest score of a mapped column or a joined key."""

    def __init__(self, spark: SparkSession, least: float = 0.5, bands: int = BANDS, k: int = K) -> None:
        self.spark, self.least, self.bands, self.k = spark, least, bands, k
        self.path, self.live = scratch_path(spark, "profiles"), {}

    def profile(self, df: DataFrame, keys: Sequence[str], features: Sequence[str]) -> DataFrame:
        return profile_of(df, keys, features, self.k)

    def insert(self, dataset: str, df: DataFrame, keys: Sequence[str], features: Sequence[str]) -> None:
        self.insert_profile(dataset, self.profile(df, keys, features))

    def insert_profile(self, dataset: str, profile: DataFrame) -> None:
        version = self.live.get(dataset, 0) + 1
        profile.select(F.lit(dataset).alias("dataset"), F.lit(version).alias("version"), *[F.col(f.split()[0]) for f in PROFILE.split(", ")]).write.mode("append").parquet(self.path)
        self.live[dataset] = version

    def refresh(self, dataset: str, rows: DataFrame, keys: Sequence[str], features: Sequence[str], op: str = "insert") -> None:
        """Inserted rows are merged into the profile; after a delete, rows is the whole table and is profiled again."""
        new = self.profile(rows, keys, features)
        if op == "insert" and dataset in self.live:
            old, names = self.table([dataset]).drop("dataset"), ["column", "role", "type"]
            renamed = new.select(*names, *[F.col(c).alias(f"n_{c}") for c in new.columns if c not in names])
            plus = lambda c: (F.coalesce(c, F.lit(0)) + F.coalesce(f"n_{c}", F.lit(0))).alias(c)
            both = old.join(renamed, names, "left")
            new = both.select(
                *names, plus("rows"), plus("nulls"), F.least("low", "n_low").alias("low"), F.greatest("high", "n_high").alias("high"), plus("sum"), plus("squares"),
                F.coalesce(F.hll_union("hll", "n_hll"), "hll", "n_hll").alias("hll"), F.coalesce(merge(F.col("signature"), F.col("n_signature")), "signature").alias("signature"),
            )
        self.insert_profile(dataset, new)

    def table(self, datasets: Sequence[str] | None = None) -> DataFrame:
        """The latest profile of each live dataset."""
        names = [n for n in (self.live if datasets is None else datasets) if n in self.live]
        wanted = self.spark.createDataFrame([(n, self.live[n]) for n in names], "dataset string, version int")
        if not names:
            return self.spark.createDataFrame([], f"dataset string, {PROFILE}")
        every = self.spark.read.schema(f"dataset string, version int, {PROFILE}").parquet(self.path)
        return every.join(F.broadcast(wanted), ["dataset", "version"], "left_semi").drop("version")  # a row a dataset

    def _banded(self, p: DataFrame) -> DataFrame:
        rows = self.k // self.bands
        hashed = F.transform(F.sequence(F.lit(0), F.lit(self.bands - 1)), lambda i: F.concat_ws(":", F.lit("band"), i.cast("string"), F.xxhash64(F.slice("signature", i * rows + 1, rows)).cast("string")))
        blocks = F.concat(tokens(F.col("column")), F.when(F.element_at("signature", 1).isNotNull(), hashed).otherwise(F.array().cast("array<string>")))
        return p.withColumn("block", F.explode(blocks))

    def compared(self, profile: DataFrame, datasets: Sequence[str] | None = None) -> DataFrame:
        """Columns of the request beside columns of the corpus that share a block, with their similarities."""
        own = ["column", "role", "type", "rows", "nulls", "low", "high", "sum", "squares", "hll", "signature"]
        left = self._banded(profile).select("block", *[F.col(c).alias(f"a_{c}") for c in own])
        right = self._banded(self.table(datasets)).select("block", "dataset", *[F.col(c).alias(f"b_{c}") for c in own])
        met = left.join(right, "block").filter((F.col("a_type") == F.col("b_type")) & (F.col("a_role") == F.col("b_role"))).dropDuplicates(["a_column", "dataset", "b_column"])
        na, nb = distinct_values("a_"), distinct_values("b_")
        jaccard = F.coalesce(similarity(F.col("a_signature"), F.col("b_signature")), F.lit(0.0))
        common = jaccard / (1 + jaccard) * (na + nb)
        inside = overlap(F.col("a_low"), F.col("a_high"), F.col("b_low"), F.col("b_high"))
        dense = F.least(nb / (F.col("b_high") - F.col("b_low") + 1), F.lit(1.0))  # of whole numbers
        contained = F.least(F.greatest(common / F.greatest(na, F.lit(1.0)), F.coalesce(inside * dense, F.lit(0.0))), F.lit(1.0))
        names = name_similarity(normal_name(F.col("a_column")), normal_name(F.col("b_column")))
        back = overlap(F.col("b_low"), F.col("b_high"), F.col("a_low"), F.col("a_high"))
        values = F.coalesce(F.greatest(jaccard, (inside + back) / 2), jaccard)
        return met.select(
            "dataset", F.col("a_role").alias("role"), "a_column", "b_column", jaccard.alias("jaccard"), contained.alias("containment"), semantic(normal_name(F.col("a_column")), normal_name(F.col("b_column"))).alias("semantic"),
            names.alias("name"), values.alias("values"),
        )

    def unionable(self, compared: DataFrame, wanted: int) -> DataFrame:
        """(dataset, mapping, score) of datasets where all ``wanted`` columns of the request have a column of their own."""
        scored = compared.filter("role = 'feature'").withColumn("score", (F.col("name") + F.col("values")) / 2).filter((F.col("score") >= self.least) & (F.col("name") >= self.least))
        best = Window.partitionBy("dataset", "a_column").orderBy(F.desc("score"), "b_column")
        once = Window.partitionBy("dataset", "b_column").orderBy(F.desc("score"), "a_column")
        kept = scored.withColumn("_n", F.row_number().over(best)).filter("_n = 1").withColumn("_n", F.row_number().over(once)).filter("_n = 1")
        found = kept.groupBy("dataset").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("a_column", "b_column")))).alias("mapping"), F.avg("score").alias("score"), F.count("*").alias("_n"))
        return found.filter(F.col("_n") == wanted).drop("_n")

    def joinable(self, compared: DataFrame) -> DataFrame:
        """(dataset, key, via, score): keys of the request mostly contained in a key of a dataset."""
        scored = compared.filter("role = 'key'").withColumn("score", (F.col("jaccard") + F.col("containment") + F.col("semantic")) / 3)
        return scored.filter(F.col("containment") >= self.least).select("dataset", F.col("a_column").alias("key"), F.col("b_column").alias("via"), "score", "jaccard", "containment", "semantic")

    def candidates(self, profile: DataFrame, datasets: Sequence[str] | None = None) -> DataFrame:
        """(kind, dataset, key, via, mapping, score) for a request's profile, whose target counts as a feature."""
        met = self.compared(profile, datasets)
        wanted = profile.filter("role = 'feature'").count()
        unions = self.unionable(met, wanted).select(F.lit("horizontal").alias("kind"), "dataset", F.lit(None).cast("string").alias("key"), F.lit(None).cast("string").alias("via"), "mapping", "score")
        joins = self.joinable(met).select(F.lit("vertical").alias("kind"), "dataset", "key", "via", F.lit(None).cast("map<string,string>").alias("mapping"), "score")
        return unions.unionByName(joins)
