"""The corpus: datasets with release labels, their preparation, profiles and stored sketches.

A table is prepared when it is registered: missing feature values get constants fitted on it, and means and deviations
for standardising are read off its total sketch. All later changes use the same constants, so sketches stay those of one
prepared table. Sketches of all datasets live in one store; tables are scanned once to profile and once to sketch.
"""

from __future__ import annotations

import hashlib
import itertools
import uuid
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from augspark.assess.reuse import PlanMemo
from augspark.cluster import materialize
from augspark.prep import impute
from augspark.profile.index import ProfileIndex, valid_keys
from augspark.profile.stats import compute
from augspark.ring import gram
from augspark.sketch import build, maintain
from augspark.sketch.store import SketchStore

RAW, MD, API = 0, 1, 2
LABELS = {"RAW": RAW, "MD": MD, "API": API}
#: Partner elements of joins that are kept for later requests, by dataset version.
PARTNERS = 256
CATALOG = "dataset string, label int, version long, lineage string, keys array<string>, features array<string>, row_count long"


def release_filter(catalog: DataFrame, returns: Sequence[str]) -> DataFrame:
    """Datasets usable for a request: label at most the smallest of its return labels."""
    return catalog.filter(F.col("label") <= min(LABELS[r] for r in returns))


def allowed_kinds(returns: Sequence[str], api_may_join: bool = False) -> tuple[str, ...]:
    """Without raw data in return only unions are allowed; optionally an API-only request may join on the user's behalf."""
    least = min(LABELS[r] for r in returns)
    if least >= MD and not (api_may_join and least == API):
        return ("horizontal",)
    return ("horizontal", "vertical")


def joins_allowed(returns: Column, api_may_join: Column) -> Column:
    """Whether ``allowed_kinds`` has joins, for a column of arrays of return labels and one of the option."""
    codes = F.create_map(*[F.lit(x) for pair in LABELS.items() for x in pair])
    least = F.array_min(F.transform(returns, lambda x: F.element_at(codes, x)))
    return (least < MD) | (api_may_join & (least == API))


def schema_fingerprint(df: DataFrame) -> str:
    return hashlib.sha256(",".join(sorted(f"{n}:{t}" for n, t in df.dtypes)).encode()).hexdigest()


@dataclass
class Dataset:
    """fill and scales: per feature its stand-in for missing values, and (mean, deviation); carried: per key the other keys
    that each of its values fixes, which a plan gains with a join on it."""

    name: str
    label: int
    keys: tuple[str, ...]
    features: tuple[str, ...]
    lineage: str
    version: int
    row_count: int
    held: DataFrame | Callable[[], DataFrame] | None
    store: SketchStore
    fill: dict[str, float] = field(default_factory=dict)
    scales: dict[str, tuple[float, float]] = field(default_factory=dict)
    carried: dict[str, tuple[str, ...]] = field(default_factory=dict)
    carry: bool = True
    serial: str = field(default_factory=lambda: uuid.uuid4().hex[:12])

    @property
    def sid(self) -> str:
        """Names the sketches of this version; never used twice, also where a name is registered anew."""
        return f"{self.name}@{self.version}:{self.serial}"

    @property
    def data(self) -> DataFrame | None:
        """The prepared rows; None where a provider keeps them. Bulk uploads form the frame only when it is asked for."""
        return self.held() if callable(self.held) else self.held

    def renew(self) -> None:
        self.version, self.serial = self.version + 1, uuid.uuid4().hex[:12]

    @property
    def total(self) -> DataFrame:
        return self.store.total([self.sid]).select("g")

    @property
    def by_key(self) -> dict[str, DataFrame]:
        return {k: self.store.read(k, [self.sid]).select(F.col("key_value").alias(k), "g") for k in self.keys}

    def fixed_by(self, key: str, other: str) -> DataFrame:
        """(key, other): the other key's value of each value of a key that carries it."""
        pair = sorted((key, other))
        values = F.from_json("key_value", "array<string>")
        found = self.store.read("&".join(pair), [self.sid]).select(values.alias("v"))
        return found.select(F.col("v")[pair.index(key)].alias(key), F.col("v")[pair.index(other)].alias(other))


class Corpus:
    """Registered datasets. Each is scanned at upload; requests read stored sketches only."""

    def __init__(self, spark: SparkSession, index: ProfileIndex | None = None, store: SketchStore | None = None) -> None:
        self.spark, self.datasets, self.index = spark, {}, index
        self.store = store or SketchStore(spark)
        self.memo = PlanMemo(PARTNERS)
        self.standins: dict[tuple, list[float] | None] = {}

    def upload(self, df: DataFrame, name: str, label: str = "RAW", keys: Sequence[str] | None = (), features: Sequence[str] | None = (), lineage: str | None = None, fill: str | dict[str, float] = "mean", carry: bool = True) -> Dataset:
        """Register a table. keys or features of None are found: valid keys by the profile, features all other numbers.

        carry: sketch pairs of keys too, so that a join on one can bring the others to a plan.

        fill: how missing values of features are replaced (mean, median, mode), or the constants themselves. No row goes.
        """
        if keys is None or features is None:
            keys, features = self.roles(df, keys, features)
        constants = dict(fill) if isinstance(fill, dict) else impute.fit(df, features, fill) if features else {}
        data = impute.apply(df, {f: constants.get(f, 0.0) for f in features}) if features else df
        d = Dataset(name, LABELS[label], tuple(keys), tuple(features), lineage or name, self._next_version(name), 0, data, self.store, constants, carry=carry)
        self.store.append(self._sketches(d, data).withColumn("sid", F.lit(d.sid)))
        self._settle(d)
        if self.index is not None:
            self.index.insert(d.name, df, d.keys, d.features)
        self.datasets[name] = d
        return d

    def upload_columns(self, df: DataFrame, key: str, columns: Sequence[str], label: str = "RAW", lineage: str | None = None, prefix: str = "") -> list[Dataset]:
        """Register each column as a dataset of one feature, all in one pass over the table."""
        return self.upload_tables([(df, key, columns)], label, lineage, prefix)

    def upload_tables(self, tables: Sequence[tuple[DataFrame, str, Sequence[str]]], label: str = "RAW", lineage: str | None = None, prefix: str = "") -> list[Dataset]:
        """Register each column of several tables (rows, key, columns) as a dataset of one feature, in the jobs of one upload."""
        parts = []
        for df, key, columns in tables:
            named = F.array(*[F.lit(prefix + c) for c in columns])
            cells = F.posexplode(F.array(*[F.col(f"`{c}`").cast("double") for c in columns])).alias("at", "value")
            parts.append(df.select(F.col(f"`{key}`").cast("string").alias("key_value"), cells).select(F.element_at(named, F.col("at") + 1).alias("name"), F.lit(key).alias("key_name"), "key_value", "value"))
        made = self.upload_long(reduce(DataFrame.unionByName, parts), label, lineage)
        for d, c, df, key in ((self.datasets[prefix + c], c, df, key) for df, key, columns in tables for c in columns):
            d.features, d.fill, d.scales = (c,), {c: d.fill["x"]}, {c: d.scales["x"]}
            d.held = lambda c=c, fill=d.fill, df=df, key=key: impute.apply(df.select(key, c), fill)
            if self.index is not None:
                self.index.insert(d.name, df, d.keys, d.features)
        return made

    def upload_long(self, df: DataFrame, label: str = "RAW", lineage: str | None = None) -> list[Dataset]:
        """Register many datasets of one key and one feature x from rows (name, key_name, key_value, value), in one pass.

        Only a row a dataset reaches the driver: its name, mean and total.
        """
        serial = uuid.uuid4().hex[:12]
        own = df.select("name", "key_name", F.col("key_value").cast("string").alias("key_value"), F.col("value").cast("double").alias("x"))
        means = materialize(own.groupBy("name").agg(F.coalesce(F.avg("x"), F.lit(0.0)).alias("mean"), F.first("key_name").alias("key")), "means")
        known = means.collect()
        version = 1 + max((self.datasets[r["name"]].version for r in known if r["name"] in self.datasets), default=0)
        sid = F.concat(F.col("name"), F.lit(f"@{version}:{serial}"))
        filled = own.join(means, "name").select(sid.alias("sid"), "key_name", "key_value", F.coalesce("x", "mean").alias("x"))
        sets = [[F.col("sid"), F.col("key_name")], [F.col("sid"), F.col("key_name"), F.col("key_value")]]
        sums = filled.groupingSets(sets, "sid", "key_name", "key_value").agg(*gram.sums([F.col("x")]), F.grouping_id().alias("_level"))
        total = F.col("_level") == 1
        self.store.append(sums.filter(total | F.col("key_value").isNotNull()).select("sid", F.when(total, F.lit(build.ALL)).otherwise(F.col("key_name")).alias("key_name"), "key_value", gram.pack(1).alias("g")))
        made = []
        for r in known:
            held = lambda n=r["name"], k=r["key"], m=r["mean"]: df.filter(F.col("name") == n).select(F.col("key_value").alias(k), F.coalesce(F.col("value").cast("double"), F.lit(m)).alias("x"))
            made.append(Dataset(r["name"], LABELS[label], (r["key"],), ("x",), lineage or r["name"], version, 0, held, self.store, {"x": r["mean"]}, carry=False, serial=serial))
        totals = {r["sid"]: r["g"] for r in self.store.total([d.sid for d in made]).collect()}
        for d in made:
            self._settle(d, totals.get(d.sid))
            self.datasets[d.name] = d
        return made

    def upload_partitions(self, df: DataFrame, by: str, features: Sequence[str], keys: Sequence[str] = (), label: str = "RAW", prefix: str = "") -> list[Dataset]:
        """Register the rows of each value of ``by`` as a dataset of its own, all in one pass over the table."""
        data = impute.apply(df, impute.fit(df, features, "mean"))
        found = build.keyed(data, [gram.number(f) for f in features], [[k] for k in keys], F.col(f"`{by}`").cast("string"))
        parts = [r["v"] for r in data.select(F.col(f"`{by}`").cast("string").alias("v")).distinct().orderBy("v").collect()]  # a row a dataset
        made = {v: Dataset(f"{prefix}{v}", LABELS[label], tuple(keys), tuple(features), f"{prefix}{v}", self._next_version(f"{prefix}{v}"), 0, lambda v=v: data.filter(F.col(f"`{by}`").cast("string") == v), self.store, carry=False) for v in parts if v is not None}
        sids = self.spark.createDataFrame([(v, d.sid) for v, d in made.items()], "fold string, sid string")
        self.store.append(found.join(F.broadcast(sids), "fold"))  # a row a dataset
        totals = {r["sid"]: r["g"] for r in self.store.total([d.sid for d in made.values()]).collect()}
        for d in made.values():
            self._settle(d, totals.get(d.sid))
            self.datasets[d.name] = d
        return list(made.values())

    def upload_sketch(self, name: str, label: str, total: DataFrame, by_key: dict[str, DataFrame], features: Sequence[str], rows: int, lineage: str | None = None, profile: DataFrame | None = None) -> Dataset:
        """Register sketches, and optionally a profile, that a provider made; its rows are never seen."""
        d = Dataset(name, LABELS[label], tuple(by_key), tuple(features), lineage or name, self._next_version(name), rows, None, self.store)
        every = total.select(F.lit(build.ALL).alias("key_name"), F.lit(None).cast("string").alias("key_value"), "g")
        for k, s in by_key.items():
            every = every.unionByName(s.select(F.lit(k).alias("key_name"), F.col(k).cast("string").alias("key_value"), "g"))
        self.store.append(every.withColumn("sid", F.lit(d.sid)))
        self._settle(d)
        d.row_count = rows
        if self.index is not None and profile is not None:
            self.index.insert_profile(name, profile)
        self.datasets[name] = d
        return d

    def change(self, name: str, rows: DataFrame, op: str) -> Dataset:
        """Insert or delete rows: they are prepared as the dataset was, and sketches of all keys follow by signed deltas."""
        d = self.datasets[name]
        prepared = impute.apply(rows, {f: d.fill.get(f, 0.0) for f in d.features}) if d.features else rows
        names = [build.ALL, *d.keys, *("&".join(p) for p in itertools.combinations(sorted(d.keys), 2) if d.carry)]
        stored = None
        for k in names:
            one = self.store.read(k, [d.sid]).select(F.lit(k).alias("key_name"), "key_value", "g")
            stored = one if stored is None else stored.unionByName(one)
        delta = maintain.signed(self._sketches(d, prepared), len(d.features), op)
        d.renew()
        new = maintain.apply(stored, [delta], len(d.features), ["key_name", "key_value"])
        self.store.append(new.withColumn("sid", F.lit(d.sid)))
        if d.held is not None:
            d.held = d.data.unionByName(prepared) if op == "insert" else d.data.exceptAll(prepared)
        self._settle(d)
        if self.index is not None:
            self.index.refresh(name, d.data if op != "insert" else rows, d.keys, d.features, op)
        return d

    def roles(self, df: DataFrame, keys: Sequence[str] | None, features: Sequence[str] | None) -> tuple[list[str], list[str]]:
        """Keys and features by profile and type: whole numbers, text and dates can be keys; other numbers are features."""
        types = dict(df.dtypes)
        if keys is None:
            able = [c for c, t in types.items() if t in ("int", "bigint", "smallint", "string", "date") and c not in (features or ())]
            found = compute(df, able, approximate=True).withColumn("key_type", F.lit(True)) if able else None
            keys = [r["column"] for r in valid_keys(found).collect()] if able else []  # a row a column
        if features is None:
            features = [c for c, t in types.items() if c not in keys and (t in ("int", "bigint", "smallint", "float", "double") or t.startswith("decimal"))]
        return list(keys), list(features)

    def _sketches(self, d: Dataset, data: DataFrame) -> DataFrame:
        """(key_name, key_value, g) of the total, each key and each pair of keys, each by a pass of its own in one job."""
        pairs = list(itertools.combinations(sorted(d.keys), 2)) if d.carry else []
        return build.keyed(data, [gram.number(f) for f in d.features], [*([k] for k in d.keys), *map(list, pairs)], apart=True).drop("fold")

    def _settle(self, d: Dataset, g=None) -> None:
        """Row count, scales and carried keys, read off stored sketches."""
        first = g if g is not None else next((r["g"] for r in d.total.collect()), None)
        d.row_count = int(first["c"]) if first else 0
        d.scales = {}
        for i, f in enumerate(d.features):
            m, n = len(d.features), d.row_count
            mean = first["s"][i] / n if n else 0.0
            var = first["q"][gram.at(i, i, m)] / n - mean * mean if n else 0.0
            d.scales[f] = (mean, var**0.5 if var > 1e-12 * max(1.0, mean * mean) else 1.0)
        d.carried = {}
        both = list(itertools.permutations(d.keys, 2)) if d.held is not None and d.carry else []
        if not both:
            return
        every = self.store.read_keys([*d.keys, *("&".join(sorted(p)) for p in both)], [d.sid])
        values = {r["key_name"]: (r["n"], r["rows"]) for r in every.groupBy("key_name").agg(F.count("*").alias("n"), F.sum("g.c").alias("rows")).collect()}
        for a, b in both:
            n, rows = values.get(a, (0, 0.0))
            pairs, paired = values.get("&".join(sorted((a, b))), (0, 0.0))
            if pairs > n:
                continue  # more pairs than values: some value has several
            # where no row lacks b, each value has a pair, so as many pairs as values are one each
            if (pairs == n and paired == rows) or d.fixed_by(a, b).groupBy(a).count().filter("count > 1").isEmpty():
                d.carried[a] = (*d.carried.get(a, ()), b)

    def _next_version(self, name: str) -> int:
        return self.datasets[name].version + 1 if name in self.datasets else 1

    def catalog(self) -> DataFrame:
        rows = [(d.name, d.label, d.version, d.lineage, list(d.keys), list(d.features), d.row_count) for d in self.datasets.values()]
        return self.spark.createDataFrame(rows, CATALOG)

    def visible(self, returns: Sequence[str], but: str | None = None) -> list[Dataset]:
        """Datasets a request may use; those of its own lineage are left out, or a table could predict itself."""
        least = min(LABELS[r] for r in returns)
        return [d for d in self.datasets.values() if d.label <= least and (but is None or d.lineage != but)]

    def compact(self, files: int = 1) -> None:
        """Drop the sketches of earlier versions and gather the rest in few files."""
        self.store.compact([d.sid for d in self.datasets.values()], files)


def one_row_per_key(df: DataFrame, key: str, features: Sequence[str]) -> DataFrame:
    """A table's mean features per key: what a key's element of weight 1 means for a row."""
    return df.filter(F.col(key).isNotNull()).groupBy(key).agg(*[F.avg(f).alias(f) for f in features])
