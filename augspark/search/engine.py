"""Greedy search for an augmentation plan: a state machine on the driver over set-at-a-time rounds.

A round scores every candidate in one job, with one scan of the sketch store for all unions and one for all joins of a
number of features, however many candidates and keys there are. The request's rows are read once before the first round. After a
step the next round's sketches come from stored ones where they can: a union adds sketches, a join's total is the one it was
scored by, its own key and keys that the joined dataset brings are products of sketches. Only other keys that a later
candidate can use are summed again from the rows, which carry one column per joined feature (and, with weights, per pair of them) and never multiply.
Sketches by key hold counts and sums; pair sums are those of the total, as nothing takes them from a key. A key with nearly as
many values in folds as there are rows is not summed at all: each row is then an element, read off the rows where it is used.
"""

from __future__ import annotations

import itertools
import time
from collections.abc import Sequence
from dataclasses import dataclass, field, replace
from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark import baselines
from augspark.assess import crossval, horizontal, reuse, vertical
from augspark.catalog import Corpus, Dataset, allowed_kinds
from augspark.cluster import free_shuffles, materialize
from augspark.prep import impute
from augspark.profile.index import Discovery
from augspark.ring import gram
from augspark.search import shape
from augspark.search.cache import PlanCache
from augspark.search.cost import CostModel
from augspark.search.deadline import Deadline
from augspark.search.request import Answer, Request, Step
from augspark.sketch import build
from augspark.sketch.build import ALL

DELTA = 0.02
FOLDS = 10
#: Unions come before joins (horizontal_first), may follow them (any), or are tried first alone (unions_alone).
ORDERS = ("horizontal_first", "any", "unions_alone")
#: Joins after which a plan's rows are written anew: each round would else plan and run all joins since the beginning.
JOINS_PENDING = 3
#: Share of values and folds among the rows above which summing by a key is not worth its shuffle.
LOOSE = 0.5


class Candidate(NamedTuple):
    """key is the request's column, via the dataset's key; mapping gives the dataset's column of each of the request's."""

    kind: str
    dataset: Dataset
    key: str | None
    via: str | None = None
    mapping: dict[str, str] | None = None

    def step(self, gain: float, cv_r2: float) -> Step:
        return Step(self.kind, self.dataset.name, self.key, gain, cv_r2, self.via, tuple(sorted((self.mapping or {}).items())))

    @property
    def id(self) -> tuple[str, str, str | None]:
        return self.kind, self.dataset.name, self.key


def clash_free(dataset: str, features: Sequence[str]) -> list[str]:
    """Names of a dataset's features inside a plan."""
    return [f"{dataset}__{f}" for f in features]


def schema_of(req: Request) -> str:
    """The training schema that cached plans are kept by."""
    return repr((sorted(req.features), req.target, sorted(req.keys.items(), key=str)))


@dataclass
class Plan:
    """The state of a search: steps, the names of all features, keys, sketches by key name, and rows where they are whole.

    products are row columns that stand for the product of two joined features; loose are keys whose sketches are the rows.
    wanted are the keys that a next round needs sketches by (None: all); with rows_only it needs none. given are the written rows.
    scored are the elements by fold that the join to be taken was scored by, its next total; without them they are formed again.
    """

    names: list[str]
    target: str
    keys: dict[str, str | None]
    sketches: DataFrame
    rows: DataFrame | None
    products: dict[tuple[str, str], str] = field(default_factory=dict)
    pairs: tuple[tuple[str, str], ...] = ()
    steps: list[Step] = field(default_factory=list)
    used: set = field(default_factory=set)
    fill: dict[str, float] = field(default_factory=dict)
    unions_done: bool = False
    pending: int = 0
    loose: tuple[str, ...] = ()
    wanted: set[str] | None = None
    scored: Sequence | None = None
    rows_only: bool = False
    given: DataFrame | None = None

    @property
    def joined(self) -> bool:
        return any(s.kind == "vertical" for s in self.steps)

    def total(self) -> DataFrame:
        return self.sketches.filter(F.col("key_name") == ALL).select("fold", "g")

    def by(self, key: str) -> DataFrame:
        return self.sketches.filter(F.col("key_name") == key).select("key_value", "fold", "g")

    @property
    def at(self) -> int:
        return self.names.index(self.target)


class Search:
    """order: see ORDERS; mode: how several partners of a row count (weight 1/c each, or their mean); ranker: proxy or
    novelty (unions only); online: no stored sketch is used, base rows are aggregated for each candidate."""

    def __init__(
        self, corpus: Corpus, delta: float = DELTA, order: str = "horizontal_first", mode: str = "weight", impute: str = "mean", api_may_join: bool = False, cost: CostModel | None = None,
        lam: float = 1e-6, discovery: Discovery | None = None, ranker: str = "proxy", online: bool = False, standardise: bool = True, pair_share: float = 0.5,
    ) -> None:
        if order not in ORDERS or mode not in ("weight", "mean") or ranker not in ("proxy", "novelty"):
            raise ValueError("unknown order, mode or ranker")
        self.corpus, self.delta, self.order, self.mode, self.impute, self.api_may_join = corpus, delta, order, mode, impute, api_may_join
        self.cost, self.lam, self.discovery, self.ranker, self.online, self.standardise, self.pair_share = cost, lam, discovery, ranker, online, standardise, pair_share

    # opening a request

    def open(self, req: Request) -> Plan:
        """The request's rows, written once as however they were made they are read in every round, and their sketches."""
        names = [*req.features, req.target]
        rows = req.train
        fold = F.col(req.fold).cast("int") if req.fold and req.fold in rows.columns else F.pmod(F.xxhash64(*[F.col(c) for c in rows.columns]), F.lit(FOLDS)).cast("int")
        held = req.validation is not None
        take = lambda df, f: df.select(*[F.col(n).cast("double").alias(n) for n in names], *req.keys, f.alias("_fold")).filter(F.col(req.target).isNotNull())
        rows = take(rows, F.lit(crossval.ADDED) if held else fold)
        rows = given = materialize(rows.unionByName(take(req.validation, F.lit(0))) if held else rows, "request")
        pairs = list(itertools.combinations(sorted(req.keys), 2)) if self.pair_share > 0 and not self._rows_only(req) else []  # no pair is read then
        seen = rows.filter(F.col("_fold") == crossval.ADDED) if held else rows
        values = lambda ks: F.approx_count_distinct(F.xxhash64(*ks))
        told = seen.agg(
            F.count("*").alias("n"), *[F.avg(f).alias(f"m{i}") for i, f in enumerate(req.features)], *[values(p).alias(f"d{i}") for i, p in enumerate(pairs)], *[values((k, "_fold")).alias(f"v{i}") for i, k in enumerate(req.keys)]
        ).first()
        fill = {f: told[f"m{i}"] if told[f"m{i}"] is not None else 0.0 for i, f in enumerate(req.features)}
        rows = impute.apply(rows, fill) if fill else rows
        kept = tuple(p for i, p in enumerate(pairs) if told[f"d{i}"] <= self.pair_share * told["n"])
        loose = tuple(k for i, k in enumerate(req.keys) if told[f"v{i}"] > LOOSE * told["n"])
        plan = Plan(names, req.target, dict(req.keys), None, rows, pairs=kept, fill=fill, loose=loose, rows_only=self._rows_only(req), given=given)
        summed = [] if self._rows_only(req) else [*([k] for k in req.keys if k not in loose), *map(list, kept)]
        plan.sketches = self._with_loose(plan, materialize(self._sketches(rows, [gram.number(n) for n in names], summed, True, apart=True), "round"), () if plan.rows_only else loose)
        return plan

    def _rows_only(self, req: Request) -> bool:
        """Whether no sketch by key is read: base rows are aggregated for each candidate, and no shape is predicted."""
        return self.online and (req.model == "linear" or self.cost is None)

    def _with_loose(self, plan: Plan, sketches: DataFrame, keys: Sequence[str]) -> DataFrame:
        """sketches with the elements of a plan's rows by loose keys, which are not written."""
        x = [F.col(f"`{n}`").cast("double") for n in plan.names]
        return reduce(DataFrame.unionByName, [build.single(plan.rows, x, k, F.col("_fold")) for k in keys], sketches)

    def _sketches(self, rows: DataFrame, x: Sequence[Column], keys: Sequence[Sequence[str]], total: bool, products: dict | None = None, apart: bool = False) -> DataFrame:
        """(key_name, key_value, fold, g): whole elements overall, and elements without pair sums by each list of keys."""
        parts = [build.keyed(rows, x, [], F.col("_fold"), products=products)] if total or not keys else []
        parts += [build.linear(rows, x, keys, F.col("_fold"), apart)] if keys else []
        return reduce(DataFrame.unionByName, parts)

    # candidates

    def candidates(self, req: Request, plan: Plan | None = None, found: DataFrame | None = None) -> list[Candidate]:
        """Candidates allowed by labels, lineage, order rule and what the plan already has; discovered or by key name."""
        kinds, out = allowed_kinds(req.returns, self.api_may_join), []
        steps, used = (plan.joined, plan.used) if plan else (False, set())
        keys = plan.keys if plan else req.keys
        schema = set(plan.names) if plan else {*req.features, req.target}
        visible = {d.name: d for d in self.corpus.visible(req.returns, req.lineage)}
        if found is not None:
            for r in found.collect():  # a row a candidate
                d = visible.get(r["dataset"])
                if d and r["kind"] == "horizontal" and not steps:
                    out.append(Candidate("horizontal", d, None, None, dict(r["mapping"])))
                elif d and r["kind"] == "vertical" and req.target not in d.features:
                    out.append(Candidate("vertical", d, r["key"], r["via"]))
        for d in visible.values():
            if found is None and schema <= set(d.features) and (self.order == "any" or not steps):
                out.append(Candidate("horizontal", d, None, None, {n: n for n in schema}))
            if req.target not in d.features:
                out += [Candidate("vertical", d, own, name) for own, name in keys.items() if name in d.keys and (found is None or own not in req.keys)]
        out = [c for c in out if c.kind in kinds and c.id not in used and not (plan and plan.rows is None and c.kind == "vertical" and not c.dataset.keys)]
        if self.order == "unions_alone" and not (plan and plan.unions_done) and any(c.kind == "horizontal" for c in out):
            out = [c for c in out if c.kind == "horizontal"]
        return sorted(set_of(out), key=lambda c: (c.kind, c.dataset.name, c.key or "", c.via or ""))

    def shapes(self, plan: Plan, found: Sequence[Candidate]) -> DataFrame:
        """(cid, rows, cols) of the training table with each candidate, from counts in sketches."""
        spark = self.corpus.spark
        own = plan.total().agg(F.sum("g.c")).first()[0] or 0.0
        fixed = [(i, int(own) + c.dataset.row_count, len(plan.names)) for i, c in enumerate(found) if c.kind == "horizontal"]
        out = spark.createDataFrame(fixed, "cid int, rows long, cols int")
        for p, group in grouped(found).items():
            counts = self._read(group).select("dataset", "own", "key_value", F.col("g.c").alias("c"), F.lit(p).alias("p"))
            mine = plan.sketches.select(F.col("key_name").alias("own"), "key_value", "g.c").groupBy("own", "key_value").agg(F.sum("c").alias("c"))
            out = out.unionByName(shape.estimate(mine, counts, ["own", "key_value"], len(plan.names), "raw" if self.mode == "weight" else "mean", own).select(F.col("dataset").alias("cid"), "rows", "cols"))
        return out

    def affordable(self, req: Request, plan: Plan, found: Sequence[Candidate], left: float) -> dict[int, float]:
        """Predicted model seconds of the candidates that fit the time left; a linear request trains no further model."""
        if req.model == "linear" or self.cost is None:
            return dict.fromkeys(range(len(found)), 0.0)
        rows = self.cost.predict(self.shapes(plan, found)).filter(F.col("predicted_s") <= F.lit(float(left))).collect()  # a row a candidate
        return {r["cid"]: r["predicted_s"] for r in rows}

    # scoring

    def _read(self, group: Sequence[tuple[int, Candidate]]) -> DataFrame:
        """(dataset, own, key_value, g, shift, scale): stored sketches of joins by their number and the request's key, one scan."""
        rows = []
        for i, c in group:
            shift, scale = zip(*self.scales(c.dataset), strict=True) if c.dataset.features else ((), ())
            rows.append((c.dataset.sid, c.via, i, c.key, [float(x) for x in shift], [float(x) for x in scale]))
        ids = self.corpus.spark.createDataFrame(rows, "sid string, key_name string, dataset int, own string, shift array<double>, scale array<double>")
        read = self.corpus.store.read_keys(sorted({c.via for _, c in group}), sorted({c.dataset.sid for _, c in group}))
        return read.join(F.broadcast(ids), ["sid", "key_name"]).select("dataset", "own", "key_value", "g", "shift", "scale")  # a row a candidate

    def _scaled(self, group: Sequence[tuple[int, Candidate]], p: int) -> DataFrame:
        """(dataset, own, key_value, g): the same, standardised."""
        g = gram.affine(F.col("g"), [F.col("shift")[i] for i in range(p)], [F.col("scale")[i] for i in range(p)])
        return self._read(group).select("dataset", "own", "key_value", g.alias("g"))

    def scales(self, d: Dataset) -> list[tuple[float, float]]:
        return [d.scales.get(f, (0.0, 1.0)) if self.standardise else (0.0, 1.0) for f in d.features]

    def _aligned(self, unions: Sequence[tuple[int, Candidate]], plan: Plan, key: str | None = None) -> DataFrame:
        """(dataset, [key_value,] g): totals, or sketches by a key, of union candidates over the plan's features in its order."""
        rows = []
        for i, c in unions:
            at, m = [list(c.dataset.features).index(c.mapping[n]) for n in plan.names], len(c.dataset.features)
            rows.append((c.dataset.sid, i, at, [gram.at(at[a], at[b], m) for a, b in gram.pairs(len(at))]))
        ids = F.broadcast(self.corpus.spark.createDataFrame(rows, "sid string, dataset int, at array<int>, pair array<int>"))  # a row a candidate
        pick = lambda of, places: F.transform(places, lambda i: F.get(of, i))
        g = F.struct(F.col("g.c").alias("c"), pick(F.col("g.s"), F.col("at")).alias("s"), pick(F.col("g.q"), F.col("pair")).alias("q"))
        sids = [c.dataset.sid for _, c in unions]
        read = self.corpus.store.total(sids) if key is None else self.corpus.store.read(key, sids)
        return read.join(ids, "sid").select("dataset", *([] if key is None else ["key_value"]), g.alias("g"))

    def standins(self, group: Sequence[tuple[int, Candidate]], p: int) -> dict[int, list[float]]:
        """Values that stand in for a missing partner, by a join's number; joins without sketches have none.

        They depend on the dataset's version alone, so the corpus keeps them and a round sums only those it lacks, in one job.
        """
        known, name = self.corpus.standins, lambda c: (c.dataset.sid, c.via, str(self.impute), self.standardise)
        new = [(i, c) for i, c in group if name(c) not in known]
        if new:
            read = {r["dataset"]: list(r["u"]) for r in vertical.defaults(self._scaled(new, p), p, self.impute).collect()}  # a row a candidate
            known.update({name(c): read.get(i) for i, c in new})
        return {i: known[name(c)] for i, c in group if known[name(c)] is not None}

    def score(self, plan: Plan, found: Sequence[Candidate], req: Request, elements: bool = False) -> DataFrame:
        """(dataset, cv_r2, theta) of all candidates; dataset is the candidate's place in ``found``. elements: and f, the
        elements by fold that it was scored by."""
        held = req.validation is not None
        parts = self._online(plan, found) if self.online else []
        unions = [(i, c) for i, c in enumerate(found) if c.kind == "horizontal"]
        if unions and not self.online:
            parts.append(horizontal.batch(plan.total(), self._aligned(unions, plan)))
        for p, group in grouped(found).items() if not self.online else ():
            keys = sorted({c.key for _, c in group})  # named by their places, which are shorter
            place = F.coalesce(*[F.when(F.col("own") == k, F.lit(i)) for i, k in enumerate(keys)])
            mine = plan.sketches.filter(F.col("key_name").isin(keys)).select(F.col("key_name").alias("own"), "key_value", "fold", "g").withColumn("own", place)
            known = self.corpus.spark.createDataFrame(list(self.standins(group, p).items()), "dataset int, u array<double>")
            parts.append(vertical.batch(mine, self._scaled(group, p).withColumn("own", place), plan.total(), len(plan.names), p, self.mode, self.impute, ["key_value", "own"], known))
        return crossval.score(reduce(DataFrame.unionByName, parts), plan.at, lam=self.lam, held=held, elements=elements)

    def _online(self, plan: Plan, found: Sequence[Candidate]) -> list[DataFrame]:
        """The same from base rows: the request and the candidate are aggregated for every single candidate."""
        parts, x = [], [F.col(f"`{n}`").cast("double") for n in plan.names]
        products = self._products(plan)
        for i, c in enumerate(found):
            d = c.dataset
            loose = c.key in plan.loose
            mine = self._sketches(plan.rows, x, [[c.key]] if c.key and not loose else [], True, products)
            mine = self._with_loose(plan, mine, [c.key] if loose else [])
            total = mine.filter(F.col("key_name") == ALL).select("fold", "g")
            if c.kind == "horizontal":
                parts.append(horizontal.batch(total, build.total(d.data.select(*[F.col(c.mapping[n]).alias(n) for n in plan.names]), plan.names).select(F.lit(i).alias("dataset"), "g")))
                continue
            p, scales = len(d.features), self.scales(d)
            own = build.by_key(d.data, d.features, [c.via]).select(F.lit(i).alias("dataset"), F.col(c.via).cast("string").alias("key"), gram.affine(F.col("g"), [s[0] for s in scales], [s[1] for s in scales]).alias("g"))
            by = mine.filter(F.col("key_name") == c.key).select(F.col("key_value").alias("key"), "fold", "g")
            parts.append(vertical.batch(by, own, total, len(plan.names), p, self.mode, self.impute))
        return parts

    def base(self, plan: Plan, req: Request):
        own = plan.total().withColumn("dataset", F.lit(-1))
        return crossval.score(own, plan.at, lam=self.lam, held=req.validation is not None).first()

    # extending a plan

    def lookup(self, d: Dataset, via: str) -> tuple[DataFrame, list[float]]:
        """(key_value, g) with an element of weight 1 a key, and the values that stand in for a missing partner.

        They depend on the dataset's version alone, so the corpus keeps them for the rounds and requests that follow.
        """

        def make() -> tuple[DataFrame, list[float]]:
            scaled = self._scaled([(0, Candidate("vertical", d, via, via))], len(d.features))
            partner = scaled.select("key_value", gram.reweight(F.col("g"), len(d.features), self.mode).alias("g"))
            return materialize(partner, "partner"), self.standins([(0, Candidate("vertical", d, via, via))], len(d.features)).get(0, [0.0] * len(d.features))

        return self.corpus.memo.get([("partner", d.sid, [via, self.mode, str(self.impute), str(self.standardise)])], make)

    def extend(self, plan: Plan, c: Candidate, out: Answer | None = None, wanted: set[str] | None = None) -> Plan:
        """The plan with an accepted candidate and the sketches of its next round, by the keys ``wanted`` (None: the plan's)."""
        new = self._union(plan, c) if c.kind == "horizontal" else self._join(plan, c, out, plan.wanted if wanted is None else wanted)
        new.used = {*plan.used, c.id}
        return new

    def last(self, plan: Plan, c: Candidate) -> Plan:
        """The plan with a candidate after which no round follows: its sketches stay those before."""
        return replace(plan, used={*plan.used, c.id}) if c.kind == "horizontal" else replace(self._join_rows(plan, c, *self.lookup(c.dataset, c.via)), used={*plan.used, c.id})

    def _union(self, plan: Plan, c: Candidate) -> Plan:
        d, m = c.dataset, len(plan.names)
        more = self._aligned([(0, c)], plan).select(F.lit(ALL).alias("key_name"), F.lit(None).cast("string").alias("key_value"), F.lit(crossval.ADDED).alias("fold"), "g")
        added: list[DataFrame] = []
        for own, name in plan.keys.items():
            if name in d.keys:
                added = added + [self._aligned([(0, c)], plan, name).select(F.lit(own).alias("key_name"), "key_value", F.lit(crossval.ADDED).alias("fold"), gram.linear(F.col("g.c"), [F.col("g.s")[i] for i in range(m)]).alias("g"))]
        by = ["key_name", "key_value", "fold"]
        whole = gram.sum_elements(plan.sketches.filter(F.col("key_name") == ALL).unionByName(more), m, by)
        keyed = reduce(DataFrame.unionByName, added, plan.sketches.filter(F.col("key_name").isin(*plan.keys)))
        sketches = materialize(whole.unionByName(gram.sum_linear(keyed, m, by) if added or plan.loose else keyed), "round")
        rows = None
        if plan.rows is not None and d.data is not None:
            own = lambda k: (F.col(plan.keys[k]) if plan.keys[k] in d.data.columns else F.lit(None)).cast(plan.rows.schema[k].dataType).alias(k)
            rows = plan.rows.unionByName(d.data.select(*[F.col(c.mapping[n]).cast("double").alias(n) for n in plan.names], *[own(k) for k in plan.keys], F.lit(crossval.ADDED).alias("_fold")))
        return replace(plan, sketches=sketches, rows=rows, pairs=(), loose=(), wanted=None, scored=None, steps=list(plan.steps))

    def _products(self, plan: Plan) -> dict[tuple[int, int], Column]:
        place = {n: i for i, n in enumerate(plan.names)}
        return {(place[a], place[b]): F.col(f"`{column}`") for (a, b), column in plan.products.items()}

    def _join_rows(self, plan: Plan, c: Candidate, partner: DataFrame, u: Sequence[float], carry: bool = True) -> Plan:
        """The plan with the joined features, their products and the keys they bring, its rows joined; sketches as before.

        Without carry the rows lack the keys that the join brings, and are not written: for sums by other keys.
        """
        d, p, g = c.dataset, len(c.dataset.features), F.col("_g")
        new = clash_free(d.name, d.features)
        brought = {f"{d.name}__{k}": k for k in d.carried.get(c.via, ()) if f"{d.name}__{k}" not in plan.keys}
        products, rows = dict(plan.products), plan.rows
        if rows is not None:
            cells = {f: F.coalesce(g["s"][i], F.lit(float(u[i]))) for i, f in enumerate(new)}
            for i, j in gram.pairs(p) if self.mode == "weight" else ():
                products[new[i], new[j]] = f"{new[i]}*{new[j]}"
                cells[products[new[i], new[j]]] = F.coalesce(g["q"][gram.at(i, j, p)], F.lit(float(u[i] * u[j])))
            met = rows.join(partner.select(F.col("key_value").alias("_k"), F.col("g").alias("_g")), F.col(f"`{c.key}`").cast("string") == F.col("_k"), "left")
            for own, k in brought.items() if carry else ():
                fixed = d.fixed_by(c.via, k).select(F.col(c.via).alias("_k2"), F.col(k).alias("_v"))
                met = met.join(fixed, F.col("_k") == F.col("_k2"), "left").withColumn(own, F.col("_v")).drop("_k2", "_v")
            rows = met.withColumns(cells).drop("_k", "_g")
        names, keys, fill = [*plan.names, *new], plan.keys | brought, plan.fill | dict(zip(new, u, strict=True))
        pending = plan.pending + 1
        if rows is not None and carry and pending > JOINS_PENDING:
            rows, pending = materialize(rows, "joined"), 0
        return replace(plan, names=names, keys=keys, rows=rows, products=products, pairs=(), steps=list(plan.steps), used=set(plan.used), fill=fill, pending=pending, wanted=None, scored=None)

    def _rescanned(self, plan: Plan, keys: Sequence[str], total: bool) -> DataFrame:
        x = [F.col(f"`{n}`").cast("double") for n in plan.names]
        summed = [[k] for k in keys if k not in plan.loose]
        found = [self._sketches(plan.rows, x, summed, total, self._products(plan))] if summed or total else []
        return reduce(DataFrame.unionByName, found + [build.single(plan.rows, x, k, F.col("_fold")) for k in keys if k in plan.loose])

    def _join(self, plan: Plan, c: Candidate, out: Answer | None, wanted: set[str] | None = None) -> Plan:
        d, m, p = c.dataset, len(plan.names), len(c.dataset.features)
        partner, u = self.lookup(d, c.via)
        if plan.rows_only and plan.rows is not None:
            grown = self._join_rows(plan, c, partner, u)
            return replace(grown, sketches=self._rescanned(grown, [], True))  # formed only where it is read
        needed = lambda k: wanted is None or k in wanted
        if plan.scored is None:
            mine = plan.by(c.key).select(F.lit(c.key).alias("own"), "key_value", "fold", "g")
            total = vertical.batch(mine, self._scaled([(0, c)], p), plan.total(), m, p, self.mode, self.impute, ["key_value", "own"])
        else:
            total = self.corpus.spark.createDataFrame([(r["fold"], r["g"]) for r in plan.scored], plan.total().schema)  # a row a fold
        parts = [total.select(F.lit(ALL).alias("key_name"), F.lit(None).cast("string").alias("key_value"), "fold", "g")]
        loose = [k for k in plan.loose if needed(k)] if plan.rows is not None else []
        if needed(c.key) and c.key not in loose:
            parts.append(reuse.extend_linear(plan.by(c.key), partner, ["key_value"], ["key_value", "fold"], m, p, u).withColumn("key_name", F.lit(c.key)))
        grown = self._join_rows(plan, c, partner, u)
        for own in [k for k in grown.keys if k not in plan.keys and needed(k)]:
            k = grown.keys[own]
            fixed = d.fixed_by(c.via, k).select(F.col(c.via).alias("key_value"), F.col(k).alias("_other"))
            by_other = partner.join(fixed, "key_value").select("key_value", "_other", "g")
            parts.append(reuse.extend_linear(plan.by(c.key), by_other, ["key_value"], ["_other", "fold"], m, p, u).withColumnRenamed("_other", "key_value").withColumn("key_name", F.lit(own)))
        rest = [k for k in plan.keys if k != c.key and k not in loose and (needed(k) or grown.rows is None)]
        for k in [k for k in rest if tuple(sorted((k, c.key))) in plan.pairs]:
            pair = sorted((k, c.key))
            v = F.from_json("key_value", "array<string>")
            both = plan.by("&".join(pair)).select(v[pair.index(c.key)].alias("key_value"), v[pair.index(k)].alias("_own"), "fold", "g")
            parts.append(reuse.extend_linear(both, partner, ["key_value"], ["_own", "fold"], m, p, u).withColumnRenamed("_own", "key_value").withColumn("key_name", F.lit(k)))
            rest.remove(k)
        if out is not None:
            out.reused += len(parts)
            out.rescanned += len(rest) + len(loose) if grown.rows is not None else 0
        if rest and grown.rows is not None:
            # keys that the join brings are summed from sketches above: joining them to the rows would be for nothing
            bare = set(grown.keys) > set(plan.keys) and grown.pending > 0
            parts.append(self._rescanned(self._join_rows(plan, c, partner, u, carry=False) if bare else grown, rest, False))
        elif rest:
            grown.keys = {k: v for k, v in grown.keys.items() if k not in rest}  # rows of a union are unknown here, so these can't be summed
        columns = ["key_name", "key_value", "fold", "g"]
        grown.sketches = self._with_loose(grown, materialize(reduce(DataFrame.unionByName, [x.select(*columns) for x in parts]), "round"), loose)
        return grown

    # the search

    def pick(self, plan: Plan, found: Sequence[Candidate], able: dict[int, float], req: Request):
        """(candidate, its score row) of the best of the candidates that can be afforded, or None."""
        some = [c for i, c in enumerate(found) if i in able]
        if not some:
            return None
        if self.ranker == "novelty":
            some = [c for c in some if c.kind == "horizontal" and c.dataset.data is not None]
            if not some:
                return None
            some = [max(some, key=lambda c: (self.novelty(plan, c), c.dataset.name))]
        best = self.score(plan, some, req, not self.online).filter("cv_r2 is not null").orderBy(F.desc(F.round("cv_r2", 12)), "dataset").first()
        return (some[best["dataset"]], best, len(some)) if best else None

    def novelty(self, plan: Plan, c: Candidate, sample: int = 200) -> float:
        """How well 3-NN tells a candidate's rows from the plan's, on hash samples of both."""
        take = lambda df, cols: df.select(*cols).orderBy(F.xxhash64(*[F.col(f"`{n}`") for n in plan.names])).limit(sample)
        user = take(plan.rows, [F.col(n) for n in plan.names])
        other = take(c.dataset.data, [F.col(c.mapping[n]).cast("double").alias(n) for n in plan.names])
        pool = materialize(user.withColumn("o", F.lit(0)).unionByName(other.withColumn("o", F.lit(1))).coalesce(1).withColumn("id", F.monotonically_increasing_id()), "novelty")
        return baselines.novelty(pool.filter("o = 0").select("id", *plan.names), pool.filter("o = 1").select("id", *plan.names), plan.names).first()["novelty"]

    def run(self, req: Request, max_rounds: int | None = None, cache: PlanCache | None = None) -> Answer:
        """The greedy plan. With a cache, the search begins with a cached plan that gains on this request, and leaves its own."""
        return self.search(req, max_rounds, cache)[0]

    def search(self, req: Request, max_rounds: int | None = None, cache: PlanCache | None = None) -> tuple[Answer, Plan | None]:
        spark, began, plan, first = self.corpus.spark, time.monotonic(), None, None
        out = Answer(keys=dict(req.keys), feature_names=list(req.features))  # all there is for a model search until a score is known
        left = lambda: req.budget_s - (time.monotonic() - began)

        def settle(now: Plan, row, n: int) -> None:
            out.cv_r2, out.theta = row["cv_r2"], list(row["theta"])
            out.feature_names = [x for x in now.names if x != req.target]
            out.plan, out.keys, out.fill = now.steps, now.keys, now.fill
            out.trace.append((time.monotonic() - began, n, out.cv_r2))

        def begin():
            now = self.open(req)
            row = self.base(now, req)
            out.base_r2 = row["cv_r2"]
            settle(now, row, 0)
            return now, row

        if req.model == "linear":  # its first model is fitted whatever the budget, as a linear answer is nothing without one
            plan, first = begin()
        deadline = Deadline(spark, left())
        with deadline:
            try:
                if first is None:
                    plan, first = begin()
                found = self.discover(req, None if plan.given is None or req.validation is not None else plan.given)
                if first["cv_r2"] is None:
                    out.stopped = "constant target"  # nothing can explain it, nor be measured on it
                    return out, plan
                if cache is not None and left() > 0:
                    tried: dict[int, tuple] = {}

                    def gain_of(steps) -> float:
                        tried[id(steps)] = got = self.follow(steps, req, plan, first["cv_r2"], left(), found)
                        out.scored += 1
                        return got[1]["cv_r2"] - first["cv_r2"] if got else float("-inf")

                    out.cached, steps = cache.trial(schema_of(req), gain_of, self.delta)
                    if steps is not None:
                        plan, row = tried[id(steps)]
                        settle(plan, row, 0)
                for n in itertools.count(1):
                    if max_rounds is not None and n > max_rounds:
                        out.stopped = "rounds"
                        break
                    if left() <= 0:
                        out.stopped = "budget"
                        break
                    if 1.0 - out.cv_r2 < self.delta:
                        out.stopped = "gain"  # R² is 1 at most, so nothing can gain that much
                        break
                    some = self.candidates(req, plan, found)
                    if not some:
                        out.stopped = "no candidate"
                        break
                    able = self.affordable(req, plan, some, left())
                    if not able:
                        out.stopped = "unaffordable"
                        break
                    got = self.pick(plan, some, able, req)
                    out.scored += got[2] if got else 0
                    out.rounds = n
                    gain = got[1]["cv_r2"] - out.cv_r2 if got else float("-inf")
                    if gain < self.delta and not (self.ranker == "novelty" and n == 1 and got):
                        if self.order == "unions_alone" and not plan.unions_done and "vertical" in allowed_kinds(req.returns, self.api_may_join):
                            plan.unions_done = True  # no union helps any more: joins are next
                            continue
                        out.stopped = "gain"
                        break
                    c, row, _ = got
                    predicted = able[some.index(c)]
                    if predicted > left():
                        out.stopped = "unaffordable"
                        break
                    done = plan.unions_done
                    steps = [*plan.steps, c.step(gain, row["cv_r2"])]
                    plan = self.last(plan, c) if 1.0 - row["cv_r2"] < self.delta else self.extend(replace(plan, wanted=self.ahead(req, plan, c, found), scored=row["f"] if "f" in row else None), c, out)
                    free_shuffles(spark)
                    plan.steps, plan.unions_done, out.predicted_s = steps, done, predicted
                    settle(plan, row, n)
                    if req.model != "linear":
                        deadline.move(left() - predicted)
            except Exception:
                if not deadline.expired:
                    raise
                out.stopped = "budget"
        if cache is not None and out.plan:
            cache.put(schema_of(req), repr(tuple((x.kind, x.dataset, x.key) for x in out.plan)), list(out.plan))
        out.seconds = time.monotonic() - began
        return out, plan

    def ahead(self, req: Request, plan: Plan, c: Candidate, found: DataFrame | None) -> set[str]:
        """Keys by which candidates can be joined after a candidate is taken; a union leaves those of its plan."""
        brought = {f"{c.dataset.name}__{k}": k for k in c.dataset.carried.get(c.via, ())} if c.kind == "vertical" else {}
        then = replace(plan, keys=plan.keys | brought, used={*plan.used, c.id}, steps=[*plan.steps, c.step(0.0, 0.0)], unions_done=True)
        return {x.key for x in self.candidates(req, then, found) if x.key is not None}

    def discover(self, req: Request, rows: DataFrame | None = None) -> DataFrame | None:
        """Candidates that the discovery index finds for the request's profile; None without an index. rows: its written rows."""
        if self.discovery is None:
            return None
        profile = self.discovery.profile(req.train if rows is None else rows, list(req.keys), [*req.features, req.target])
        return materialize(self.discovery.candidates(materialize(profile, "profile"), [d.name for d in self.corpus.visible(req.returns, req.lineage)]), "candidates")

    def follow(self, steps: Sequence[Step], req: Request, plan: Plan, before: float, left: float, found: DataFrame | None = None):
        """(plan, score row) of given steps assessed on a request's own rows; None where one isn't allowed or affordable.

        All steps are joined first, and one pass over the rows gives the sketches of the whole plan.
        """
        now = replace(plan, steps=[], used=set(), unions_done=True)  # a plan may join first or only join
        for x in steps:
            some = [c for c in self.candidates(req, now, found) if c.id == (x.kind, x.dataset, x.key)][:1]
            if not some or not self.affordable(req, now, some, left):
                return None
            c, taken, used = some[0], [*now.steps, x], {*now.used, some[0].id}
            if c.kind == "horizontal":
                now = self._union(now, c)
            else:
                now = self._join_rows(now, c, *self.lookup(c.dataset, c.via))
            now.steps, now.used = taken, used
        if now.rows is None:
            return None
        now.sketches = materialize(self._rescanned(now, list(now.keys), True), "round")
        row = self.base(now, req)
        if row["cv_r2"] is None:
            return None
        now.steps[-1] = replace(now.steps[-1], gain=row["cv_r2"] - before - sum(s.gain for s in now.steps[:-1]), cv_r2=row["cv_r2"])
        return now, row


def set_of(candidates: Sequence[Candidate]) -> list[Candidate]:
    """Each (kind, dataset, key) once, by the first way it was found."""
    return list({c.id: c for c in reversed(candidates)}.values())


def grouped(found: Sequence[Candidate]) -> dict[int, list[tuple[int, Candidate]]]:
    """Joins that are scored together, by their number of features: over all keys, so a round has few scans."""
    out: dict[int, list[tuple[int, Candidate]]] = {}
    for i, c in enumerate(found):
        if c.kind == "vertical":
            out.setdefault(len(c.dataset.features), []).append((i, c))
    return out
