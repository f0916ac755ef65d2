"""Approximate nearest neighbours: a hierarchical k-means tree searched best bin first.

The tree is fitted on a bounded sample of vectors (``SAMPLE_ROWS``, smallest hashes of their ids) on the driver; every
vector of the table is indexed by the leaf it descends to. A query walks the tree through a priority queue keyed by the
distance to each branch's centre, and takes leaves in that order until their number reaches the calibrated width and
they hold enough vectors. The width is the smallest at which queries from the half of the sample that the tree was not fitted
on find the wanted share of their true neighbours inside that half.

Leaves are compared exactly, in bins of bounded size: small neighbouring leaves share a bin, and the vectors of a leaf
that is larger than a bin are dealt into several by hash, so a leaf that holds a third of all rows becomes many tasks. A
query goes once to each bin with leaves it visits, and each bin gives at most k rows a query. A task holds the vectors of
one bin and streams the queries past; above DECK_QUERIES queries in all, each bin is repeated and its queries dealt out. Scores are Euclidean distances in double precision on
the original vectors; ties go to the smaller vec_id.

Defined results: null or empty vectors, zero vectors, vectors holding null or non-finite components, and vectors whose
length differs from most of the sample's take no part, as query or candidate; a query's own vec_id is never returned,
another vec_id is returned once a query, by the nearest of the vectors that rows give it; with fewer than k candidates
all are returned; an empty table gives no rows; extra columns are not read.
"""

from __future__ import annotations

import heapq
import itertools
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from augspark.cluster import materialize

K = 10
SAMPLE_ROWS = 24_000
BRANCH = 512
LEAF_ROWS = 96
CALIBRATION_QUERIES = 300
#: Recall aimed at on the sample, above what is promised for the table.
TARGET = 0.92
#: Vectors in one bin, and queries that a task is to answer from it.
BIN_ROWS = 4_000
DECK_QUERIES = 100_000


def usable(embedding):
    """A vector of at least one component, all finite, not all zero."""
    bad = F.exists(embedding, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce((F.size(embedding) > 0) & ~bad & F.exists(embedding, lambda x: x != 0), F.lit(False))


def kmeans(x: np.ndarray, k: int, draw: np.random.Generator, rounds: int = 8) -> tuple[np.ndarray, np.ndarray]:
    """Lloyd's rounds from distinct random rows: (centres, assignment)."""
    centres = x[draw.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        own = nearest(x, centres)
        for j in range(len(centres)):
            if (mine := x[own == j]).size:
                centres[j] = mine.mean(axis=0)
    return centres, nearest(x, centres)


def nearest(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return ((centres**2).sum(axis=1)[None, :] - 2 * (x @ centres.T)).argmin(axis=1)


@dataclass(frozen=True)
class Tree:
    """Nodes by number, 0 is the root: their children (none for a leaf) and the children's centres."""

    children: list[np.ndarray]
    centres: list[np.ndarray]
    leaf: np.ndarray
    width: int = 1

    @property
    def leaves(self) -> int:
        return int(self.leaf.max()) + 1

    def assign(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row."""
        out, todo = np.zeros(len(x), np.int64), [(0, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            if not len(self.children[node]):
                out[rows] = self.leaf[node]
                continue
            best = nearest(x[rows], self.centres[node])
            todo += [(int(self.children[node][j]), rows[best == j]) for j in np.unique(best)]
        return out

    def walk(self, q: np.ndarray) -> Iterator[int]:
        """Leaves in best-bin-first order."""
        queue, step = [(0.0, 0, 0)], 0
        while queue:
            _, _, node = heapq.heappop(queue)
            if not len(self.children[node]):
                yield int(self.leaf[node])
                continue
            for child, far in zip(self.children[node], ((self.centres[node] - q) ** 2).sum(axis=1), strict=True):
                step += 1
                heapq.heappush(queue, (float(far), step, int(child)))

    def visit(self, q: np.ndarray, rows: np.ndarray, need: int) -> list[int]:
        """Leaves for a query: ``width`` of those holding rows, and on until they hold ``need``."""
        out, held = [], 0
        for leaf in self.walk(q):
            if rows[leaf]:
                out.append(leaf)
                held += rows[leaf]
            if len(out) >= self.width and held >= need:
                break
        return out


def build(sample: np.ndarray, k: int = K, branch: int = BRANCH, leaf_rows: int = LEAF_ROWS, target: float = TARGET, queries: int = CALIBRATION_QUERIES, seed: int = 3) -> Tree:
    """Fit the tree on half of a sample, and calibrate how many leaves a query visits on the other half.

    Vectors that shaped the tree lie nearer to their leaves' centres than others, so they would promise too much.
    """
    draw = np.random.default_rng(seed)
    if len(sample) <= 4 * (k + 1):
        return Tree([np.array([], int)], [np.zeros((0, sample.shape[1]))], np.array([0]))
    order = draw.permutation(len(sample))
    sample, other = sample[order[::2]], sample[order[1::2]]
    children, centres, leaf, todo, leaves = [np.array([], int)], [np.zeros((0, sample.shape[1]))], [-1], [(0, np.arange(len(sample)))], 0
    while todo:
        node, rows = todo.pop()
        if len(rows) > leaf_rows:
            c, own = kmeans(sample[rows], branch, draw)
            used = np.unique(own)
            if len(used) > 1:
                first = len(children)
                children[node], centres[node] = np.arange(first, first + len(used)), c[used]
                for j, u in enumerate(used):
                    children.append(np.array([], int))
                    centres.append(np.zeros((0, sample.shape[1])))
                    leaf.append(-1)
                    todo.append((first + j, rows[own == u]))
                continue
        leaf[node] = leaves
        leaves += 1
    tree = Tree(children, centres, np.array(leaf))
    home = tree.assign(other)
    asked = draw.choice(len(other), min(queries, len(other)), replace=False)
    ranks = []  # per true neighbour, how many leaves a query opens up to that neighbour's
    for i in asked:
        far = ((other - other[i]) ** 2).sum(axis=1)
        far[i] = np.inf
        place = {leaf_no: n for n, leaf_no in enumerate(tree.walk(other[i]), 1)}
        ranks += [place[home[j]] for j in np.argpartition(far, k)[:k]]
    width = int(np.quantile(ranks, target, method="higher"))
    return Tree(children, centres, tree.leaf, width)


def _stack(column: pd.Series, dim: int) -> np.ndarray:
    return np.stack(column.to_numpy()).astype(np.float64) if len(column) else np.zeros((0, dim))


def fit_tree(vectors: DataFrame, k: int = K, sample_rows: int = SAMPLE_ROWS, **how) -> Tree | None:
    """The tree over a bounded sample of usable vectors of the commonest length; None without any."""
    named = vectors.select("embedding", F.xxhash64(F.col("vec_id").cast("string"), "embedding").alias("h"))
    share = min(1.0, 2.0 * sample_rows / max(1, vectors.count()))  # first thinned by hash, so that no task sends a whole sample
    thin = named.filter(F.pmod("h", F.lit(1_000_000)) < F.lit(int(1_000_000 * share) + 1))
    got = thin.orderBy("h").limit(sample_rows).toPandas()
    if not len(got):
        return None
    sizes = got["embedding"].map(len)
    sample = got.loc[sizes == sizes.mode().iloc[0], "embedding"]
    return build(_stack(sample, 0), k, **how)


def bins(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each leaf its first bin and its number of bins."""
    first, parts, at, filled = np.zeros(len(rows), np.int64), np.ones(len(rows), np.int64), 0, 0
    for leaf, n in enumerate(rows):
        if filled and filled + n > BIN_ROWS:
            at, filled = at + 1, 0
        first[leaf], parts[leaf] = at, max(1, -(-int(n) // BIN_ROWS))
        filled += int(n)
        if parts[leaf] > 1:
            at, filled = at + int(parts[leaf]), 0
    return first, parts


def _compare(dim: int, leaves: int, k: int):
    """Rows (place, ask, id, vector, leaf, wanted) sorted by place, vectors of a bin first -> (query_id, vec_id, score).

    A task holds the vectors of one bin; queries stream past in batches, however many ask that bin.
    """
    nothing = pd.DataFrame({"query_id": [], "vec_id": [], "score": []}).astype({"query_id": "int64", "vec_id": "int64", "score": "float64"})

    def answer(x, ids, leaf, asks: pd.DataFrame) -> Iterator[pd.DataFrame]:
        for query_id, q, wanted in zip(asks["id"].tolist(), asks["vector"], asks["wanted"], strict=True):
            open_leaf = np.zeros(leaves, bool)
            open_leaf[np.asarray(wanted)] = True
            at = np.flatnonzero(open_leaf[leaf] & (ids != query_id))
            if len(at):
                far = np.sqrt(((x[at] - np.asarray(q)) ** 2).sum(axis=1))
                last = min(k, len(far)) - 1
                best = np.flatnonzero(far <= np.partition(far, last)[last])
                best = best[np.lexsort((ids[at[best]], far[best]))][:k]
                yield pd.DataFrame({"query_id": query_id, "vec_id": ids[at[best]], "score": far[best]})

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        here, waiting, held = None, [], None
        for batch in batches:
            places, asks = batch["place"].to_numpy(), batch["ask"].to_numpy()
            edges = [0, *(np.flatnonzero((places[1:] != places[:-1]) | (asks[1:] != asks[:-1])) + 1).tolist(), len(batch)]
            out = []
            for a, b in itertools.pairwise(edges):
                part = batch.iloc[a:b]
                if a == b:
                    continue
                if places[a] != here:
                    here, waiting, held = places[a], [], None
                if not asks[a]:
                    waiting.append((_stack(part["vector"], dim), part["id"].to_numpy(), part["leaf"].to_numpy()))
                elif waiting:
                    held = held or tuple(np.concatenate([w[i] for w in waiting]) for i in range(3))
                    out += answer(*held, part)
            yield pd.concat(out) if out else nothing

    return run


def index(table: DataFrame, k: int = K, tree: Tree | None = None, sample_rows: int = SAMPLE_ROWS, **how) -> tuple[Tree, DataFrame] | None:
    """The tree, and every usable vector with its leaf; None without usable vectors."""
    whole = table.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding"))
    vectors = whole.filter(F.col("vec_id").isNotNull() & usable(F.col("embedding")))
    tree = tree or fit_tree(vectors, k, sample_rows, **how)
    if tree is None:
        return None
    dim = tree.centres[0].shape[1]

    @F.pandas_udf("int")
    def leaf_of(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series(tree.assign(_stack(batch, dim)), dtype="int32")

    own = vectors.filter(F.size("embedding") == dim).dropDuplicates(["vec_id", "embedding"])
    return tree, materialize(own.withColumn("leaf", leaf_of("embedding")), "vector-index")


def leaf_rows(tree: Tree, indexed: DataFrame) -> np.ndarray:
    """Vectors a leaf; a row a leaf reaches the driver, which the sample bounds."""
    held = {r["leaf"]: r["n"] for r in indexed.groupBy("leaf").agg(F.count("*").alias("n")).collect()}
    return np.array([held.get(i, 0) for i in range(tree.leaves)])


def search(table: DataFrame, is_query, k: int = K, tree: Tree | None = None, sample_rows: int = SAMPLE_ROWS, **how) -> DataFrame:
    """(query_id, rank, vec_id, score): the k nearest found for each row that ``is_query`` (a Column on vec_id) holds for."""
    found = index(table, k, tree, sample_rows, **how)
    if found is None:
        return table.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    tree, indexed = found
    rows = leaf_rows(tree, indexed)
    dim, (first, parts) = tree.centres[0].shape[1], bins(rows)

    @F.pandas_udf("array<struct<bin:int,leaves:array<int>>>")
    def bins_for(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            out = []
            for q in _stack(batch, dim):
                sent: dict[int, list[int]] = {}
                for leaf in tree.visit(q, rows, k + 1):
                    for b in range(first[leaf], first[leaf] + parts[leaf]):
                        sent.setdefault(int(b), []).append(leaf)
                out.append([{"bin": b, "leaves": leaves} for b, leaves in sent.items()])
            yield pd.Series(out, dtype=object)

    @F.pandas_udf("int")
    def bin_of(batches: Iterator[tuple[pd.Series, pd.Series]]) -> Iterator[pd.Series]:
        for leaf, h in batches:
            yield pd.Series(first[leaf] + h.to_numpy() % parts[leaf], dtype="int32")

    asked = indexed.filter(is_query(F.col("vec_id")))
    decks = max(1, -(-asked.count() // DECK_QUERIES))  # a bin meets its queries in so many tasks
    place = lambda b, deck: (b * F.lit(decks) + deck).cast("long").alias("place")
    every = F.explode(F.sequence(F.lit(0), F.lit(decks - 1)))
    dealt = indexed.select(bin_of("leaf", F.xxhash64("vec_id")).alias("bin"), "vec_id", "embedding", "leaf", every.alias("deck"))
    dealt = dealt.select(place(F.col("bin"), F.col("deck")), F.lit(False).alias("ask"), F.col("vec_id").alias("id"), F.col("embedding").alias("vector"), "leaf", F.lit(None).cast("array<int>").alias("wanted"))
    sent = asked.withColumn("_to", F.explode(bins_for("embedding")))
    sent = sent.select(place(F.col("_to.bin"), F.pmod(F.xxhash64("vec_id", "embedding"), F.lit(decks))), F.lit(True).alias("ask"), F.col("vec_id").alias("id"), F.col("embedding").alias("vector"), "leaf", F.col("_to.leaves").alias("wanted"))
    laid = dealt.unionByName(sent).repartition("place").sortWithinPartitions("place", "ask")
    near = laid.mapInPandas(_compare(dim, tree.leaves, k), "query_id long, vec_id long, score double")
    best = near.groupBy("query_id", "vec_id").agg(F.min("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return best.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def opened(table: DataFrame, is_query, k: int = K, **how) -> DataFrame:
    """(vectors, queries, leaves, width, opened): the share of vectors that a query's leaves hold, over all queries."""
    spark, empty = table.sparkSession, "vectors long, queries long, leaves int, width int, opened double"
    found = index(table, k, **how)
    if found is None:
        return spark.createDataFrame([], empty)
    tree, indexed = found
    rows = leaf_rows(tree, indexed)
    dim = tree.centres[0].shape[1]

    @F.pandas_udf("long")
    def compared(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in batches:
            yield pd.Series([int(rows[tree.visit(q, rows, k + 1)].sum()) for q in _stack(batch, dim)], dtype="int64")

    asked = indexed.filter(is_query(F.col("vec_id"))).agg(F.count("*").alias("queries"), F.avg(compared("embedding")).alias("mean"))
    n = int(rows.sum())
    return asked.select(F.lit(n).cast("long").alias("vectors"), "queries", F.lit(tree.leaves).alias("leaves"), F.lit(tree.width).alias("width"), (F.col("mean") / max(1, n)).alias("opened"))


def exact(table: DataFrame, is_query, k: int = K) -> DataFrame:
    """The same by brute force in SQL functions, for measuring recall on small tables: queries are broadcast in one batch."""
    v = table.filter(F.col("vec_id").isNotNull() & usable(F.col("embedding"))).select("vec_id", F.col("embedding").cast("array<double>").alias("embedding")).distinct()
    q = v.filter(is_query(F.col("vec_id"))).select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("query"))
    both = v.join(F.broadcast(q), (F.col("vec_id") != F.col("query_id")) & (F.size("embedding") == F.size("query")))
    far = F.sqrt(F.aggregate(F.zip_with("embedding", "query", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda a, b: a + b))
    order = Window.partitionBy("query_id").orderBy("score", "vec_id")
    ranked = both.select("query_id", "vec_id", far.alias("score")).withColumn("rank", F.row_number().over(order))
    return ranked.filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
