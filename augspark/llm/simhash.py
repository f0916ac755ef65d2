r"""SimHash near-duplicates by tiled exact comparison.

Fingerprints: texts are lower-cased (A-Z), split into words ``[^\x20\x09-\x0D]+`` and 3-word shingles; a bit is set where
over half of the shingles' XXH64 (seed 42) have it set.

Comparison: equal fingerprints are first merged, so thousands of copies count once. Distinct fingerprints are laid out in
tiles by the population counts of their parts (four of 16 bits by default). Two fingerprints that differ in at most
``radius`` bits have count vectors at most ``radius`` apart, so all other tile pairs are skipped without losing a link:
each fingerprint is a resident of its own tile and a visitor in the following ones within reach. Inside a tile numpy
compares blocks by exclusive-or and bit counts. A tile gives a spanning forest of its links, never all pairs, and holds
only its residents in memory; visitors stream past in batches. More parts make smaller tiles for more fingerprints.

Defined results: a null, empty or blank text has fingerprint zero and is linked like any other; fewer than three words
are one shingle; repeated rows share fingerprint and component; a null doc_id never names a component unless all of its
doc_ids are null; an empty table gives an empty table; extra columns, whatever their names, are carried along by
``keep_one`` and not read otherwise.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from augspark.cluster import materialize
from augspark.llm.components import connected, join_groups
from augspark.llm.text import column, fresh, small_batches

RADIUS = 2
SHINGLE = 3
SEED = 42
#: Expected residents of the largest tile; with more fingerprints than a layout holds, tiles are cut finer.
TILE_ROWS = 50_000
_BITS = (np.uint64(1) << np.arange(64, dtype=np.uint64)).astype(np.uint64)


def shingle_hashes(text: str | None, shingle: int = SHINGLE) -> np.ndarray:
    """XXH64 of each shingle in order: none for a blank text, one for a text with fewer words than a shingle."""
    from xxhash import xxh64_intdigest as h

    ws = (text or "").encode("utf-8").lower().split()  # bytes: exactly A-Z, and exactly the six ASCII spaces
    joined = b" ".join(ws)
    if len(ws) < shingle:
        return np.array([h(joined, SEED)] if ws else [], np.uint64)
    ends = np.append(np.flatnonzero(np.frombuffer(joined, np.uint8) == 32), len(joined))
    starts = np.concatenate(([0], ends[:-1] + 1))
    n = len(ws) - shingle + 1
    return np.fromiter((h(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends[shingle - 1 :].tolist(), strict=True)), np.uint64, n)


def fingerprint(text: str | None, shingle: int = SHINGLE) -> int:
    """The 64-bit fingerprint of a whole text."""
    hashes = shingle_hashes(text, shingle)
    n = len(hashes)
    ones = np.zeros(64, np.int64)
    for at in range(0, n, 65_536):
        ones += np.unpackbits(hashes[at : at + 65_536].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(_BITS[2 * ones > n].sum(dtype=np.uint64))


def print_text(text: str):
    """The fingerprint of a text column, as a signed long."""

    @F.pandas_udf("long")
    def printed(texts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in texts:
            yield pd.Series(np.array([fingerprint(t) for t in batch], dtype=np.uint64).view(np.int64), dtype="int64")

    return printed(text)


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed long."""
    small_batches(docs.sparkSession)
    return docs.select("doc_id", print_text("text").alias("fp"))


def parts_for(distinct: int) -> int:
    """Parts (4, 8 or 16) whose fullest tile is expected to hold at most TILE_ROWS of so many random fingerprints."""
    fullest = {4: 0.1964**4, 8: 0.2734**8, 16: 0.375**16}
    return next((p for p, share in fullest.items() if distinct * share <= TILE_ROWS), 16)


def _base(parts: int, radius: int) -> int:
    return 64 // parts + 2 * radius + 1


def _steps(parts: int, radius: int) -> list[int]:
    """Code differences of tiles that follow a tile within reach: the half of the neighbourhood above zero."""
    base = _base(parts, radius)
    found = set()
    for k in range(1, radius + 1):
        for at in itertools.combinations_with_replacement(range(parts), k):
            for signs in itertools.product((1, -1), repeat=k):
                move = [0] * parts
                for a, s in zip(at, signs, strict=True):
                    move[a] += s
                first = next((m for m in reversed(move) if m), 0)
                if first > 0:
                    found.add(sum(m * base**i for i, m in enumerate(move)))
    return sorted(found)


def _tile_code(fp, parts: int, radius: int):
    """The count vector as a number whose digits have room for ``radius`` below and above."""
    bits, base = 64 // parts, _base(parts, radius)
    code = F.lit(0).cast("long")
    for i in range(parts):
        count = F.bit_count(F.shiftrightunsigned(fp, i * bits).bitwiseAND(F.lit((1 << bits) - 1).cast("long")))
        code = code + (count.cast("long") + radius) * F.lit(base**i).cast("long")
    return code


class _Tile:
    """Residents of one tile and the forest of their links."""

    def __init__(self, residents: np.ndarray, radius: int) -> None:
        self.fp, self.radius = residents, radius
        self.parent = np.arange(len(residents))
        self._visit(residents, own=True)

    def _roots(self) -> None:
        while True:
            up = self.parent[self.parent]
            if np.array_equal(up, self.parent):
                return
            self.parent = up

    def _visit(self, rows: np.ndarray, own: bool) -> np.ndarray:
        """For each row a resident within reach (or -1); residents that reach the same row are joined."""
        link = np.full(len(rows), -1, dtype=np.int64)
        step = max(1, 4_000_000 // max(1, len(self.fp)))
        for at in range(0, len(rows), step):
            near = np.bitwise_count(rows[at : at + step, None] ^ self.fp[None, :]) <= self.radius
            for i in np.flatnonzero(near.sum(axis=1) > own):  # an own row always reaches itself
                roots = np.unique(self.parent[near[i]])
                while not np.array_equal(self.parent[roots], roots):
                    roots = np.unique(self.parent[roots])
                self.parent[roots] = roots[0]
                link[at + i] = roots[0]
                if len(roots) > 32:
                    self._roots()
        self._roots()
        return link

    def visitors(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        link = self._visit(rows, own=False)
        hit = link >= 0
        return rows[hit], self.fp[self.parent[link[hit]]]

    def forest(self) -> tuple[np.ndarray, np.ndarray]:
        below = np.flatnonzero(self.parent != np.arange(len(self.fp)))
        return self.fp[below], self.fp[self.parent[below]]


def _compare(radius: int):
    """Rows (tile, visitor, fp), sorted by tile and residents first -> links (u, v)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tile, waiting, current = None, [], None

        def settled():
            nonlocal current
            if current is None:
                current = _Tile(np.concatenate(waiting), radius) if waiting else _Tile(np.array([], np.uint64), radius)
            return current

        def frame(u, v):
            return pd.DataFrame({"u": u.view(np.int64), "v": v.view(np.int64)})

        for batch in batches:
            codes, visitor, fps = batch["tile"].to_numpy(), batch["visitor"].to_numpy(), batch["fp"].to_numpy().view(np.uint64)
            change = codes[1:] != codes[:-1]
            edges = [0, *(np.flatnonzero(change | (visitor[1:] != visitor[:-1])) + 1).tolist(), len(codes)]
            links = []
            for a, b in itertools.pairwise(edges):
                if a == b:
                    continue
                if codes[a] != tile:
                    if tile is not None and waiting:
                        links.append(settled().forest())
                    tile, waiting, current = codes[a], [], None
                if not visitor[a]:
                    waiting.append(fps[a:b])
                elif waiting:
                    links.append(settled().visitors(fps[a:b]))
            if links:
                yield frame(np.concatenate([x for x, _ in links]), np.concatenate([x for _, x in links]))
        if tile is not None and waiting:
            yield frame(*settled().forest())

    return run


def links(distinct: DataFrame, radius: int = RADIUS, parts: int = 4) -> DataFrame:
    """Distinct fingerprints (fp) -> links (u, v) that connect all fingerprints within ``radius`` bits of each other."""
    if _base(parts, radius) ** parts >= 2**63:
        raise ValueError("tile codes of so many parts and such a radius exceed 64 bits")
    tiled = distinct.select("fp", _tile_code(F.col("fp"), parts, radius).alias("tile"))
    steps = F.array(*[F.lit(s).cast("long") for s in [0, *_steps(parts, radius)]])
    sent = tiled.select("fp", F.col("tile").alias("home"), F.explode(steps).alias("step"))
    sent = sent.select((F.col("home") + F.col("step")).alias("tile"), (F.col("step") != 0).alias("visitor"), "fp")
    laid = sent.repartition("tile").sortWithinPartitions("tile", "visitor")
    return laid.mapInPandas(_compare(radius), "u long, v long")


def near_duplicates(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """One row per row of docs: doc_id, fp (long), root (a fingerprint that names the component) and component_id, the
    smallest doc_id reachable over links."""
    prints = materialize(fingerprints(docs), "fingerprints")
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("n")), "distinct-fingerprints")
    found = materialize(links(distinct.select("fp"), radius, parts_for(distinct.count())), "links")
    roots = connected(found)
    return members(prints, distinct, roots)


def members(prints: DataFrame, distinct: DataFrame, roots: DataFrame) -> DataFrame:
    """prints (doc_id, fp), distinct (fp, first_id, n) and roots (node, root) -> (doc_id, fp, root, component_id).

    Both a component of very many fingerprints and a fingerprint of very many copies are dealt over tasks.
    """
    named = distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "first_id", "n", F.coalesce("root", "fp").alias("root"))
    named = materialize(named, "named-fingerprints")
    count, rows = named.agg(F.count("*"), F.sum("n")).first()
    lowest = named.groupBy("root").agg(F.count("*").alias("size"), F.min("first_id").alias("component_id"))
    joined = join_groups(named, "root", lowest, "size", count, F.col("fp"))
    return join_groups(prints.select("doc_id", "fp"), "fp", joined.select("fp", "n", "root", "component_id"), "n", rows or 0, F.coalesce("doc_id", F.monotonically_increasing_id()))


def keep_one(docs: DataFrame, radius: int = RADIUS) -> DataFrame:
    """The rows of docs with one document of each component: one row of that with the smallest doc_id.

    Where doc_ids name one row each, losers leave by an anti-join on the id. Otherwise (repeated rows, one id with
    several texts, null ids) fingerprints are joined instead, and one row of each component stays.
    """
    return keep_first(docs, materialize(near_duplicates(docs, radius), "components"), print_text("text"))


def keep_first(docs: DataFrame, found: DataFrame, printed: Column) -> DataFrame:
    """``keep_one`` for components (doc_id, fp, root, component_id) of any kind; printed gives the fp of a row."""
    if found.groupBy("doc_id").agg(F.count("*").alias("n")).filter("n > 1 or doc_id is null").isEmpty():
        gone = found.filter("doc_id != component_id").select("doc_id")
        return docs.join(gone, "doc_id", "left_anti").select(*[column(c) for c in docs.columns])
    fp, of, root, one = fresh(docs.columns, "_fp", "_fp_of", "_root", "_first")
    first = found.select(F.col("fp").alias(of), F.col("root").alias(root), F.col("component_id").alias(one)).distinct()
    known = docs.withColumn(fp, printed).join(first, F.col(fp) == F.col(of))
    return known.filter(F.col("doc_id").eqNullSafe(F.col(one))).dropDuplicates([root]).select(*[column(c) for c in docs.columns])
