"""Exact top-k by inner product with the MaxScore split over postings, in shards of rows.

A component is a term, and its posting list has the rows whose weight there is not zero, in order of their
ids, with their weights. For a query, a term's bound is the largest product that any of the list's rows can
have, 0 at least, since rows without the term have 0. With the terms in order of their bounds, the
non-essential ones are those at the end whose bounds together do not reach the current k-th score: a
row that none of the other lists has with a positive product cannot get in. So the essential lists are
traversed, strip by strip of rows, and what they have of each row is added up; the others are probed by
binary search for those rows only that are still competitive, that is, while what a row has plus the bounds
still open reaches the k-th score. Equal scores stay, so ties go to the smaller id exactly. Where the lists have most rows
(dense vectors), a strip's lists lie side by side as one matrix: a block of queries, each with its own essential
lists only, traverses them in one product, and probes are look-ups there.

Rows are dealt to shards of a bounded number, and queries to blocks, by hashes of their ids, so none is hot.
Queries meet one shard first, and the k-th score they have there is a bound that all other shards start
from. A task holds the postings of one shard and streams a block of queries past them; blocks are large, so
rows travel once for each of few blocks. Shards are merged by rank.

Defined cases: vectors that are null, or hold null or non-finite components, take no part; shorter vectors count as filled
up with zeros; fewer candidates than k give fewer rows; an empty table gives none; extra columns are ignored;
rows that repeat an id are candidates of their own, but not of a query with that id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import forget, stored

#: Share of rows times terms from which the lists are held as a matrix too, and queries that traverse it together.
DENSE, TOGETHER = 0.25, 1024
#: Rows of a shard, queries of a block, rows that are traversed together, lists that are probed between two looks at who is left.
SHARD_ROWS, BLOCK_QUERIES, STRIP, PROBES = 8192, 65536, 2048, 4
RESULT = "query_id long, vec_id long, score long"


def usable(vector: str = "embedding") -> Column:
    """Whether a vector takes part."""
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf")))
    return F.col(vector).isNotNull() & ~bad


def quantised(df: DataFrame, id_col: str = "vec_id", vector: str = "embedding", scale: int = 256) -> DataFrame:
    """(id, w) with w = floor(scale * x) of every component as long."""
    return df.where(usable(vector)).select(F.col(id_col).alias("id"), F.transform(vector, lambda x: F.floor(F.lit(float(scale)) * x.cast("double"))).alias("w"))


def _matrix(column: pa.ChunkedArray | pa.Array, width: int) -> np.ndarray:
    out = np.zeros((len(column), width), np.int64)
    for i, row in enumerate(column):
        v = row.values.to_numpy()
        out[i, : len(v)] = v
    return out


class Shard:
    """Posting lists of some rows: per term the rows (places in the order of their ids) that have it, and their weights."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray, most: int = 0):
        """most: bound on the absolute weights of the queries to come, if larger than these rows'."""
        order = np.argsort(ids, kind="stable")
        self.ids, rows = ids[order], rows[order]
        most = max(most, int(np.abs(rows).max(initial=0)))
        self.terms = rows.shape[1]
        # products and sums up to 2^53 are exact in doubles, which are several times faster
        self.exact = most * most * max(1, self.terms) < 1 << 52
        self.kind = np.float64 if self.exact else np.int64
        self.lists: list[tuple[np.ndarray, np.ndarray]] = []
        for t in range(self.terms):
            at = np.flatnonzero(rows[:, t])
            self.lists.append((at, rows[at, t].astype(self.kind)))
        # largest and smallest weight of each list; a row that is not in it has 0
        self.high = np.array([w.max(initial=0) for _, w in self.lists], self.kind)
        self.low = np.array([w.min(initial=0) for _, w in self.lists], self.kind)
        # where each strip's part of a list begins
        cuts = np.arange(0, len(self.ids) + STRIP, STRIP)
        self.cuts = [np.searchsorted(at, cuts) for at, _ in self.lists]
        self.touched = self.probed = 0
        held = sum(len(at) for at, _ in self.lists)
        self.matrix = rows.astype(self.kind) if held >= DENSE * rows.size else None

    def search_all(self, query_ids: np.ndarray, queries: np.ndarray, k: int, floors: list[int | None]) -> list[tuple[np.ndarray, np.ndarray]]:
        """search() for each of the queries; together where the lists are dense."""
        if self.matrix is None:
            return [self.search(*x, k, floor) for *x, floor in zip(query_ids, queries, floors)]
        out = []
        for i in range(0, len(query_ids), TOGETHER):
            out += self._search_dense(query_ids[i : i + TOGETHER], queries[i : i + TOGETHER], k, floors[i : i + TOGETHER])
        return out

    def _search_dense(self, query_ids: np.ndarray, queries: np.ndarray, k: int, floors: list[int | None]) -> list[tuple[np.ndarray, np.ndarray]]:
        kind, n, every = self.kind, len(query_ids), np.arange(len(query_ids))
        none = -np.inf if self.exact else np.iinfo(np.int64).min
        q = queries.astype(kind)
        bound = np.maximum(q * self.high, q * self.low)
        terms = np.argsort(-bound, axis=1, kind="stable")
        place = np.argsort(terms, axis=1, kind="stable")
        after = np.zeros((n, self.terms + 1), kind)  # bounds of the terms from here on
        after[:, :-1] = np.cumsum(np.take_along_axis(bound, terms, 1)[:, ::-1], axis=1)[:, ::-1]
        needed = np.array([none if f is None else f for f in floors], kind)
        found = [(np.empty(0, np.int64), np.empty(0, kind)) for _ in range(n)]
        for strip, at in enumerate(range(0, len(self.ids), STRIP)):
            own, part = self.ids[at : at + STRIP], self.matrix[at : at + STRIP]
            essential = np.where(needed > 0, (after >= needed[:, None]).sum(axis=1), self.terms)
            used = (place < essential[:, None]) & (q != 0)
            self.touched += int((used @ np.array([c[strip + 1] - c[strip] for c in self.cuts])).sum())
            gained = np.where(used, q, 0) @ part.T
            # what falls short by this is no candidate, whatever the other lists have
            alive = gained + after[every, essential][:, None] >= needed[:, None]
            for i in np.flatnonzero(alive.any(axis=1)):
                keep, e = np.flatnonzero(alive[i]), int(essential[i])
                got = gained[i, keep]
                while e < self.terms and len(keep):
                    t = terms[i, e : e + PROBES]
                    got = got + part[np.ix_(keep, t)] @ q[i, t]
                    self.probed += len(keep) * len(t)
                    e = min(e + PROBES, self.terms)
                    stay = got + after[i, e] >= needed[i]
                    keep, got = keep[stay], got[stay]
                other = own[keep] != query_ids[i]
                ids, scores = np.concatenate([found[i][0], own[keep][other]]), np.concatenate([found[i][1], got[other]])
                if len(ids) >= k:
                    best = np.lexsort((ids, -scores))[:k]
                    ids, scores = ids[best], scores[best]
                    needed[i] = max(needed[i], scores[-1])
                found[i] = ids, scores
        return found

    def search(self, query_id: int, q: np.ndarray, k: int, floor: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids and scores of the k best rows, those below floor left out; ties to the smaller id."""
        kind = self.kind
        q = q.astype(kind)
        bound = np.maximum(q * self.high, q * self.low)
        terms = [int(t) for t in np.argsort(-bound, kind="stable") if q[t]]
        after = np.concatenate([np.cumsum(bound[terms][::-1])[::-1], [0]]).astype(kind)  # bounds of the terms from here on
        ids, scores = np.empty(0, np.int64), np.empty(0, kind)
        needed = floor
        for strip, at in enumerate(range(0, len(self.ids), STRIP)):
            own = self.ids[at : at + STRIP]
            got = np.zeros(len(own), kind)
            if needed is None or needed <= 0:  # a row without any list may get in
                essential, alive = len(terms), np.ones(len(own), bool)
            else:  # lists behind these cannot lift a row to what is needed
                essential, alive = int(np.searchsorted(-after, -needed, side="right")), np.zeros(len(own), bool)
            for t in terms[:essential]:
                lo, hi = self.cuts[t][strip : strip + 2]
                rows, product = self.lists[t][0][lo:hi] - at, self.lists[t][1][lo:hi] * q[t]
                got[rows] += product
                alive[rows[product > 0]] = True
                self.touched += len(rows)
            keep = np.flatnonzero(alive) if needed is None else np.flatnonzero(alive & (got + after[essential] >= needed))
            got = got[keep]
            while essential < len(terms) and len(keep):
                for t in terms[essential : essential + PROBES]:
                    lo, hi = self.cuts[t][strip : strip + 2]
                    rows, weights = self.lists[t][0][lo:hi], self.lists[t][1][lo:hi]
                    if len(rows):
                        place = np.minimum(np.searchsorted(rows, keep + at), len(rows) - 1)
                        got = got + np.where(rows[place] == keep + at, weights[place], 0) * q[t]
                    self.probed += len(keep)
                essential = min(essential + PROBES, len(terms))
                stay = got + after[essential] >= needed
                keep, got = keep[stay], got[stay]
            other = own[keep] != query_id
            ids, scores = np.concatenate([ids, own[keep][other]]), np.concatenate([scores, got[other]])
            if len(ids) >= k:
                order = np.lexsort((ids, -scores))[:k]
                ids, scores = ids[order], scores[order]
                needed = scores[-1] if needed is None else max(needed, scores[-1])
        return ids, scores


def _searched(k: int, width: int, most: int):
    """Rows (cell, kind, id, w, floor), those of one cell together and its index rows (kind 0) before its queries, to results."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        current, shard, held = None, None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            cells, kinds = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            new = np.flatnonzero(np.r_[True, (cells[1:] != cells[:-1]) | (kinds[1:] != kinds[:-1])])
            for lo, hi in zip(new, np.r_[new[1:], len(cells)]):
                part = batch.slice(lo, hi - lo)
                if cells[lo] != current:
                    current, shard, held = cells[lo], None, []
                if kinds[lo] == 0:
                    held.append((part.column(2).to_numpy(), _matrix(part.column(3), width)))
                    continue
                if shard is None:
                    if not held:
                        continue
                    shard, held = Shard(np.concatenate([x for x, _ in held]), np.concatenate([x for _, x in held]), most), []
                found: list[np.ndarray] = [np.empty((0, 3), np.int64)]
                asked = part.column(2).to_numpy()
                for query, (ids, scores) in zip(asked, shard.search_all(asked, _matrix(part.column(3), width), k, part.column(4).to_pylist())):
                    found.append(np.stack([np.full(len(ids), query), ids, scores.astype(np.int64)], axis=1))
                a = np.concatenate(found)
                yield pa.RecordBatch.from_arrays([pa.array(a[:, i]) for i in range(3)], ["query_id", "vec_id", "score"])

    return run


def top_k(index: DataFrame, queries: DataFrame, k: int = 5, rows: int = SHARD_ROWS, block: int = BLOCK_QUERIES) -> DataFrame:
    """index(id, w array<long>), queries(id, w) to (query_id, rank, vec_id, score); counting both and the searches run at once."""
    largest = F.coalesce(F.max(F.array_max(F.transform("w", F.abs))), F.lit(0))
    stats = [df.agg(F.count("*"), F.coalesce(F.max(F.size("w")), F.lit(0)), largest).first() for df in (index, queries)]
    (n, *_), (nq, *_) = stats
    width, most = (max(s[i] for s in stats) for i in (1, 2))
    shards = max(1, -(-n // rows))
    upto = lambda lo, hi: F.explode(F.sequence(F.lit(lo).cast("long"), F.lit(hi - 1).cast("long")))
    dealt = lambda m, *salt: F.pmod(F.xxhash64("id", *salt), F.lit(m).cast("long"))
    none = F.lit(None).cast("long").alias("floor")

    def searched(asked: DataFrame, lo: int, hi: int, size: int) -> DataFrame:
        """The queries asked (id, w, floor) against the shards from lo up to hi, in blocks of so many queries."""
        blocks = max(1, -(-nq // size))
        cell = (F.col("shard") * blocks + F.col("block")).alias("cell")
        left = index.withColumn("shard", dealt(shards)).where((F.col("shard") >= lo) & (F.col("shard") < hi)).withColumn("block", upto(0, blocks)).select(cell, F.lit(0).alias("kind"), "id", "w", none)
        right = asked.withColumn("block", dealt(blocks, F.lit(1))).withColumn("shard", upto(lo, hi)).select(cell, F.lit(1).alias("kind"), "id", "w", "floor")
        return left.union(right).repartition("cell").sortWithinPartitions("cell", "kind").mapInArrow(_searched(k, width, most), RESULT)

    first = stored(searched(queries.select("id", "w", none), 0, 1, rows), "first-shard")
    found = first
    if shards > 1:
        # the k-th score in the first shard, where it has so many
        bounds = first.groupBy(F.col("query_id").alias("id")).agg(F.when(F.count("*") >= k, F.min("score")).alias("floor"))
        found = first.union(searched(queries.select("id", "w").join(bounds, "id", "left"), 1, shards, block))
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")))
    out = stored(ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score"), "top-k")
    forget(first)
    return out
