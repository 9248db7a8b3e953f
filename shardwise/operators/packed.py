"""A turn's counts on a packed graph: blocks of whole queries, read in place, against one broadcast array of buckets.

The edges of a run never change, only the vertices' buckets do. A packed graph is dealt by query once; a turn then sends
each task the bucket of every vertex, a byte each, and gets back, by vertex, the sums that a proposal needs.
Edges do not travel any more. All numbers are the integers of the general way, so results are the same bit by bit. For
graphs whose vertices fit a checked broadcast (PACK_VERTICES) and whose queries fit a task (WHOLE_QUERY); others go the general way.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.kernel import PLACES, Kernel, _terms, gain_bin
from ..session import forget, stored
from . import refine

#: Edges from which packing pays.
PACK_EDGES = 1_000_000

#: Vertices whose buckets are broadcast, buckets of a level, and sums (vertices times children of a parent) that a task holds, at most.
PACK_VERTICES, PACK_BUCKETS, PACK_SUMS = 1 << 22, 64, 1 << 24

#: Edges of a block (a larger query is a block by itself), edges of a part that make another part worth while, and edges of a part at most.
BLOCK, PART, MOST = 1 << 18, 1 << 23, 1 << 28

#: Counts of queries times buckets that are held at once.
CELLS = 1 << 21

BLOCKS = pa.schema([("sizes", pa.binary()), ("members", pa.binary())])
SUMS = pa.schema([("r", pa.int32()), ("idx", pa.binary()), ("sums", pa.binary()), ("f", pa.int64()), ("sq", pa.int64()), ("dead", pa.int64()), ("pf", pa.float64())])
MOVES = pa.schema([("vid", pa.int64()), ("parent", pa.int32()), ("src", pa.int32()), ("dst", pa.int32()), ("gain_fx", pa.int64())])


@dataclass(frozen=True)
class Form:
    """A level as arrays: its buckets in order, with parent, place among the parent's children, and all of these children (-1: none).

    tables: per bucket what c members of a query are worth against none, for c = 0, 1, ..., the last entry for all beyond; None: c itself.
    """

    names: np.ndarray
    parents: np.ndarray
    family: np.ndarray
    place: np.ndarray
    children: np.ndarray
    starts: np.ndarray
    tables: list[np.ndarray | None]

    @property
    def alike(self) -> bool:
        return all(t is self.tables[0] for t in self.tables)

    def worth(self, counts: np.ndarray) -> np.ndarray:
        """counts by query and bucket: the kernel's idle term less its term of arriving, for each."""
        if self.alike:
            return _worth(self.tables[0], counts)
        return np.stack([_worth(t, counts[:, b]) for b, t in enumerate(self.tables)], axis=1)


def _worth(table: np.ndarray | None, counts: np.ndarray) -> np.ndarray:
    return counts if table is None else table[np.minimum(counts, len(table) - 1)]


def _table(kernel: Kernel, t: int) -> np.ndarray | None:
    if kernel.objective == "clique":
        return None
    if kernel.objective == "fanout":
        return np.array([0, 1], np.int64)
    terms = _terms(kernel.base(t))
    return np.array([(1 << PLACES) - x for x in terms] + [1 << PLACES], np.int64)


def form_of(split, kernel: Kernel, lookahead: bool) -> Form:
    """split: (parent, children) as the plan of a level has them, each (first final bucket, number of final buckets)."""
    names, parents, family, place, children, starts, ts = [], [], [], [], [], [], []
    width = max(len(c) for _, c in split)
    for number, ((parent, _), below) in enumerate(split):
        starts.append(len(names))
        line = [starts[-1] + i for i in range(len(below))] + [-1] * (width - len(below))
        for i, (name, t) in enumerate(below):
            names.append(name)
            parents.append(parent)
            family.append(number)
            place.append(i)
            children.append(line)
            ts.append(t if lookahead else 1)
    tables = {t: _table(kernel, t) for t in set(ts)}
    if kernel.objective != "pfanout":
        tables = dict.fromkeys(tables, tables[ts[0]])
    ints = lambda x: np.array(x, np.int32)
    return Form(ints(names), ints(parents), np.array(family, np.intp), np.array(place, np.intp), np.array(children, np.intp), np.array(starts, np.intp), [tables[t] for t in ts])


def _blocks_of(vids) -> object:
    """Rows (qid, vid) in the order of qid to blocks of whole queries: their sizes, and their members' numbers."""

    def block(qid: np.ndarray, vid: np.ndarray) -> pa.RecordBatch:
        cuts = np.flatnonzero(np.r_[True, qid[1:] != qid[:-1], True])
        members = np.searchsorted(vids.value, vid).astype(np.int32)
        return pa.RecordBatch.from_arrays([pa.array([np.diff(cuts).astype(np.int32).tobytes()], pa.binary()), pa.array([members.tobytes()], pa.binary())], schema=BLOCKS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, rows = [], 0
        for batch in batches:
            if batch.num_rows:
                held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
                rows += batch.num_rows
            if rows >= BLOCK:
                qid, vid = (np.concatenate(x) for x in zip(*held))
                cut = int(np.searchsorted(qid, qid[-1]))  # the last query may go on
                if cut:
                    yield block(qid[:cut], vid[:cut])
                held, rows = [(qid[cut:], vid[cut:])], len(qid) - cut
        if rows:
            yield block(*(np.concatenate(x) for x in zip(*held)))

    return run


def _pieces(batches: Iterator[pa.RecordBatch], buckets: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(sizes, members) of blocks, in pieces of few enough queries."""
    step = max(1, CELLS // buckets)
    for batch in batches:
        for s, m in zip(batch.column(0), batch.column(1)):
            sizes, members = np.frombuffer(s.as_buffer(), np.int32), np.frombuffer(m.as_buffer(), np.int32)
            ends = np.r_[0, np.cumsum(sizes, dtype=np.int64)]
            for i in range(0, len(sizes), step):
                j = min(i + step, len(sizes))
                yield sizes[i:j], members[ends[i] : ends[j]].astype(np.intp)


def _counter(at, form: Form, largest: int, p: float, prune: bool, ranges: int, sums: bool) -> object:
    """Blocks to rows of SUMS: by range of vertices what a task's queries say of them, and one row of totals."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where, k, width = at.value, len(form.names), form.children.shape[1]
        n, gaps = len(where), bool((form.children < 0).any())
        acc, met = (np.zeros((width, n), np.int64), np.zeros(n, bool)) if sums else (None, None)
        seen, dead = np.zeros(largest + 1, np.int64), 0
        for sizes, members in _pieces(batches, k):
            row = np.repeat(np.arange(len(sizes), dtype=np.intp) * k, sizes)
            b = where[members].astype(np.intp)
            cell = row + b
            flat = np.bincount(cell, minlength=len(sizes) * k)
            seen += np.bincount(flat, minlength=largest + 1)
            counts = flat.reshape(-1, k)
            alive = members
            if prune:
                whole = np.add.reduceat(counts, form.starts, axis=1)
                dead += int((whole == 1).sum())
                if sums:
                    alive = members[whole[row // k, form.family[b]] > 1]
            if not sums:
                continue
            met[alive] = True
            there, own = form.worth(counts).reshape(-1), form.worth(np.maximum(counts - 1, 0)).reshape(-1)
            mine, place = -own[cell], form.place[b]
            for j in range(width):
                child = form.children[b, j]
                other = there[row + np.maximum(child, 0)]
                if gaps:
                    other = np.where(child < 0, 0, other)
                np.add.at(acc[j], members, np.where(place == j, mine, other))
        seen[1] -= dead
        c = np.flatnonzero(seen[1:]) + 1
        f, sq, pf = int(seen[c].sum()), int((seen[c] * c * c).sum()), float((seen[c] * (1.0 - (1.0 - p) ** c.astype(float))).sum())
        yield pa.RecordBatch.from_pylist([{"r": 0, "idx": b"", "sums": b"", "f": f, "sq": sq, "dead": dead, "pf": pf}], schema=SUMS)
        if not sums:
            return
        idx = np.flatnonzero(met)
        cuts = np.searchsorted(idx, [n * r // ranges for r in range(ranges + 1)])
        for r in range(ranges):
            some = idx[cuts[r] : cuts[r + 1]]
            if len(some):
                yield pa.RecordBatch.from_pylist([{"r": r, "idx": some.astype(np.int32).tobytes(), "sums": acc[:, some].tobytes(), "f": 0, "sq": 0, "dead": 0, "pf": 0.0}], schema=SUMS)

    return run


def _proposer(at, vids, form: Form, given: bool, ranges: int) -> object:
    """Rows of SUMS, all of a range in one task, to the best target of each vertex; ties to the lowest. given: targets that no query uses count too."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        where, width, held = at.value, form.children.shape[1], {}
        n = len(where)
        for batch in batches:
            for r, idx, sums in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2)):
                some = np.frombuffer(idx.as_buffer(), np.int32)
                if len(some):
                    lo = n * r // ranges
                    acc, met = held.setdefault(r, (np.zeros((width, n * (r + 1) // ranges - lo), np.int64), np.zeros(n * (r + 1) // ranges - lo, bool)))
                    acc[:, some - lo] += np.frombuffer(sums.as_buffer(), np.int64).reshape(width, -1)
                    met[some - lo] = True
        for r, (acc, met) in held.items():
            lo, some = n * r // ranges, np.flatnonzero(met)
            b, part = where[lo + some].astype(np.intp), acc[:, some]
            each, place = np.arange(len(some)), form.place[b]
            own = part[place, each]
            free = form.children[b].T >= 0
            free[place, each] = False
            if not given:
                free &= part > 0
            option = np.where(free, part, np.iinfo(np.int64).min)
            best = option.argmax(axis=0)
            gain = own + part[best, each]
            good = free[best, each] & (given | (gain > 0))
            b, best, gain, vid = b[good], best[good], gain[good], vids.value[lo + some[good]]
            yield pa.RecordBatch.from_arrays([pa.array(vid), pa.array(form.parents[b]), pa.array(form.names[b]), pa.array(form.names[form.children[b, best]]), pa.array(gain)], schema=MOVES)

    return run


class Packed:
    """A graph's blocks, its vertices, and how many queries it has and members the largest of them."""

    def __init__(self, table: DataFrame, vertices: DataFrame, vids: np.ndarray, known, queries: int, largest: int, parts: int):
        self.table, self.vertices, self.vids, self.known = table, vertices, vids, known
        self.queries, self.largest, self.parts = queries, largest, parts

    def fits(self, spec) -> bool:
        """Whether a run's levels, and its kernel's terms, are small enough for arrays."""
        if spec.k > PACK_BUCKETS or len(self.vids) * min(spec.arity or spec.k, spec.k) > PACK_SUMS:
            return False
        if spec.objective != "pfanout":
            return True
        few = [_terms(1 - spec.p / t) for t in range(1, spec.k + 1 if spec.lookahead else 2)]
        return all(x is not None and (len(x) < 2 or x[1] < 1 << PLACES) for x in few)

    def _placed(self, state: DataFrame, names: np.ndarray | None):
        """Bucket numbers by vertex, of all vertices of the graph; None if some have no bucket. names None: those that the state has."""
        got = state.select("vid", "bucket").toArrow()
        vid, bucket = got.column("vid").to_numpy(), got.column("bucket").to_numpy()
        if names is None:
            names = np.unique(bucket)
        at = np.minimum(np.searchsorted(self.vids, vid), len(self.vids) - 1)
        ours = self.vids[at] == vid
        if len(names) > PACK_BUCKETS or int(ours.sum()) != len(self.vids):
            return None, names
        where = np.zeros(len(self.vids), np.uint8)
        where[at[ours]] = np.searchsorted(names, bucket[ours])
        return where, names

    def totals(self, state: DataFrame, form: Form, p: float, prune: bool) -> tuple[int, float, int, int]:
        """(f, pf, sq, dead): used buckets, their smoothed number, squares of counts, all without the edges that are alone in their parent, and how many these are."""
        where, _ = self._placed(state, form.names)
        return self._totals(where, form, p, prune)

    def _totals(self, where: np.ndarray, form: Form, p: float, prune: bool) -> tuple[int, float, int, int]:
        sent = self.table.sparkSession.sparkContext.broadcast(where)
        counted = self.table.mapInArrow(_counter(sent, form, self.largest, p, prune, 1, False), "r int, idx binary, sums binary, f long, sq long, dead long, pf double")
        got = counted.agg(*[F.sum(c).alias(c) for c in ("f", "pf", "sq", "dead")]).first()
        sent.unpersist()
        return tuple(got)

    def proposals(self, state: DataFrame, form: Form, p: float, prune: bool, given: bool) -> tuple[DataFrame, tuple[int, float, int, int]]:
        """What best_of_parts gives, as a stored table, and the totals."""
        where, _ = self._placed(state, form.names)
        sent, ranges, seen = self.table.sparkSession.sparkContext.broadcast(where), 4 * self.parts, Observation()
        counted = self.table.mapInArrow(_counter(sent, form, self.largest, p, prune, ranges, True), "r int, idx binary, sums binary, f long, sq long, dead long, pf double")
        counted = counted.observe(seen, *[F.sum(c).alias(c) for c in ("f", "pf", "sq", "dead")])
        dealt = counted.select("r", "idx", "sums").repartition(self.parts, "r")
        found = dealt.mapInArrow(_proposer(sent, self.known, form, given, ranges), "vid long, parent int, src int, dst int, gain_fx long")
        table = stored(found.withColumn("gbin", gain_bin(F.col("gain_fx"))), "proposals")
        got = seen.get
        sent.unpersist()
        return table, tuple(got[c] for c in ("f", "pf", "sq", "dead"))

    def fanout(self, assign: DataFrame) -> int | None:
        """Buckets that the queries touch, all together; None if the assignment is not one of all vertices to few buckets."""
        where, names = self._placed(assign, None)
        if where is None:
            return None
        return self._totals(where, form_of([((0, len(names)), [(int(x), 1) for x in names])], Kernel("fanout", 1.0), False), 1.0, False)[0]

    def drop(self) -> None:
        forget(self.table, self.vertices)
        self.known.unpersist()


def pack(edges: DataFrame) -> Packed | None:
    """The packed form of a stored table of edges; None where the graph is too small for it to pay, or too large."""
    spark = edges.sparkSession
    count = edges.count()
    if count < PACK_EDGES:
        return None
    degrees = edges.groupBy("qid").agg(F.count("*").alias("d"))
    queries, largest = degrees.agg(F.count("qid"), F.max("d")).first()
    shuffles = int(spark.conf.get("spark.sql.shuffle.partitions"))
    parts = min(shuffles, max(spark.sparkContext.defaultParallelism, -(-count // PART)))
    vertices = stored(edges.select("vid").distinct(), "vertices")
    if largest > refine.WHOLE_QUERY or count // parts > MOST or vertices.count() > PACK_VERTICES:
        forget(vertices)
        return None
    vids = np.sort(vertices.toArrow().column("vid").to_numpy())
    known = spark.sparkContext.broadcast(vids)
    table = stored(edges.select("qid", "vid").repartition(parts, "qid").sortWithinPartitions("qid").mapInArrow(_blocks_of(known), "sizes binary, members binary"), "packed")
    return Packed(table, vertices, vids, known, queries, largest, parts)


def vertices_of(edges: DataFrame) -> DataFrame:
    """(vid) of the data vertices of edges, each once."""
    packed = getattr(edges, "_packed", None)
    return edges.select("vid").distinct() if packed is None else packed.vertices
