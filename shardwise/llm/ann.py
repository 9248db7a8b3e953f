"""Approximate nearest neighbours: a neighbour graph by NN-descent in Spark joins, queries by greedy graph search.

The graph holds for each vector its K best neighbours found so far, with a flag for those not tried yet.
It starts from random hyperplane blocks: vectors with equal signs of a few projections are compared
with each other, in chunks of bounded size. A round of NN-descent takes per vector some new and some
old neighbours, both ways (at most SAMPLE of each kind each way, chosen by hash, so a hub's list stays
bounded), joins them with their vectors, and compares the neighbours of each vector with each other;
pairs that improve a list go back to it. Rounds end when few entries change.

A query walks the graph: it starts from its own entry (or from given ones), opens its best unopened
candidates, a beam at a time, and scores their neighbours, until none of its best WIDTH candidates is
unopened or the hop limit is reached. Work is grouped by blocks of vectors and of queries: a query's
vector is sent once per block and hop, not once per candidate. All steps are joins or cogroups of
written tables; nothing is collected.

Equal vectors are one node; its members come back with the answer, by smallest id, so copies do
not fill up lists. Inside the graph vectors are kept as half floats with a scale of their own, so one of another
magnitude takes no digits from the rest; the returned score is the inner product of the original vectors in double
precision, and ranks follow it. The walk gets wider with the logarithm of the number of vectors (see Params.wide).

Defined cases: vectors that are null, zero, or hold null or non-finite components take no part; shorter ones count as
filled up with zeros; magnitudes may differ by a factor of 10^15, beyond which products of the smallest count as equal in the walk; with K or fewer other vectors all are returned; ties go to the smaller id; an
empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import forget, stored


@dataclass(frozen=True)
class Params:
    """neighbours: K of the graph. sample: per kind and direction in a round. tables, chunk: random starts. block: vectors treated together in a round; home: those scored together for queries. width, beam, hops: greedy search."""

    neighbours: int = 30
    sample: int = 12
    tables: int = 4
    target: int = 400
    chunk: int = 1024
    rounds: int = 7
    least_change: float = 0.5
    block: int = 1024
    home: int = 8192
    query_block: int = 256
    width: int = 400
    beam: int = 80
    hops: int = 10
    seed: int = 17

    def wide(self, n: int) -> tuple[int, int]:
        """Width and hops for n vectors: both grow by a half with each doubling beyond 16,384."""
        width = round(self.width * (1 + 0.5 * max(0.0, np.log2(max(n, 1) / 16384))))
        return width, max(self.hops, -(-width // self.beam) + 5)


NODE = "id long, v binary, nbrs binary, sims binary, fresh binary"


def _packed_rows(x: np.ndarray, scale: float) -> list[bytes]:
    """Each row as its scale (float32, a share of the common one) and its components over that as half floats."""
    own = np.abs(x).max(axis=1)
    half = (x / own[:, None]).astype(np.float16)
    return [a.tobytes() + b.tobytes() for a, b in zip((own / scale).astype(np.float32), half)]


def _half(column) -> np.ndarray:
    """Binary column of such rows as a float32 matrix."""
    rows = column.to_pylist()
    raw = np.frombuffer(b"".join(rows), np.uint8).reshape(len(rows), -1)
    return raw[:, 4:].copy().view(np.float16).astype(np.float32) * raw[:, :4].copy().view(np.float32)


def _longs(x: bytes) -> np.ndarray:
    return np.frombuffer(x, np.int64)


def _best(own: np.ndarray, other: np.ndarray, sim: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per own the k entries with largest sim, each other once; ties to the smaller other."""
    order = np.lexsort((other, -sim, own))
    own, other, sim = own[order], other[order], sim[order]
    # drop repeated pairs: the first of each is its best
    pair = np.lexsort((np.arange(len(own)), other, own))
    again = np.zeros(len(own), bool)
    same = (own[pair][1:] == own[pair][:-1]) & (other[pair][1:] == other[pair][:-1])
    again[pair[1:][same]] = True
    own, other, sim = own[~again], other[~again], sim[~again]
    starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]]) if len(own) else np.empty(0, np.int64)
    rank = np.arange(len(own)) - np.repeat(starts, np.diff(np.r_[starts, len(own)]))
    keep = rank < k
    return own[keep], other[keep], sim[keep]


def _packed(own: np.ndarray, other: np.ndarray, sim: np.ndarray) -> pa.Table:
    """Rows own, others (binary), sims (binary); own must be grouped."""
    starts = np.flatnonzero(np.r_[True, own[1:] != own[:-1]]) if len(own) else np.empty(0, np.int64)
    ends = np.r_[starts[1:], len(own)] if len(own) else starts
    other, sim = other.astype(np.int64), sim.astype(np.float32)
    return pa.table({"id": pa.array(own[starts], pa.int64()), "others": pa.array([other[a:b].tobytes() for a, b in zip(starts, ends)], pa.binary()), "sims": pa.array([sim[a:b].tobytes() for a, b in zip(starts, ends)], pa.binary())})


FOUND = "id long, others binary, sims binary"


def _block(column: str, blocks: int, seed: int = 0):
    return F.pmod(F.xxhash64(column, F.lit(seed)), F.lit(blocks).cast("long"))


def prepared(df: DataFrame, id_col: str, vector: str) -> DataFrame:
    """(vec_id, x array<double>) of the vectors that take part."""
    ok = F.col(vector).isNotNull() & (F.size(vector) > 0) & ~F.exists(vector, lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double")) == float("inf"))) & F.exists(vector, lambda x: x != 0)
    rows = df.where(ok & F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(vector, lambda x: x.cast("double")).alias("x"))
    width = rows.agg(F.max(F.size("x"))).first()[0] or 0
    return rows.withColumn("x", F.concat("x", F.array_repeat(F.lit(0.0), F.lit(width) - F.size("x"))))


class Index:
    """The graph over distinct vectors, its members, and the parameters."""

    def __init__(self, vectors: DataFrame, params: Params = Params()):
        self.p = params
        rows = stored(vectors.withColumn("h", F.xxhash64("x")).withColumn("h2", F.xxhash64("x", F.lit(7))), "vectors")
        keyed = rows.groupBy("h", "h2").agg(F.min("vec_id").alias("id"), F.first("x").alias("x"))
        stats = rows.agg(F.max(F.size("x")), F.max(F.array_max(F.transform("x", F.abs)))).first()
        self.width, self.scale = int(stats[0] or 0), float(stats[1] or 1.0)
        scale, width = self.scale, self.width

        def halves(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                x = b.column(1).flatten().to_numpy().reshape(-1, width)
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(_packed_rows(x, scale) if len(x) else [], pa.binary())], ["id", "v"])

        self.nodes = stored(keyed.select("id", "x").mapInArrow(halves, "id long, v binary"), "nodes")
        self.members = rows.join(keyed.select("h", "h2", "id"), ["h", "h2"]).select("id", "vec_id", "x")
        self.rows = rows
        self.n = self.nodes.count()
        self.blocks = max(1, -(-self.n // params.block))
        self.graph = self._start() if self.n else None

    def _start(self) -> DataFrame:
        p, width = self.p, self.width
        bits = max(0, int(np.ceil(np.log2(max(1.0, self.n / p.target)))))

        def signs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            planes = np.random.default_rng(p.seed).standard_normal((p.tables, width, bits)).astype(np.float32)
            for b in batches:
                if b.num_rows:
                    x = _half(b.column(1))
                    codes = [((x @ planes[t] > 0) @ (1 << np.arange(bits, dtype=np.int64)) if bits else np.zeros(len(x), np.int64)) * p.tables + t for t in range(p.tables)]
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(codes)), pa.concat_arrays([b.column(0)] * p.tables), pa.concat_arrays([b.column(1)] * p.tables)], ["code", "id", "v"])

        coded = self.nodes.mapInArrow(signs, "code long, id long, v binary")
        sizes = stored(coded.groupBy("code").count(), "codes")
        parts = coded.join(F.broadcast(sizes) if bits <= 14 else sizes, "code").withColumn("part", _block("id", 1 << 30) % F.ceil(F.col("count") / p.chunk))

        def compare(t: pa.Table) -> pa.Table:
            ids, x = t.column("id").to_numpy(), _half(t.column("v"))
            k = min(p.neighbours, len(ids) - 1)
            if k < 1:
                return _packed(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
            s = x @ x.T
            np.fill_diagonal(s, -np.inf)
            top = np.argpartition(-s, k - 1, axis=1)[:, :k]
            own = np.repeat(np.arange(len(ids)), k)
            return _packed(ids[own], ids[top.ravel()], s[own, top.ravel()])

        found = parts.groupBy("code", "part").applyInArrow(compare, FOUND)
        empty = self.nodes.select("id", "v", F.lit(b"").alias("nbrs"), F.lit(b"").alias("sims"), F.lit(b"").alias("fresh"))
        graph, _ = self._merged(empty, found)
        return graph

    def _merged(self, graph: DataFrame, found: DataFrame) -> tuple[DataFrame, float]:
        """Put found (id, others, sims) into the lists; the share of changed entries per vector."""
        k = self.p.neighbours

        def merge(g: pa.Table, f: pa.Table) -> pa.Table:
            ids = g.column("id").to_numpy()
            if not len(ids):
                return pa.table({c: pa.array([], t) for c, t in (("id", pa.int64()), ("v", pa.binary()), ("nbrs", pa.binary()), ("sims", pa.binary()), ("fresh", pa.binary()), ("changed", pa.int64()))})
            nbrs = [_longs(x) for x in g.column("nbrs").to_pylist()]
            sims = [np.frombuffer(x, np.float32) for x in g.column("sims").to_pylist()]
            fresh = [np.frombuffer(x, np.uint8) for x in g.column("fresh").to_pylist()]
            place = {i: j for j, i in enumerate(ids.tolist())}
            more: dict[int, list] = {}
            for i, o, s in zip(f.column("id").to_pylist(), f.column("others").to_pylist(), f.column("sims").to_pylist()):
                more.setdefault(place[i], []).append((_longs(o), np.frombuffer(s, np.float32)))
            changed = [0] * len(ids)
            for j, got in more.items():
                o, s = np.concatenate([x[0] for x in got]), np.concatenate([x[1] for x in got])
                new = ~np.isin(o, nbrs[j])
                o, at = np.unique(o[new], return_index=True)
                s = s[new][at]
                other, sim, flag = np.concatenate([nbrs[j], o]), np.concatenate([sims[j], s]), np.concatenate([fresh[j], np.ones(len(o), np.uint8)])
                order = np.lexsort((other, -sim))[:k]
                changed[j] = int((order >= len(nbrs[j])).sum())
                nbrs[j], sims[j], fresh[j] = other[order], sim[order], flag[order]
            blob = lambda xs: pa.array([x.tobytes() for x in xs], pa.binary())
            return pa.table({"id": g.column("id"), "v": g.column("v"), "nbrs": blob(nbrs), "sims": blob(sims), "fresh": blob(fresh), "changed": pa.array(changed, pa.int64())})

        b = _block("id", self.blocks)
        out = stored(graph.groupBy(b).cogroup(found.groupBy(b)).applyInArrow(merge, NODE + ", changed long"), "graph")
        changed = out.agg(F.sum("changed")).first()[0] or 0
        kept = out.drop("changed")
        kept._stored_path = out._stored_path
        return kept, changed / max(1, self.n)

    def build(self) -> "Index":
        """Rounds of NN-descent until few entries change."""
        if not self.n:
            return self
        for turn in range(self.p.rounds):
            nxt, changed = self._round(turn)
            forget(self.graph)
            self.graph = nxt
            if changed < self.p.least_change:
                break
        return self

    def _round(self, turn: int) -> tuple[DataFrame, float]:
        p = self.p

        def sampled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            """Edges (u, w, new) that take part, and each vector's list with those flags cleared."""
            for b in batches:
                u, w, new = [], [], []
                for i, x, f in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist()):
                    nbrs, fresh = _longs(x), np.frombuffer(f, np.uint8)
                    coin = (nbrs * 2654435761 + i * 40503 + turn * 7919) & 0xFFFF
                    for flag in (1, 0):
                        at = np.flatnonzero(fresh == flag)
                        at = at[np.argsort(coin[at], kind="stable")[: p.sample]]
                        u.append(np.full(len(at), i))
                        w.append(nbrs[at])
                        new.append(np.full(len(at), flag, np.int32))
                cat = lambda xs, t: np.concatenate(xs).astype(t) if xs else np.empty(0, t)
                yield pa.RecordBatch.from_arrays([pa.array(cat(u, np.int64)), pa.array(cat(w, np.int64)), pa.array(cat(new, np.int32))], ["u", "w", "new"])

        edges = stored(self.graph.select("id", "nbrs", "fresh").mapInArrow(sampled, "u long, w long, new int"), "edges")
        forward = edges.select(F.col("u").alias("owner"), F.col("w").alias("member"), "new")
        # the other way round, at most so many per vector and kind: a hub is in many lists
        pick = Window.partitionBy("w", "new").orderBy(F.xxhash64("u", F.lit(turn)), "u")
        reverse = edges.withColumn("r", F.row_number().over(pick)).where(F.col("r") <= p.sample).select(F.col("w").alias("owner"), F.col("u").alias("member"), "new")
        pairs = forward.union(reverse).groupBy("owner", "member").agg(F.max("new").alias("new"))
        k, size = p.neighbours, 4
        worst = F.expr(f"CASE WHEN length(sims) < {k * size} THEN NULL ELSE substring(sims, {k * size - 3}, 4) END")
        known = self.graph.select(F.col("id").alias("member"), "v", worst.alias("worst"))
        local = pairs.join(known, "member").select("owner", "member", "new", "v", "worst")

        def compare(t: pa.Table) -> pa.Table:
            owner, member, new = t.column("owner").to_numpy(), t.column("member").to_numpy(), t.column("new").to_numpy()
            x = _half(t.column("v"))
            least = np.array([np.frombuffer(w, np.float32)[0] if w else -np.inf for w in t.column("worst").to_pylist()], np.float32)
            order = np.lexsort((-new, owner))
            owner, member, new, x, least = owner[order], member[order], new[order], x[order], least[order]
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            a, b, c = [], [], []
            for lo, hi in zip(starts, np.r_[starts[1:], len(owner)]):
                m = int(new[lo:hi].sum())
                if not m or hi - lo < 2:
                    continue
                s = x[lo : lo + m] @ x[lo:hi].T
                i, j = np.nonzero((s > least[lo : lo + m, None]) | (s > least[None, lo:hi]))
                keep = i != j
                i, j = i[keep], j[keep]
                v = s[i, j]
                up = v > least[lo + i]
                down = v > least[lo + j]
                a += [member[lo + i[up]], member[lo + j[down]]]
                b += [member[lo + j[up]], member[lo + i[down]]]
                c += [v[up], v[down]]
            if not a:
                return _packed(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))
            return _packed(*_best(np.concatenate(a), np.concatenate(b), np.concatenate(c), k))

        found = local.groupBy(_block("owner", self.blocks * 4)).applyInArrow(compare, FOUND)

        def cleared(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                out = []
                for i, x, f in zip(b.column(0).to_pylist(), b.column(2).to_pylist(), b.column(4).to_pylist()):
                    nbrs, fresh = _longs(x), np.frombuffer(f, np.uint8).copy()
                    coin = (nbrs * 2654435761 + i * 40503 + turn * 7919) & 0xFFFF
                    at = np.flatnonzero(fresh == 1)
                    fresh[at[np.argsort(coin[at], kind="stable")[: p.sample]]] = 0
                    out.append(fresh.tobytes())
                yield pa.RecordBatch.from_arrays([*b.columns[:4], pa.array(out, pa.binary())], ["id", "v", "nbrs", "sims", "fresh"])

        out = self._merged(self.graph.select("id", "v", "nbrs", "sims", "fresh").mapInArrow(cleared, NODE), found)
        forget(edges)
        return out

    def adjacency(self) -> DataFrame:
        """(id, near): neighbours both ways, at most K each way."""
        k = self.p.neighbours

        def edges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                lists = [_longs(x) for x in b.column(1).to_pylist()]
                own = np.repeat(b.column(0).to_numpy(), [len(x) for x in lists])
                sims = np.concatenate([np.frombuffer(x, np.float32) for x in b.column(2).to_pylist()] or [np.empty(0, np.float32)])
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), pa.array(np.concatenate(lists) if lists else np.empty(0, np.int64), pa.int64()), pa.array(sims, pa.float32())], ["u", "w", "sim"])

        flat = self.graph.select("id", "nbrs", "sims").mapInArrow(edges, "u long, w long, sim float")
        pick = Window.partitionBy("w").orderBy(F.desc("sim"), "u")
        back = flat.withColumn("r", F.row_number().over(pick)).where(F.col("r") <= k).select(F.col("w").alias("id"), F.col("u").alias("o"))
        both = flat.select(F.col("u").alias("id"), F.col("w").alias("o")).union(back)
        return stored(both.groupBy("id").agg(F.collect_set("o").alias("near")).join(self.nodes, "id", "right").select("id", "v", F.coalesce("near", F.array().cast("array<long>")).alias("near")), "adjacency")

    def search(self, queries: DataFrame, k: int) -> DataFrame:
        """queries(query_id, x array<double>, entry long) to (query_id, id): candidates left by the greedy walk, best first kept up to width."""
        p, scale = self.p, self.scale
        width, hops = p.wide(self.n)
        nq = queries.count()
        qblocks = max(1, -(-nq // p.query_block))
        near = self.adjacency()
        blocks = max(1, -(-self.n // p.home))
        state_t = "query_id long, q binary, ids binary, sims binary, open binary, ask binary"

        def begin(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                q = [(np.array(x, np.float64) / scale).astype(np.float32).tobytes() for x in b.column(1).to_pylist()]
                none = pa.array([b""] * len(q), pa.binary())
                ask = pa.array([np.array([e], np.int64).tobytes() for e in b.column(2).to_pylist()], pa.binary())
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(q, pa.binary()), none, none, none, ask], ["query_id", "q", "ids", "sims", "open", "ask"])

        state = stored(queries.select("query_id", "x", "entry").mapInArrow(begin, state_t), "walk")
        lists = near.select("id", "near")

        def asked(column: str) -> DataFrame:
            """(query_id, q, id) per id in a binary list, grouped per block of vectors by the caller."""
            def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
                for b in batches:
                    for at in range(0, b.num_rows, 64):
                        part = b.slice(at, 64)
                        ids = [_longs(x) for x in part.column(1).to_pylist()]
                        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(part.column(0).to_numpy(), [len(x) for x in ids]), pa.int64()), pa.array(np.concatenate(ids), pa.int64())], ["query_id", "id"])

            return state.select("query_id", column).mapInArrow(run, "query_id long, id long")

        for _ in range(hops):
            # neighbours of what the walk opens: ids only
            opened = asked("ask").join(lists, "id").groupBy("query_id").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("next"))
            first = _ == 0
            # below the last of a full list no score can enter it: such scores stay where they were made
            least = F.expr(f"CASE WHEN length(sims) < {4 * width} THEN NULL ELSE substring(sims, {4 * width - 3}, 4) END")
            wanted = state.join(opened, "query_id").select("query_id", "q", "ids", "ask", "next", least.alias("least"))

            def deal(batches: Iterator[pa.RecordBatch], first: bool = first) -> Iterator[pa.RecordBatch]:
                """Candidates that are not among the best yet, with the query's vector once per block of vectors."""
                for b in batches:
                    for at in range(0, b.num_rows, 128):
                        part = b.slice(at, 128)
                        rows: tuple[list, ...] = ([], [], [], [], [])
                        for i, q, ids, ask, nxt, last in zip(*(part.column(c).to_pylist() for c in range(4)), part.column(4), part.column(5).to_pylist()):
                            c = np.setdiff1d(nxt.values.to_numpy(), _longs(ids))
                            if first:
                                c = np.union1d(c, _longs(ask))
                            c = np.sort(c)
                            home = _home(c, blocks)
                            for h in np.unique(home):
                                for to, v in zip(rows, (int(h), i, q, c[home == h].tobytes(), last)):
                                    to.append(v)
                        types = (pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary())
                        yield pa.RecordBatch.from_arrays([pa.array(r, t) for r, t in zip(rows, types)], ["home", "query_id", "q", "c", "least"])

            dealt = wanted.mapInArrow(deal, "home long, query_id long, q binary, c binary, least binary")

            def score(x: pa.Table, y: pa.Table) -> pa.Table:
                rows = []
                if x.num_rows and y.num_rows:
                    ids, v = x.column("id").to_numpy(), _half(x.column("v"))
                    order = np.argsort(ids)
                    ids, v = ids[order], v[order]
                    for i, q, c, last in zip(*(y.column(n).to_pylist() for n in ("query_id", "q", "c", "least"))):
                        c = _longs(c)
                        s = (v[np.searchsorted(ids, c)] @ np.frombuffer(q, np.float32)).astype(np.float32)
                        if last:
                            in_reach = s >= np.frombuffer(last, np.float32)[0]
                            c, s = c[in_reach], s[in_reach]
                        if len(c):
                            rows.append((i, c.tobytes(), s.tobytes()))
                columns = list(zip(*rows)) or [[]] * 3
                return pa.table({n: pa.array(c, t) for n, c, t in zip(("query_id", "c", "s"), columns, (pa.int64(), pa.binary(), pa.binary()))})

            homes = near.select(_home_column("id", blocks).alias("home"), "id", "v")
            scored = homes.groupBy("home").cogroup(dealt.groupBy("home")).applyInArrow(score, "query_id long, c binary, s binary")

            def step(x: pa.Table, y: pa.Table) -> pa.Table:
                got: dict[int, list] = {}
                for i, c, s in zip(y.column("query_id").to_pylist(), y.column("c").to_pylist(), y.column("s").to_pylist()):
                    got.setdefault(i, []).append((_longs(c), np.frombuffer(s, np.float32)))
                rows = []
                for i, q, ids, sims, opened in zip(*(x.column(c).to_pylist() for c in ("query_id", "q", "ids", "sims", "open"))):
                    new = got.get(i, [])
                    ids = np.concatenate([_longs(ids), *[a for a, _ in new]])
                    sims = np.concatenate([np.frombuffer(sims, np.float32), *[s for _, s in new]])
                    opened = np.concatenate([np.frombuffer(opened, np.uint8), np.zeros(len(ids) - len(opened), np.uint8)])
                    # only the best stay: one that fell out and is met again falls out again, as the last one's score never falls
                    order = np.lexsort((ids, -sims))[:width]
                    ids, sims, opened = ids[order], sims[order], opened[order]
                    at = np.flatnonzero(opened == 0)[: p.beam]
                    opened[at] = 1
                    rows.append((i, q, ids.tobytes(), sims.tobytes(), opened.tobytes(), ids[at].tobytes()))
                columns = list(zip(*rows)) or [[]] * 6
                return pa.table({n: pa.array(c, t) for n, c, t in zip(("query_id", "q", "ids", "sims", "open", "ask"), columns, (pa.int64(), *[pa.binary()] * 5))})

            b = _block("query_id", qblocks, 3)
            nxt = stored(state.groupBy(b).cogroup(scored.groupBy(b)).applyInArrow(step, state_t), "walk")
            forget(state)
            state = nxt
            if state.where(F.length("ask") > 0).isEmpty():
                break

        def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                lists = [_longs(x) for x in b.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(b.column(0).to_numpy(), [len(x) for x in lists]), pa.int64()), pa.array(np.concatenate(lists) if lists else np.empty(0, np.int64), pa.int64()), pa.array(np.concatenate([np.arange(len(x)) for x in lists]) if lists else np.empty(0, np.int64), pa.int64())], ["query_id", "id", "place"])

        # half floats can swap close candidates: some more than k are scored again exactly
        return state.select("query_id", "ids").mapInArrow(best, "query_id long, id long, place long").where(F.col("place") < 2 * k + 10).select("query_id", "id")


def _home(ids: np.ndarray, blocks: int) -> np.ndarray:
    return ((ids.astype(np.uint64) * np.uint64(0x9E3779B1)) & np.uint64(0xFFFFFFFF)).astype(np.int64) % blocks


def _home_column(column: str, blocks: int):
    """The same as _home, as a column expression."""
    low = F.col(column).bitwiseAND(F.lit(0xFFFFFFFF))
    # 32 x 32 bits in two halves, so that nothing overflows
    part = (F.shiftright(low, 16) * F.lit(0x9E3779B1)).bitwiseAND(F.lit(0xFFFF)) * F.lit(65536) + low.bitwiseAND(F.lit(0xFFFF)) * F.lit(0x9E3779B1)
    return part.bitwiseAND(F.lit(0xFFFFFFFF)) % F.lit(blocks).cast("long")


def nearest(vectors: DataFrame, is_query, k: int = 20, id_col: str = "vec_id", vector: str = "embedding", params: Params = Params()) -> DataFrame:
    """Each query's k nearest other rows found: (query_id, rank, vec_id, score). is_query: a condition on the id column."""
    rows = prepared(vectors, id_col, vector)
    index = Index(rows, params).build()
    schema = "query_id long, rank int, vec_id long, score double"
    if not index.n:
        return vectors.sparkSession.createDataFrame([], schema)
    queries = index.members.where(is_query).select(F.col("vec_id").alias("query_id"), "x", F.col("id").alias("entry"))
    queries = stored(queries, "queries")
    found = stored(index.search(queries, k), "found")
    # a node's smallest k + 1 members are all that can be among the k nearest
    rank = F.row_number().over(Window.partitionBy("id").orderBy("vec_id"))
    members = index.members.withColumn("r", rank).where(F.col("r") <= k + 1).select("id", "vec_id", F.col("x").alias("y"))
    pairs = found.join(queries.select("query_id", "x"), "query_id").join(members, "id").where("vec_id <> query_id")
    dot = F.aggregate(F.zip_with("x", "y", lambda a, b: a * b), F.lit(0.0).cast("double"), lambda s, v: s + v)
    scored = pairs.select("query_id", "vec_id", dot.alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
