"""The partitioners: straight to k buckets, and recursive with any arity, on one engine.

A level has parents, each with some final buckets below it, split among children as evenly as possible. A
bucket's name is the number of the first final bucket below it, so the last level's names are the final
buckets and a level's parent is found from the plan of the levels, a table of at most k rows. One
iteration is one job for all parents of the level: it writes the new state and, by observed metrics of
that same job, what the previous state's objective was and how many vertices moved.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions.coin import FULL, coin
from ..functions.kernel import Kernel, pfanout_term
from ..model import PartitionResult, PartitionSpec
from ..operators import refine
from ..operators.packed import form_of, vertices_of
from ..session import forget, small, stored

Node = tuple[int, int]  # first final bucket, number of final buckets


def shares_of(node: Node, arity: int) -> list[Node]:
    """Children of a node: its final buckets in as even parts as possible, larger ones first."""
    first, t = node
    parts = min(arity, t)
    out = []
    for i in range(parts):
        size = t // parts + (i < t % parts)
        out.append((first, size))
        first += size
    return out


def level_plan(k: int, arity: int | None) -> list[list[tuple[Node, list[Node]]]]:
    """Per level the nodes and their children; nodes with one final bucket stay as they are."""
    levels, nodes = [], [(0, k)]
    while any(t > 1 for _, t in nodes):
        split = [(n, shares_of(n, arity or k)) for n in nodes]
        levels.append(split)
        nodes = [c for _, children in split for c in children]
    return levels


def _frame(spark, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _open_level(state: DataFrame, split: list[tuple[Node, list[Node]]], spec: PartitionSpec, level: int) -> DataFrame:
    """(vid, parent) to (vid, parent, bucket): children by coin, or by rank, in proportion to their final buckets."""
    spark = state.sparkSession
    rows = []
    for (first, t), children in split:
        at = 0
        for c, size in children:
            rows.append((first, t, c, at, at + size))
            at += size
    plan = _frame(spark, rows, "parent int, t int, child int, lo int, hi int")
    plan = small(plan, len(rows))
    if spec.init == "ranked":
        from pyspark.sql import Window

        rank = F.row_number().over(Window.partitionBy("parent").orderBy(coin("vid", spec.seed, level), "vid")) - 1
        drawn = state.withColumn("r", rank)
        slot = F.col("r") % F.col("t")
    else:
        drawn = state.withColumn("r", coin("vid", spec.seed, level))
        slot = F.shiftright(F.col("r") * F.col("t"), 32)
    joined = drawn.join(plan, "parent").where((slot >= F.col("lo")) & (slot < F.col("hi")))
    return joined.select("vid", "parent", F.col("child").alias("bucket"))


def _caps(split: list[tuple[Node, list[Node]]], sizes: dict[int, int], n: int, k: int, eps: float, eps_level: float) -> list[tuple[int, int, int]]:
    """(parent, bucket, cap): the level's allowance, but no more than what its final buckets may hold, and enough for the parent."""
    last = max(math.floor((1 + eps) * n / k + 1e-9), -(-n // k))
    out = []
    for (first, t), children in split:
        for c, size in children:
            least = -(-sizes.get(first, 0) * size // t)
            out.append((first, c, min(size * last, max(math.floor((1 + eps_level) * n * size / k + 1e-9), least))))
    return out


def partition(edges: DataFrame, spec: PartitionSpec, vertices: DataFrame | None = None, start: DataFrame | None = None, base: DataFrame | None = None, watch: Callable[[dict], None] | None = None, weights: DataFrame | None = None) -> PartitionResult:
    """Partition the data vertices of edges, and those of vertices without edges as ballast.

    start: an assignment to refine (straight runs only). base: the assignment that spec.penalty holds on to. weights: (vid, w)
    with whole numbers that opposite crowds exchange evenly in place of their counts, with the plain exchange; vertices without a
    weight, or of weight 0, stay where the start put them. Weighted buckets are even in expectation; repair, which counts vertices, is left out.
    """
    if weights is not None:
        if spec.exchange != "plain" or spec.slack:
            raise ValueError("weights need the plain exchange")
        spec = spec.but(repair=False)
    spark = edges.sparkSession
    lent = getattr(edges, "_stored_path", None) is not None  # a table of the caller's is read as it is
    edges = edges if lent else stored(edges.select("qid", "vid"), "edges")
    packed = getattr(edges, "_packed", None)
    everyone = vertices_of(edges)
    if vertices is not None:
        everyone = everyone.union(vertices.select("vid")).distinct()
    state = stored(everyone.select("vid", F.lit(0).alias("parent")), "state")
    n = state.count()
    if packed is not None:
        queries, largest = packed.queries, packed.largest
    else:
        degrees = edges.groupBy("qid").agg(F.count("*").alias("d"))
        queries, largest = degrees.agg(F.count("qid"), F.coalesce(F.max("d"), F.lit(0))).first()
    if packed is not None and (start is not None or (base is not None and spec.penalty) or not packed.fits(spec)):
        packed = None
    if spec.k > max(n, 1):
        raise ValueError("more buckets than data vertices")
    levels = level_plan(spec.k, spec.arity)
    progress: list[dict] = []
    dead = 0
    work = edges
    for number, split in enumerate(levels, start=1):
        eps_level = refine.eps_at(number, len(levels), spec.eps)
        ts = sorted({size for _, children in split for _, size in children}, reverse=True) if spec.lookahead else [1]
        kernel = Kernel(spec.objective, spec.p)
        if start is not None:
            opened = start.select("vid", F.lit(0).alias("parent"), "bucket")
        else:
            opened = _open_level(state, split, spec, number)
        opened = stored(opened, "opened")
        forget(state)
        if spec.prune and number > 1 and packed is None:  # a packed graph leaves dead edges out of its counts
            gone, tagged = Observation(), refine.prune_dead(work, opened)
            alive = stored(tagged.observe(gone, F.count_if("alone").alias("dead")).where("not alone").select("qid", "vid"), "work")
            try:
                dead += gone.get["dead"]
            except (Py4JJavaError, KeyError):  # dropped from the plan, as where no edges are left
                dead += tagged.where("alone").count()
            if work is not edges:
                forget(work)
            work = alive
        state, log = _refine(work, opened, split, ts, kernel, spec, number, n, queries, dead, eps_level, base, watch, weights, largest <= refine.WHOLE_QUERY, packed)
        progress += log
        if spec.repair:
            held = {(r[0], r[1]): r[2] for r in state.groupBy("parent", "bucket").count().collect()}  # at most k rows
            sizes: dict[int, int] = {}
            for (parent, _), c in held.items():
                sizes[parent] = sizes.get(parent, 0) + c
            rows = _caps(split, sizes, n, spec.k, spec.eps, eps_level)
            if any(held.get((parent, bucket), 0) > cap for parent, bucket, cap in rows):
                caps = _frame(spark, rows, "parent int, bucket int, cap long")
                spread = _with_t(refine.spread_counts(work, state, refine.neighbor_counts(work, state)), split, ts)
                gains = refine.best_targets(spread, kernel, True, ts=ts).select("vid", "gain_fx")
                fixed = stored(refine.repair_to_cap(state, gains, caps, spec.seed), "repaired")
                forget(state)
                state = fixed
        if number < len(levels):
            nxt = state.select("vid", F.col("bucket").alias("parent"))
            nxt._stored_path = getattr(state, "_stored_path", None)
            state = nxt
    if work is not edges:
        forget(work)
    if not lent:
        forget(edges)
    out = state.select("vid", F.col("bucket").cast("int").alias("bucket"))
    out._stored_path = getattr(state, "_stored_path", None)
    return PartitionResult(out, progress, spec)


def _totals(p: float) -> tuple:
    return (F.count("*").alias("f"), F.sum(pfanout_term(F.col("cnt"), p)).alias("pf"), F.sum(F.col("cnt") * F.col("cnt")).alias("sq"))


def _pair_totals(p: float) -> tuple:
    """The same from pair_counts: the row that stands for its query and parent speaks for both children."""
    both = lambda x: F.coalesce(F.sum(F.when(F.col("one"), x(F.col("own")) + x(F.col("other")))), F.lit(0))
    return (both(lambda c: (c > 0).cast("long")).alias("f"), both(lambda c: pfanout_term(c, p)).alias("pf"), both(lambda c: c * c).alias("sq"))


def _sides(spark, split: list[tuple[Node, list[Node]]], ts: list[int]) -> tuple[DataFrame, DataFrame, int]:
    """(bucket, upper[, t, u]) and (parent, upper, src, dst) of a level whose parents have two children or one, and a bound on their rows. t, u: final buckets below the bucket and the other child."""
    sides, names = [], []
    for (parent, _), children in split:
        for upper, (c, t) in enumerate(children):
            other, u = children[1 - upper] if len(children) == 2 else (None, t)
            sides.append((c, bool(upper), t, u))
            if other is not None:
                names.append((parent, bool(upper), c, other))
    frame = _frame(spark, sides, "bucket int, upper boolean, t int, u int")
    return (frame if len(ts) > 1 else frame.drop("t", "u")), _frame(spark, names, "parent int, upper boolean, src int, dst int"), len(sides)


def _observed(seen: Observation, shares: DataFrame, p: float) -> tuple[int, float, int]:
    """What the job has observed of the shares; counted anew where the optimiser had dropped that part of the plan, as it does if no proposal exists."""
    try:
        got = seen.get
        return tuple(got[x] or 0 for x in ("f", "pf", "sq"))
    except (Py4JJavaError, KeyError):
        return _totals_of(shares, p)


def _totals_of(shares: DataFrame, p: float) -> tuple[int, float, int]:
    return tuple(v or 0 for v in shares.agg(*_totals(p)).first())


def _with_t(spread: DataFrame, split, ts: list[int]) -> DataFrame:
    """Final buckets below each bucket, where the look-ahead differs between buckets."""
    if len(ts) == 1:
        return spread
    rows = [(c, size) for _, children in split for c, size in children]
    return spread.join(small(_frame(spread.sparkSession, rows, "bucket int, t int"), len(rows)), "bucket")


class _Kept:
    """Shares and parts of the present state as tables, from which those of the next state follow by differences."""

    def __init__(self, shares: DataFrame, parts: DataFrame):
        self.shares, self.parts = shares, parts

    def moved(self, edges, state, moves, count, kernel, spread_with, ts) -> tuple[_Kept, int]:
        """After so many moves: only the moved vertices' edges and the members of the queries they change are read. The number of changed counts comes along."""
        changed = stored(refine.changed_counts(self.shares, edges, moves, count), "changed")
        rows = changed.count()
        shares = stored(refine.updated_counts(self.shares, changed, rows), "shares")
        parts = stored(refine.updated_parts(self.parts, edges, state, moves, changed, shares, kernel, spread_with, ts, count), "parts")
        forget(changed)
        self.drop()
        return _Kept(shares, parts), rows

    def drop(self) -> None:
        forget(self.shares, self.parts)


def _refine(edges, state, split, ts, kernel, spec, level, n, queries, dead, eps_level, base, watch, weights=None, whole=False, packed=None):
    """Iterations of one level. Shares and gains are counted anew while many vertices move; from a turn that moves a share of spec.reuse or less they are kept and updated.

    whole: the members of any query may meet in one task, so levels of two children count both in one shuffle.
    packed: the graph's packed form, on which each turn counts anew.
    """
    spark = state.sparkSession
    log: list[dict] = []
    best, best_value, damp, before = None, math.inf, spec.damp, None
    p = {"fanout": 1.0, "clique": spec.p}.get(spec.objective, spec.p)
    siblings = _frame(spark, [(f, [c for c, _ in children]) for (f, _), children in split], "parent int, children array<int>") if spec.nonpositive else None
    caps = None
    if spec.exchange == "histogram" and spec.slack:  # parents keep their sizes while their children trade
        held = {r[0]: r[1] for r in state.groupBy("parent").count().collect()}
        caps = _frame(spark, _caps(split, held, n, spec.k, spec.eps, eps_level), "parent int, bucket int, cap long")
    pairs = sum(len(c) ** 2 for _, c in split) * (128 if spec.exchange == "histogram" else 1)
    spread_with = lambda rows: _with_t(rows, split, ts)
    form, alone = (form_of(split, kernel, spec.lookahead), spec.prune and level > 1) if packed else (None, False)
    paired = packed is None and whole and not (base is not None and spec.penalty) and all(len(c) <= 2 for _, c in split)
    sides, names, sided = _sides(spark, split, ts) if paired else (None, None, 0)
    kept: _Kept | None = None
    few, counted = False, None
    for turn in range(1, spec.rounds + 2):
        seen = Observation()
        plain = kept.shares if kept else refine.neighbor_counts(edges, state)
        halves, shares, lent, known = None, plain, None, None
        given = spec.nonpositive and spec.exchange != "plain"
        if packed and turn > spec.rounds:
            known = packed.totals(state, form, p, alone)
        elif packed:
            lent, known = packed.proposals(state, form, p, alone, given)
        elif paired and not kept and (turn > spec.rounds or not few):
            halves = (refine.pair_shares if turn > spec.rounds else refine.pair_counts)(edges, state, sides, sided).observe(seen, *_pair_totals(p))
        elif not kept:
            shares = plain.observe(seen, *_totals(p))
        moves_made = None
        if turn > spec.rounds:  # the last state's objective only
            if not kept and not packed:
                (shares if halves is None else halves).write.format("noop").mode("overwrite").save()
            moved_state, moved = None, 0
        else:
            if lent is not None:
                proposals = lent
            elif halves is not None:
                proposals = refine.best_of_pairs(halves, kernel, names, sided, given, ts)
            else:
                if kept:
                    parts = kept.parts
                else:
                    shares = stored(shares, "shares") if few else shares
                    parts = refine.gain_parts(spread_with(refine.spread_counts(edges, state, shares)), kernel, ts)
                    if few:
                        kept = _Kept(shares, stored(parts, "parts"))
                        parts = kept.parts
                proposals = refine.best_of_parts(parts, given, siblings, base=base, penalty_fx=int(spec.penalty * kernel.scale), rows=len(split))
            if weights is not None:
                proposals = proposals.join(weights.select("vid", F.col("w").cast("long").alias("w")), "vid").where("w > 0")
            if spec.exchange == "ranked":
                moves = refine.exchange_ranked(proposals, spec.nonpositive).select("vid", "dst")
                if damp < 1:
                    moves = moves.where(coin("vid", spec.seed, level, turn, mode=spec.coins) < int(damp * FULL))
            else:
                if spec.exchange == "plain":
                    exchange = refine.swap_probability(refine.exchange_matrix(proposals, weight="w" if weights is not None else None))
                else:
                    exchange = refine.histogram_match(refine.exchange_matrix(proposals, by_bin=True), spec.nonpositive)
                    if caps is not None:
                        sizes = state.groupBy("parent", "bucket").agg(F.count("*").alias("size"))
                        room = caps.join(sizes, ["parent", "bucket"], "left").select("bucket", "cap", F.coalesce("size", F.lit(0)).alias("size"))
                        exchange = refine.slack_moves(exchange, room)
                moves = refine.accepted(proposals, exchange, spec.seed, level, turn, damp, spec.coins, rows=min(pairs, n))
            new = refine.apply_moves(state.select("vid", "parent", "bucket", F.col("bucket").alias("was")), moves)
            count = Observation()
            table = stored(new.observe(count, F.count_if("moved").alias("m")).drop("moved"), "state")
            moved = count.get["m"]
            forget(lent)
            moves_made = table.where("bucket <> was").select("vid", "parent", F.col("was").alias("src"), F.col("bucket").alias("dst"))
            moved_state = table.select("vid", "parent", "bucket")
            moved_state._stored_path = table._stored_path
        if known:
            *totals, dead = known
        f, pf, sq = totals if known else _totals_of(plain, p) if plain is (kept and kept.shares) else _observed(seen, plain, p)
        value = {"fanout": f, "clique": -sq, "pfanout": pf}[spec.objective]
        rows_of = lambda: int(f if counted is None else counted)
        if log:
            log[-1].update(fanout=(f + dead) / max(queries, 1), pfanout=(pf + dead * p) / max(queries, 1), shuffle_rows=rows_of())
        if watch and log:
            watch(log[-1])
        if spec.keep_best and value < best_value:
            if best is not None and best is not state:
                forget(best)
            best, best_value = state, value
        elif state is not best:
            if spec.keep_best:
                forget(state)
        if moved_state is None:
            break
        if before is not None and value >= before and log and log[-1]["moved_frac"] > 0.5:
            damp = min(damp, 0.5)  # buckets would only trade their names
        before = value
        frac = moved / max(n, 1)
        log.append({"level": level, "iter": turn, "moved": int(moved), "moved_frac": float(frac), "fanout": float("nan"), "pfanout": float("nan"), "shuffle_rows": 0})
        if moved == 0:
            forget(moved_state)
            log[-1].update(fanout=(f + dead) / max(queries, 1), pfanout=(pf + dead * p) / max(queries, 1), shuffle_rows=0)
            break
        few, counted = frac <= spec.reuse and packed is None, None
        if kept and few:
            kept, counted = kept.moved(edges, moved_state, moves_made, int(moved), kernel, spread_with, ts)
        elif kept:
            kept.drop()
            kept = None
        state = moved_state
        if frac <= spec.tol:
            last = kept.shares if kept else refine.neighbor_counts(edges, state)
            f, pf, sq = packed.totals(state, form, p, alone)[:3] if packed else _totals_of(last, p)
            log[-1].update(fanout=(f + dead) / max(queries, 1), pfanout=(pf + dead * p) / max(queries, 1), shuffle_rows=rows_of())
            if spec.keep_best and {"fanout": f, "clique": -sq, "pfanout": pf}[spec.objective] >= best_value:
                forget(state)
            else:
                best = state
            break
    if kept:
        kept.drop()
    return (best if spec.keep_best and best is not None else state), log


def partition_direct(edges: DataFrame, spec: PartitionSpec, **more) -> PartitionResult:
    """Straight into k buckets."""
    return partition(edges, spec.but(arity=None), **more)


def partition_bisect(edges: DataFrame, spec: PartitionSpec, **more) -> PartitionResult:
    """By halves."""
    return partition(edges, spec.but(arity=2), **more)


def partition_recursive(edges: DataFrame, spec: PartitionSpec, arity: int, **more) -> PartitionResult:
    return partition(edges, spec.but(arity=arity), **more)


def repartition(edges: DataFrame, former: DataFrame, spec: PartitionSpec, damp: float = 1.0, penalty: float = 0.0) -> PartitionResult:
    """Refine a former assignment: moves are damped, and leaving the former bucket costs penalty. moved_from_base() says how much has moved."""
    everyone = edges.select("vid").union(former.select("vid")).distinct()
    start = refine.init_from(former, everyone, spec.k, spec.eps, spec.seed)
    if damp == 0 or penalty == math.inf:
        return PartitionResult(stored(start, "kept"), [], spec)
    return partition(edges, spec.but(arity=None, damp=damp, penalty=penalty), vertices=everyone, start=start, base=former if penalty else None)


def moved_from_base(assign: DataFrame, former: DataFrame) -> DataFrame:
    """One row: vertices that both know, how many of them changed their bucket, and their share."""
    both = assign.join(former.select("vid", F.col("bucket").alias("was")), "vid")
    moved = F.count_if(F.col("bucket") != F.col("was"))
    return both.agg(F.count("*").alias("known"), moved.alias("moved"), F.round(moved / F.greatest(F.count("*"), F.lit(1)), 6).alias("share"))


def partition_weighted(edges: DataFrame, weights: DataFrame, spec: PartitionSpec) -> PartitionResult:
    """Vertices of different weight (vid, w): over-split, then merged by weight. partition(weights=...) exchanges weight evenly instead."""
    from .multidim import partition_multidim

    return partition_multidim(edges, weights.select("vid", F.array(F.col("w").cast("double")).alias("dims")), spec, c=4)


def best_of(edges: DataFrame, specs: list[PartitionSpec], vertices: DataFrame | None = None) -> PartitionResult:
    """Run all, keep the one with the lowest true fanout."""
    from ..operators.measures import avg_fanout

    best, lowest = None, math.inf
    edges = stored(edges.select("qid", "vid"), "edges")
    for spec in specs:
        got = partition(edges, spec, vertices=vertices)
        value = avg_fanout(edges, got.assign).first()["fanout"]
        if value < lowest:
            if best is not None:
                forget(best.assign)
            best, lowest = got, value
        else:
            forget(got.assign)
    forget(edges)
    return best
