"""One iteration of refinement as relational steps.

State is (vid, parent, bucket): a vertex may only move among the buckets of its parent. Straight k-way
refinement has one parent; recursion has one per bucket of the level above, and all of them are refined
by the same plan.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.coin import FULL, coin
from ..functions.kernel import Kernel, gain_bin
from ..session import BROADCAST_ROWS, small

WIDE = "decimal(38,0)"

#: Members of the largest query up to which all members of a query may meet in one task.
WHOLE_QUERY = 100_000


def init_random(vertices: DataFrame, k: int, seed: int = 42) -> DataFrame:
    """Bucket by hash coin; no shuffle."""
    return vertices.select("vid", (coin("vid", seed) % k).cast("int").alias("bucket"))


def init_ranked(vertices: DataFrame, k: int, seed: int = 42, parent: str | None = None) -> DataFrame:
    """Buckets of equal size, up to one vertex, within each parent. Sorts each parent's vertices: for few vertices per bucket."""
    keys = [parent] if parent else []
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy(coin("vid", seed), "vid"))
    return vertices.select("vid", *keys, ((rank - 1) % k).cast("int").alias("bucket"))


def init_from(base: DataFrame, vertices: DataFrame, k: int, eps: float, seed: int = 42) -> DataFrame:
    """A former assignment; new vertices go by coin to buckets with room, weighted by their room."""
    n = vertices.count()
    cap = max(int((1 + eps) * n / k), -(-n // k))
    known = vertices.join(base, "vid", "left")
    sizes = known.where("bucket is not null").groupBy("bucket").agg(F.count("*").alias("size"))
    every = base.sparkSession.range(k).select(F.col("id").cast("int").alias("b"))
    room = every.join(sizes, every.b == sizes.bucket, "left").select("b", F.greatest(F.lit(cap) - F.coalesce("size", F.lit(0)), F.lit(0)).alias("room"))
    run = Window.partitionBy(F.lit(0)).orderBy("b")  # k rows
    slots = room.withColumn("hi", F.sum("room").over(run)).withColumn("lo", F.col("hi") - F.col("room"))
    total = max(1, slots.agg(F.max("hi")).first()[0] or 1)
    new = known.where("bucket is null").select("vid", (coin("vid", seed) % total).alias("slot"))
    placed = new.join(F.broadcast(slots), (F.col("slot") >= F.col("lo")) & (F.col("slot") < F.col("hi"))).select("vid", F.col("b").alias("bucket"))
    return known.where("bucket is not null").select("vid", "bucket").unionByName(placed)


def neighbor_counts(edges: DataFrame, state: DataFrame) -> DataFrame:
    """First step: (qid, parent, bucket, cnt), nonzero counts only."""
    return edges.join(state, "vid").groupBy("qid", "parent", "bucket").agg(F.count("*").alias("cnt"))


def spread_counts(edges: DataFrame, state: DataFrame, shares: DataFrame) -> DataFrame:
    """Second step: each member of a query learns its query's counts within its own parent: (vid, src, bucket, cnt)."""
    members = edges.join(state.select("vid", "parent", F.col("bucket").alias("src")), "vid")
    return members.join(shares, ["qid", "parent"]).select("vid", "parent", "src", "bucket", "cnt")


def gain_parts(spread: DataFrame, kernel: Kernel, ts: list[int] | None = None, t_col: str = "t") -> DataFrame:
    """(vid, parent, src, bucket, part, uses): what the vertex's queries that use a bucket say of it, and how many they are.

    Only nonzero counts are summed: a bucket that a query does not use is worth the kernel's idle term, so
    the sum over all queries is the idle term times the degree less what the used ones save. The gain of a move is
    the own bucket's part and the target's. Parts are sums over queries, so signed differences update them.
    """
    own = F.col("bucket") == F.col("src")
    part = F.when(own, _term(kernel, "cnt", "leave", ts, t_col) - F.lit(kernel.idle)).otherwise(F.lit(kernel.idle) - _term(kernel, "cnt", "arrive", ts, t_col))
    return spread.groupBy("vid", "parent", "src", "bucket").agg(F.sum(part).alias("part"), F.count("*").alias("uses"))


def _term(kernel: Kernel, cnt: str, kind: str, ts: list[int] | None, t_col: str = "t"):
    ts = ts or [1]
    return kernel.by_target(F.col(cnt), F.col(t_col) if len(ts) > 1 else F.lit(ts[0]), ts, kind)


def move_gains(spread: DataFrame, kernel: Kernel, ts: list[int] | None = None, t_col: str = "t") -> DataFrame:
    """(vid, parent, src, dst, gain_fx) for each bucket that a query of the vertex uses; for others the gain is not positive."""
    own = F.col("bucket") == F.col("src")
    line = F.collect_list(F.when(~own, F.struct(F.col("bucket").alias("dst"), "part")))  # as many as buckets are used
    per = gain_parts(spread, kernel, ts, t_col).groupBy("vid", "parent", "src").agg(F.max(F.when(own, F.col("part"))).alias("own"), line.alias("line"))
    return per.select("vid", "parent", "src", "own", F.explode("line").alias("x")).select("vid", "parent", "src", "x.dst", (F.col("own") + F.col("x.part")).alias("gain_fx"))


def best_targets(spread: DataFrame, kernel: Kernel, nonpositive: bool = False, siblings: DataFrame | None = None, ts: list[int] | None = None, t_col: str = "t", base: DataFrame | None = None, penalty_fx: int = 0) -> DataFrame:
    """One proposal per vertex: (vid, parent, src, dst, gain_fx, gbin), the best bucket, ties to the lowest."""
    return best_of_parts(gain_parts(spread, kernel, ts, t_col), nonpositive, siblings, base, penalty_fx)


def best_of_parts(parts: DataFrame, nonpositive: bool = False, siblings: DataFrame | None = None, base: DataFrame | None = None, penalty_fx: int = 0, rows: int | None = None) -> DataFrame:
    """The same from stored parts. The own part is common to all targets, so one aggregate per vertex finds the best.

    siblings: (parent, children) with the array of all candidates of a parent, needed only if nonpositive
    targets that no query uses count too: of those the lowest is the best. rows: how many parents there are, if known. base and
    penalty_fx: leaving the base bucket costs, returning to it pays.
    """
    keys, held = ["vid", "parent", "src"], base is not None and penalty_fx
    own, home = F.col("bucket") == F.col("src"), F.col("home")
    bonus = lambda at: F.when(at == home, F.lit(penalty_fx)).otherwise(F.lit(0)) if held else F.lit(0)
    option = lambda part, at: F.struct((part + bonus(at)).cast("long").alias("part"), (-at).cast("int").alias("back"))
    if held:
        parts = parts.join(base.select("vid", F.col("bucket").alias("home")), "vid", "left")
        keys.append("home")
    what = [F.max(F.when(own, F.col("part"))).alias("own"), F.max(F.when(~own, option(F.col("part"), F.col("bucket")))).alias("top")]
    every = nonpositive and siblings is not None
    per = parts.groupBy(*keys).agg(*what, *([F.collect_set("bucket").alias("used")] if every else []))
    if every:
        listed = siblings.select("parent", "children")
        per = per.join(small(listed, rows) if rows is not None else listed, "parent").withColumn("free", F.array_min(F.array_except("children", "used")))
        more = [F.when(F.col("free").isNotNull(), option(F.lit(0), F.col("free")))]
        if held:
            more.append(F.when(F.array_contains("children", home) & ~F.array_contains("used", home), option(F.lit(0), home)))
        per = per.withColumn("top", F.array_max(F.array("top", *more)))
    lost = F.when(F.col("src") == home, F.lit(penalty_fx)).otherwise(F.lit(0)) if held else F.lit(0)
    out = per.where("top is not null").select("vid", "parent", "src", (-F.col("top.back")).alias("dst"), (F.col("own") + F.col("top.part") - lost).alias("gain_fx"))
    out = out if nonpositive else out.where("gain_fx > 0")
    return out.withColumn("gbin", gain_bin(F.col("gain_fx")))


def _sided(edges: DataFrame, state: DataFrame, sides: DataFrame, rows: int) -> DataFrame:
    """Edges with their vertex's parent and side. sides: (bucket, upper[, t, u]), so many rows; upper tells the two children of a parent apart."""
    return edges.join(state.select("vid", "parent", "bucket"), "vid").join(small(sides, rows), "bucket").drop("bucket")


def pair_shares(edges: DataFrame, state: DataFrame, sides: DataFrame, rows: int) -> DataFrame:
    """First step where no parent has more than two children: (own, other, one), the members in both children, by query and parent."""
    per = _sided(edges, state, sides, rows).groupBy("qid", "parent").agg(F.count("*").alias("d"), F.count_if("upper").alias("own"))
    return per.select("own", (F.col("d") - F.col("own")).alias("other"), F.lit(True).alias("one"))


def pair_counts(edges: DataFrame, state: DataFrame, sides: DataFrame, rows: int) -> DataFrame:
    """First and second step in one where no parent has more than two children: a row (vid, parent, upper, own, other, one[, t, u]) for each edge.

    own and other are its query's members in the vertex's bucket and in the other child: one shuffle of the edges brings both, and
    one marks a single row of each query and parent. All members of a query and a parent meet in one task: for graphs
    whose largest query is known to be small (WHOLE_QUERY).
    """
    line = Window.partitionBy("qid", "parent").orderBy("upper")
    whole = line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    found = _sided(edges, state, sides, rows).withColumns({"d": F.count("*").over(whole), "up": F.count_if("upper").over(whole), "one": F.row_number().over(line) == 1}).drop("qid")
    own = F.when(F.col("upper"), F.col("up")).otherwise(F.col("d") - F.col("up"))
    return found.withColumn("own", own).withColumn("other", F.col("d") - F.col("own")).drop("d", "up")


def best_of_pairs(pairs: DataFrame, kernel: Kernel, names: DataFrame, rows: int, nonpositive: bool = False, ts: list[int] | None = None) -> DataFrame:
    """What best_of_parts gives, from pair_counts: the other child is the only target, so sums are enough.

    names: (parent, upper, src, dst), so many rows, without parents of one child. nonpositive: the target counts even if no query uses it.
    """
    own, used = _term(kernel, "own", "leave", ts) - F.lit(kernel.idle), F.lit(kernel.idle) - _term(kernel, "other", "arrive", ts, "u")
    part = F.sum(F.when(F.col("other") > 0, used))  # null where no query uses it
    per = pairs.groupBy("vid", "parent", "upper").agg(F.sum(own).alias("own"), part.alias("part")).join(small(names, rows), ["parent", "upper"])
    gain = F.col("own") + (F.coalesce("part", F.lit(0).cast("long")) if nonpositive else F.col("part"))
    out = per.select("vid", "parent", "src", "dst", gain.alias("gain_fx"))
    out = out if nonpositive else out.where("gain_fx > 0")
    return out.withColumn("gbin", gain_bin(F.col("gain_fx")))


def gain_state(edges: DataFrame, shares: DataFrame, p: float) -> DataFrame:
    """Side-free sums (vid, bucket, h_fx) of (1-p)^cnt over the queries of a vertex that use a bucket, less one each: additive, so deltas update them."""
    kernel = Kernel("pfanout", p)
    rows = edges.join(shares.select("qid", "bucket", "cnt"), "qid")
    return rows.groupBy("vid", "bucket").agg(F.sum(kernel.arrive(F.col("cnt")) - F.lit(kernel.idle)).alias("h_fx"))


def gain_from_state(state: DataFrame, assign: DataFrame, degrees: DataFrame, p: float) -> DataFrame:
    """(vid, src, dst, gain) with gain = p (H_own / (1-p) - H_other); exact where (1-p) divides the fixed-point terms, as for p = 0.5."""
    scale = float(1 << 40)
    full = state.join(degrees.select("vid", "deg"), "vid").select("vid", "bucket", (F.col("h_fx") / scale + F.col("deg")).alias("h"), "deg")
    own = full.join(assign.select("vid", F.col("bucket").alias("src")), "vid")
    mine = own.where("bucket = src").select("vid", F.col("h").alias("ho"))
    return own.where("bucket <> src").join(mine, "vid").select("vid", "src", F.col("bucket").alias("dst"), F.round(F.lit(p) * (F.col("ho") / (1 - p) - F.col("h")), 9).alias("gain"))


def exchange_matrix(proposals: DataFrame, by_bin: bool = False, weight: str | None = None) -> DataFrame:
    """Third step: (src, dst[, gbin], candidates, gain_sum); sparse. weight: a column of whole numbers that count in place of the vertices."""
    keys = ["src", "dst", "gbin"] if by_bin else ["src", "dst"]
    count = F.sum(weight) if weight else F.count("*")
    return proposals.groupBy(*keys).agg(count.alias("candidates"), F.sum(F.col("gain_fx").cast(WIDE)).cast(WIDE).alias("gain_sum"))


def swap_probability(exchange: DataFrame) -> DataFrame:
    """(src, dst, admitted, threshold): of two opposite crowds as many move as the smaller has, in expectation."""
    back = exchange.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("candidates").alias("opposite"))
    both = exchange.join(back, ["src", "dst"], "left").withColumn("admitted", F.least("candidates", F.coalesce("opposite", F.lit(0).cast("long"))))
    return both.select("src", "dst", "candidates", "admitted", F.expr(f"cast((cast(admitted as {WIDE}) * {FULL}) div candidates as bigint)").alias("threshold"))


def bin_intervals(exchange: DataFrame) -> DataFrame:
    """Place of each bin's candidates in its direction's queue, best bins first: [lo, hi)."""
    queue = Window.partitionBy("src", "dst").orderBy(F.desc("gbin"))
    return exchange.withColumn("hi", F.sum("candidates").over(queue)).withColumn("lo", F.col("hi") - F.col("candidates"))


def histogram_match(exchange: DataFrame, nonpositive: bool = False) -> DataFrame:
    """(src, dst, gbin, candidates, gain_sum, admitted, threshold): opposite queues are paired from the top.

    Where the intervals of two bins overlap, that many of each are paired. With nonpositive gains a pair
    of bins counts only if their mean gains add up to more than zero; sums fall along the queue, so what is
    admitted is its head.
    """
    here = bin_intervals(exchange)
    there = here.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("lo").alias("lo2"), F.col("hi").alias("hi2"), F.col("candidates").alias("c2"), F.col("gain_sum").alias("g2"))
    meet = here.join(there, ["src", "dst"]).where("lo < hi2 and lo2 < hi")
    if nonpositive:
        meet = meet.where(F.col("gain_sum").cast("decimal(28,0)") * F.col("c2").cast("decimal(10,0)") + F.col("g2").cast("decimal(28,0)") * F.col("candidates").cast("decimal(10,0)") > 0)
    part = meet.groupBy("src", "dst", "gbin").agg(F.sum(F.least("hi", "hi2") - F.greatest("lo", "lo2")).alias("a"))
    out = here.join(part, ["src", "dst", "gbin"], "left").withColumn("admitted", F.coalesce("a", F.lit(0).cast("long")))
    return _with_threshold(out)


def _with_threshold(ex: DataFrame) -> DataFrame:
    return ex.select("src", "dst", "gbin", "candidates", "gain_sum", "admitted", F.expr(f"cast((cast(admitted as {WIDE}) * {FULL}) div candidates as bigint)").alias("threshold"))


def slack_moves(exchange: DataFrame, sizes: DataFrame) -> DataFrame:
    """Unpaired candidates with positive gains fill the room of their target, best bins first, sources in order.

    exchange as histogram_match gives it; sizes: (bucket, size, cap).
    """
    room = sizes.select(F.col("bucket").alias("dst"), F.greatest(F.col("cap") - F.col("size"), F.lit(0)).alias("room"))
    spare = F.when(F.col("gbin") > 0, F.col("candidates") - F.col("admitted")).otherwise(F.lit(0))
    queue = Window.partitionBy("dst").orderBy(F.desc("gbin"), "src").rowsBetween(Window.unboundedPreceding, -1)
    x = exchange.join(room, "dst", "left").withColumn("spare", spare).withColumn("before", F.coalesce(F.sum("spare").over(queue), F.lit(0)))
    more = F.greatest(F.least("spare", F.coalesce("room", F.lit(0)) - F.col("before")), F.lit(0))
    return _with_threshold(x.withColumn("admitted", (F.col("admitted") + more).cast("long")))


def exchange_ranked(proposals: DataFrame, positive_sum: bool = False) -> DataFrame:
    """Exact pairing: the i-th best of one direction moves with the i-th best of the other. (vid, src, dst).

    positive_sum: pairs count while their gains add up to more than zero. Sorts each ordered pair's candidates: for small data.
    """
    queue = Window.partitionBy("src", "dst").orderBy(F.desc("gain_fx"), "vid")
    ranked = proposals.withColumn("rn", F.row_number().over(queue))
    back = ranked.select(F.col("src").alias("dst"), F.col("dst").alias("src"), "rn", F.col("gain_fx").alias("g2"))
    both = ranked.join(back, ["src", "dst", "rn"])
    if positive_sum:
        both = both.where("gain_fx + g2 > 0")
    return both.select("vid", "src", "dst")


def eps_at(level: int, levels: int, eps: float) -> float:
    """Allowance at a level of the recursion (from 1): all of it only at the last."""
    return eps * level / levels


def accepted(proposals: DataFrame, exchange: DataFrame, seed: int, level: int, iteration: int, damp: float = 1.0, mode: str = "portable", rows: int | None = None) -> DataFrame:
    """Fourth step: proposals whose coin falls below their threshold: (vid, dst).

    rows: known number of rows of exchange; it is broadcast up to the limit and joined by shuffle beyond it.
    """
    keys = ["src", "dst"] + (["gbin"] if "gbin" in exchange.columns else [])
    ex = exchange.select(*keys, "threshold")
    if rows is not None and rows <= BROADCAST_ROWS:
        ex = F.broadcast(ex)
    limit = F.col("threshold") if damp == 1 else F.floor(F.col("threshold") * F.lit(damp)).cast("long")
    return proposals.join(ex, keys).where(coin("vid", seed, level, iteration, mode=mode) < limit).select("vid", "dst")


def apply_moves(state: DataFrame, moves: DataFrame) -> DataFrame:
    """State with moved vertices in their targets."""
    cols = [c for c in state.columns if c != "bucket"]
    return state.join(moves, "vid", "left").select(*cols, F.coalesce("dst", "bucket").cast("int").alias("bucket"), F.col("dst").isNotNull().alias("moved"))


def delta_counts(shares: DataFrame, edges: DataFrame, moves: DataFrame) -> DataFrame:
    """Shares after moves (vid, src, dst) from the old ones and the moved vertices' edges only."""
    touched = edges.join(moves, "vid")
    less, more = touched.select("qid", F.col("src").alias("bucket"), F.lit(-1).cast("long").alias("cnt")), touched.select("qid", F.col("dst").alias("bucket"), F.lit(1).cast("long").alias("cnt"))
    return shares.select("qid", "bucket", "cnt").union(less).union(more).groupBy("qid", "bucket").agg(F.sum("cnt").alias("cnt")).where("cnt <> 0")


def dirty_vertices(edges: DataFrame, moves: DataFrame) -> DataFrame:
    """Vertices whose gains change: members of the queries of moved ones."""
    queries = edges.join(moves.select("vid"), "vid", "left_semi").select("qid").distinct()
    return edges.join(queries, "qid", "left_semi").select("vid").distinct()


def changed_counts(shares: DataFrame, edges: DataFrame, moves: DataFrame, rows: int | None = None) -> DataFrame:
    """(qid, parent, bucket, old, new) of the counts that moves (vid, parent, src, dst) change: only moved vertices' edges are read. rows: how many vertices moved, if known."""
    touched = edges.join(small(moves, rows) if rows is not None else moves, "vid")
    signed = touched.select("qid", "parent", F.explode(F.array(F.struct(F.col("src").alias("bucket"), F.lit(-1).alias("d")), F.struct(F.col("dst").alias("bucket"), F.lit(1).alias("d")))).alias("x"))
    delta = signed.groupBy("qid", "parent", F.col("x.bucket").alias("bucket")).agg(F.sum("x.d").alias("d")).where("d <> 0")
    old = F.coalesce("cnt", F.lit(0).cast("long"))
    return delta.join(shares, ["qid", "parent", "bucket"], "left").select("qid", "parent", "bucket", old.alias("old"), (old + F.col("d")).alias("new"))


def updated_counts(shares: DataFrame, changed: DataFrame, rows: int | None = None) -> DataFrame:
    """Shares after the changes; rows: how many of them there are, if known."""
    keys = ["qid", "parent", "bucket"]
    kept = shares.join(small(changed.select(keys), rows) if rows is not None else changed.select(keys), keys, "left_anti")
    return kept.select(*keys, "cnt").union(changed.where("new > 0").select(*keys, F.col("new").alias("cnt")))


def updated_parts(parts: DataFrame, edges: DataFrame, state: DataFrame, moves: DataFrame, changed: DataFrame, shares: DataFrame, kernel: Kernel, spread_with, ts: list[int] | None = None, moved: int | None = None) -> DataFrame:
    """Parts after moves: differences for members of changed queries, a new count for the moved vertices themselves.

    state and shares are those after the moves; spread_with adds the look-ahead's column where it differs between buckets.
    """
    movers = moves.select("vid")
    movers = small(movers, moved) if moved is not None else movers
    members = edges.join(changed, "qid").join(state.select("vid", F.col("parent").alias("p"), F.col("bucket").alias("src")), "vid").where("p = parent").drop("p").join(movers, "vid", "left_anti")
    own = F.col("bucket") == F.col("src")
    change = F.when(own, _term(kernel, "new", "leave", ts) - _term(kernel, "old", "leave", ts)).otherwise(_term(kernel, "old", "arrive", ts) - _term(kernel, "new", "arrive", ts))
    uses = (F.col("new") > 0).cast("long") - (F.col("old") > 0).cast("long")
    differences = spread_with(members).select("vid", "parent", "src", "bucket", change.alias("part"), uses.alias("uses"))
    keys = ["vid", "parent", "src", "bucket"]
    kept = parts.join(movers, "vid", "left_anti").select(*keys, "part", "uses")
    stayed = kept.union(differences).groupBy(*keys).agg(F.sum("part").alias("part"), F.sum("uses").alias("uses")).where("uses > 0")
    theirs = edges.join(movers, "vid", "left_semi")
    fresh = gain_parts(spread_with(spread_counts(theirs, state, shares)), kernel, ts)
    return stayed.select(*keys, "part", "uses").union(fresh.select(*keys, "part", "uses"))


def prune_dead(edges: DataFrame, state: DataFrame) -> DataFrame:
    """(qid, vid, alone): alone where the query has one member in the parent; its terms are zero from here on."""
    tagged = edges.join(state.select("vid", "parent"), "vid")
    return tagged.withColumn("alone", F.count("*").over(Window.partitionBy("qid", "parent")) == 1).select("qid", "vid", "alone")


def numbered(rows: DataFrame, keys: list[str], name: str, parts: int = 256) -> DataFrame:
    """Rows of vertices numbered from 0 within their keys, in an order of no meaning: counts per part of a hash give the offsets, so no task sees all rows of a key."""
    dealt = rows.withColumn("_h", F.pmod(F.xxhash64("vid"), F.lit(parts)).cast("int"))
    counts = dealt.groupBy(*keys, "_h").agg(F.count("*").alias("_c"))
    before = F.sum("_c").over(Window.partitionBy(*keys).orderBy("_h").rowsBetween(Window.unboundedPreceding, -1))
    offsets = counts.select(*keys, "_h", F.coalesce(before, F.lit(0)).alias("_o"))
    place = F.row_number().over(Window.partitionBy(*keys, "_h").orderBy("vid")) - 1
    return dealt.withColumn("_r", place).join(offsets, [*keys, "_h"]).withColumn(name, F.col("_o") + F.col("_r")).drop("_h", "_r", "_o")


def _cut(counts: DataFrame, keys: list[str], order, need: str) -> DataFrame:
    """counts(keys, step, c, need) with what comes before each step and whether all of it is needed."""
    queue = Window.partitionBy(*keys).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    return counts.withColumn("before", F.coalesce(F.sum("c").over(queue), F.lit(0))).where(F.col("before") < F.col(need)).withColumn("all", F.col("before") + F.col("c") <= F.col(need))


def repair_to_cap(state: DataFrame, gains: DataFrame | None, caps: DataFrame, seed: int = 42) -> DataFrame:
    """Overfull buckets give up the vertices that lose least, by gain bins, which fill the room of their siblings.

    caps: (parent, bucket, cap) of all buckets. gains: optional (vid, gain_fx) of each vertex's best move. Whole bins
    go from the best on; of the bin that would be too many, whole slices of a coin, and of the last slice as many as are missing:
    only that slice, a thousandth of a bin, is sorted.
    """
    sizes = state.groupBy("parent", "bucket").agg(F.count("*").alias("size"))
    full = caps.join(sizes, ["parent", "bucket"], "left").select("parent", "bucket", "cap", F.coalesce("size", F.lit(0)).alias("size"))
    over = full.where("size > cap").select("parent", "bucket", (F.col("size") - F.col("cap")).alias("excess"))
    keys = ["parent", "bucket"]
    inside = state.join(over.select(keys), keys, "left_semi").select("vid", *keys)
    worst = F.lit(-999)
    binned = inside.join(gains, "vid", "left").withColumn("step", F.coalesce(gain_bin(F.col("gain_fx")), worst)) if gains is not None else inside.withColumn("step", worst)
    binned = binned.select("vid", *keys, "step", coin("vid", seed).alias("c1")).withColumn("slice", F.shiftright("c1", 22))
    bins = _cut(binned.groupBy(*keys, "step").agg(F.count("*").alias("c")).join(over, keys), keys, F.desc("step"), "excess")
    bins = bins.select(*keys, "step", "all", (F.col("excess") - F.col("before")).alias("missing"))
    chosen = binned.join(bins, [*keys, "step"])
    edge = chosen.where("not all").drop("all")
    slices = _cut(edge.groupBy(*keys, "slice", "missing").agg(F.count("*").alias("c")), keys, F.asc("slice"), "missing")
    slices = slices.select(*keys, "slice", "all", (F.col("missing") - F.col("before")).alias("few"))
    last = edge.join(slices, [*keys, "slice"])
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy("c1", "vid"))
    shed = chosen.where("all").select("vid", "parent").union(last.where("all").select("vid", "parent"))
    shed = shed.union(last.where("not all").withColumn("r", rank).where("r <= few").select("vid", "parent"))
    slot = numbered(shed, ["parent"], "slot")
    run = Window.partitionBy("parent").orderBy("bucket")  # at most k rows
    room = full.where("size < cap").withColumn("hi", F.sum(F.col("cap") - F.col("size")).over(run)).withColumn("lo", F.col("hi") - (F.col("cap") - F.col("size")))
    # a parent's rooms as one sorted list, so that a slot finds its own without a range join
    rooms = room.groupBy("parent").agg(F.array_sort(F.collect_list(F.struct("hi", F.col("bucket").alias("dst")))).alias("rooms"))
    found = slot.join(rooms, "parent").withColumn("dst", F.try_element_at(F.filter("rooms", lambda x: x["hi"] > F.col("slot")), F.lit(1))["dst"])
    return apply_moves(state, found.where("dst is not null").select("vid", "dst")).drop("moved")
