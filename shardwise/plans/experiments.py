"""The experiments: latency against fanout, quality, scaling, parameters, ablations. Results are tables."""

from __future__ import annotations

import concurrent.futures
import math
import time
import uuid
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.coin import FULL, coin
from ..model import RESULT, PartitionResult, PartitionSpec
from ..operators import baselines, measures, refine
from ..operators.packed import pack, vertices_of
from ..session import forget, stored
from .multilevel import multilevel
from .partition import partition, repartition

FANOUTS = (1, 2, 5, 10, 20, 35, 40)


def _in_parts(rows: DataFrame, value: str, parts: int = 256) -> DataFrame:
    """Rows with a column part that grows with value, from approximate quantiles: a running sum needs no task that sees all rows."""
    cuts = rows.agg(F.percentile_approx(value, [i / parts for i in range(1, parts)], 10_000).alias("_cuts"))
    return rows.crossJoin(F.broadcast(cuts)).withColumn("part", F.size(F.filter("_cuts", lambda x: x < F.col(value)))).drop("_cuts")


def _running(rows: DataFrame, order: list[str], weight) -> DataFrame:
    """rows(part, ...) with hi, the sum of weight up to and with each row in the order of part and order: sums of parts give the offsets."""
    sums = rows.groupBy("part").agg(F.sum(weight).alias("_s"))  # as many rows as parts
    before = F.sum("_s").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    offsets = sums.select("part", F.coalesce(before, F.lit(0)).alias("_o"))
    own = F.sum(weight).over(Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return rows.withColumn("_own", own).join(F.broadcast(offsets), "part").withColumn("hi", F.col("_o") + F.col("_own")).drop("_own", "_o", "part")


def latency_exact(latencies: DataFrame, fanouts: Iterable[int] = FANOUTS, percentiles: Iterable[float] = (0.5, 0.9, 0.95, 0.99)) -> DataFrame:
    """latencies(value) of single calls: exact mean and percentiles of the largest of f independent ones.

    Values are grouped with their counts, so the ranks come from a running sum over distinct values, part by part.
    """
    counts = latencies.where("value is not null").groupBy("value").agg(F.count("*").alias("c"))
    n = counts.agg(F.sum("c").alias("n"))
    ranked = _running(_in_parts(counts, "value"), ["value"], F.col("c")).withColumn("lo", F.col("hi") - F.col("c")).crossJoin(F.broadcast(n))
    each = ranked.withColumn("f", F.explode(F.array(*[F.lit(f) for f in fanouts])))
    power = lambda x: F.pow(F.col(x) / F.col("n"), F.col("f").cast("double"))
    cols = [F.sum(F.col("value") * (power("hi") - power("lo"))).alias("mean")]
    cols += [F.min(F.when(power("hi") >= u, F.col("value"))).alias(f"p{u * 100:g}".replace(".", "_")) for u in percentiles]
    out = each.groupBy(F.col("f").alias("fanout")).agg(*cols)
    return out.select("fanout", *[F.round(c, 6).alias(c) for c in out.columns[1:]])


def latency_simulated(latencies: DataFrame, fanouts: Iterable[int] = FANOUTS, trials: int = 200, seed: int = 42) -> DataFrame:
    """The same by hash draws: per trial the largest of f values drawn by rank."""
    known = _in_parts(latencies.where("value is not null").select("value", "event_id"), "value")
    pool = _running(known, ["value", "event_id"], F.lit(1)).select("value", (F.col("hi") - 1).alias("i"))
    n = pool.agg(F.count("*").alias("n"))
    draws = latencies.sparkSession.range(trials).select(F.col("id").alias("trial"), F.explode(F.array(*[F.lit(f) for f in fanouts])).alias("fanout"))
    draws = draws.select("trial", "fanout", F.explode(F.sequence(F.lit(1), F.col("fanout"))).alias("call")).crossJoin(F.broadcast(n))
    drawn = draws.withColumn("i", coin("trial", "fanout", "call", seed) % F.col("n")).join(pool, "i").groupBy("fanout", "trial").agg(F.max("value").alias("m"))
    return drawn.groupBy("fanout").agg(F.round(F.avg("m"), 6).alias("mean"), F.round(F.max("m"), 6).alias("largest"))


def sharded_traffic(edges: DataFrame, assign: DataFrame, rate: float = 1.0, per_record: float = 0.01, seed: int = 42, most: int = 35) -> DataFrame:
    """Sampled queries against a placement: latency of a query is its slowest server's, an exponential draw plus a cost per record. By fanout, up to most."""
    from ..sources.build import sample_queries

    shares = measures.share(sample_queries(edges, rate, seed) if rate < 1 else edges, assign)
    draw = -F.log((coin("qid", "bucket", seed) + 1) / F.lit(float(FULL + 1)))
    per = shares.withColumn("t", draw + per_record * F.col("cnt")).groupBy("qid").agg(F.count("*").alias("fanout"), F.max("t").alias("latency"))
    return per.where(F.col("fanout") <= most).groupBy("fanout").agg(F.count("*").alias("queries"), F.round(F.avg("latency"), 6).alias("latency"))


def _together(work: Callable, cells: Iterable, at_once: int) -> list:
    """work(cell) of all cells in their order, so many at once: small jobs leave cores idle that another cell's can use."""
    with concurrent.futures.ThreadPoolExecutor(max(1, at_once)) as pool:
        return list(pool.map(work, cells))


#: Bytes that no file has: as a split's size and as a file's cost they make one task of each file.
WHOLE_FILE = 1 << 40

#: Cells of an experiment that does not measure times, at once.
AT_ONCE = 4

METHODS: dict[str, Callable[[PartitionSpec], Callable[[DataFrame], PartitionResult]]] = {
    "direct": lambda s: lambda e: partition(e, s.but(arity=None)),
    "bisect": lambda s: lambda e: partition(e, s.but(arity=2, lookahead=True)),
    "direct_p1": lambda s: lambda e: partition(e, s.but(arity=None, objective="fanout", p=1.0)),
    "clique_net": lambda s: lambda e: partition(e, s.but(arity=2, objective="clique")),
    "multilevel": lambda s: lambda e: multilevel(e, s.but(arity=2)),
    "random": lambda s: lambda e: PartitionResult(baselines.baseline_random(vertices_of(e), s.k, s.seed), [], s),
}


def run_one(name: str, edges: DataFrame, method: str, spec: PartitionSpec, timeout_s: float | None = None) -> tuple:
    """A row of RESULT; a run that takes longer than timeout_s, when its jobs are cancelled, has status 'failed'. Whatever else goes wrong in it is raised."""
    began = time.perf_counter()
    context, group = edges.sparkSession.sparkContext, f"run-{uuid.uuid4().hex}"

    def work() -> tuple[float, float]:
        if timeout_s is not None:
            context.setJobGroup(group, f"{name} {method} k={spec.k}", True)
        got = METHODS[method](spec)(edges)
        f = measures.avg_fanout(edges, got.assign).first()["fanout"]
        b = measures.imbalance(got.assign, spec.k).first()["imbalance"]
        forget(got.assign)
        return f, b

    late = False
    if timeout_s is None:
        f, b = work()
    else:
        pool = concurrent.futures.ThreadPoolExecutor(1)
        run = pool.submit(work)
        try:
            late = not concurrent.futures.wait([run], timeout=timeout_s).done
        finally:
            context._jsc.sc().cancelJobGroupAndFutureJobs(group)
            pool.shutdown(wait=True, cancel_futures=True)
        f, b = (math.nan, math.nan) if late else run.result()
    status = "failed" if late else "ok"
    return (name, method, spec.k, spec.p, spec.eps, f, b, time.perf_counter() - began, status)


def quality_grid(spark: SparkSession, graphs: dict[str, DataFrame], methods: Iterable[str], ks: Iterable[int], spec: PartitionSpec = PartitionSpec(), timeout_s: float | None = None, at_once: int = 1) -> DataFrame:
    """Fanout of every method on every graph for every k; k above half the data vertices is skipped. at_once: cells that run side by side, for grids whose run_s is not what they are for; their large graphs are packed once for all cells."""
    rows, methods, ks = [], list(methods), list(ks)
    for name, edges in graphs.items():
        edges = stored(edges.select("qid", "vid"), "grid")
        edges._packed = pack(edges) if at_once > 1 else None
        n = vertices_of(edges).count()
        cells = [(m, k) for k in ks if 2 * k <= n for m in methods]
        rows += _together(lambda c, name=name, edges=edges: run_one(name, edges, c[0], spec.but(k=c[1]), timeout_s), cells, at_once)
        if edges._packed is not None:
            edges._packed.drop()
        forget(edges)
    return spark.createDataFrame(rows, RESULT)


def quality_relative(results: DataFrame) -> DataFrame:
    """Rows of a grid with the excess over the best method of each graph and k, and the share of random sharding's fanout that each saves."""
    done = results.where("status = 'ok'").select("graph", "method", "k", "fanout")
    saved = measures.reduction(done, "random").select("graph", "method", "k", "reduction")
    return measures.relative_quality(done).join(saved, ["graph", "method", "k"], "left")


def runtime_grid(spark, graphs, methods=("direct", "bisect", "multilevel"), ks=(32, 512, 8192), spec=PartitionSpec(), timeout_s: float = 600.0) -> DataFrame:
    return quality_grid(spark, graphs, methods, ks, spec, timeout_s)


def scaling_edges(spark, ladder: dict[str, DataFrame], ks: Iterable[int], spec=PartitionSpec(arity=2)) -> DataFrame:
    """Time of bisection against the number of edges and k, with the ratio to edges * log2(k)."""
    sizes = spark.createDataFrame([(n, e.count()) for n, e in ladder.items()], "graph string, edges long")
    got = quality_grid(spark, ladder, ["bisect"], ks, spec).join(F.broadcast(sizes), "graph")
    return got.select("graph", "edges", "k", "run_s", (F.col("run_s") / (F.col("edges") * F.log2(F.col("k").cast("double")))).alias("s_per_edge_level"))


def scaling_workers(make: Callable[[int], SparkSession], build: Callable[[SparkSession], DataFrame], workers: Iterable[int], spec=PartitionSpec(arity=2)) -> list[dict]:
    """Run and total time for each number of workers; make(w) starts a session with so many."""
    out = []
    for w in workers:
        spark = make(w)
        edges = build(spark)
        edges.count()
        t = measures.timed(lambda: partition(edges, spec), w)
        out.append({"workers": w, "run_s": t["run_s"], "total_s": t["total_s"]})
        spark.stop()
    return out


def scaling_tasks(spark, edges: DataFrame, tasks: Iterable[int], spec=PartitionSpec(arity=2)) -> DataFrame:
    """(tasks, run_s, total_s, speedup): the same run with at most so many tasks of a stage at once, as on so many machines.

    Shuffles have so many parts, and a stored table, which so many tasks wrote, is read file by file.
    Only the plan of a level, a few rows that the driver sends, still comes in one task for each core.
    """
    names, rows = ("spark.sql.shuffle.partitions", "spark.sql.files.maxPartitionBytes", "spark.sql.files.openCostInBytes"), []
    before = {name: spark.conf.get(name) for name in names}
    edges = stored(edges.select("qid", "vid"), "scaling")
    try:
        for w in tasks:
            for name, value in zip(names, (w, WHOLE_FILE, WHOLE_FILE)):
                spark.conf.set(name, str(value))
            t = measures.timed(lambda w=w: forget(partition(edges.coalesce(w), spec).assign), w)
            rows.append((w, t["run_s"], t["total_s"], rows[0][1] / t["run_s"] if rows else 1.0))
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)
    forget(edges)
    return spark.createDataFrame(rows, "tasks int, run_s double, total_s double, speedup double")


def p_sweep(spark, edges: DataFrame, ps: Iterable[float], ks: Iterable[int], spec=PartitionSpec(arity=2, lookahead=True)) -> DataFrame:
    """(k, p, fanout, reduction): share of random sharding's fanout that each p saves."""
    edges, ps = stored(edges.select("qid", "vid"), "sweep"), list(ps)
    rows = []
    for k in ks:
        ref = measures.random_fanout(edges, k).first()["fanout"]
        cells = _together(lambda p, k=k: run_one("sweep", edges, "bisect", spec.but(k=k, p=p)), ps, AT_ONCE)
        rows += [(k, p, row[5], 1 - row[5] / ref) for p, row in zip(ps, cells)]
    forget(edges)
    return spark.createDataFrame(rows, "k int, p double, fanout double, reduction double")


def convergence(spark, edges: DataFrame, k: int, ps: Iterable[float], iterations: int, spec=PartitionSpec()) -> DataFrame:
    """(p, level, iter, moved, moved_frac, fanout, ...) of straight runs."""
    out = None
    edges = stored(edges.select("qid", "vid"), "trace")
    for p in ps:
        got = partition(edges, spec.but(k=k, p=p, arity=None, iterations=iterations))
        frame = got.progress_frame().withColumn("p", F.lit(float(p)))
        forget(got.assign)
        out = frame if out is None else out.unionByName(frame)
    forget(edges)
    return out


def objective_ablation(spark, graphs: dict[str, DataFrame], ks: Iterable[int], spec=PartitionSpec(arity=2, lookahead=True)) -> DataFrame:
    """p = 1 and the clique-net limit against p = 0.5 under bisection: fanout and excess over p = 0.5."""
    rows = []
    for name, edges in graphs.items():
        edges = stored(edges.select("qid", "vid"), "ablation")

        def work(cell: tuple, name=name, edges=edges) -> tuple:
            k, label, s = cell
            got = partition(edges, s.but(k=k))
            fanout = measures.avg_fanout(edges, got.assign).first()["fanout"]
            forget(got.assign)
            return name, label, k, fanout

        variants = (("half", spec), ("p1", spec.but(objective="fanout", p=1.0)), ("clique", spec.but(objective="clique")))
        rows += _together(work, [(k, *v) for k in ks for v in variants], AT_ONCE)
        forget(edges)
    frame = spark.createDataFrame(rows, "graph string, method string, k int, fanout double")
    half = frame.where("method = 'half'").select("graph", "k", F.col("fanout").alias("half"))
    return frame.join(half, ["graph", "k"]).select("graph", "method", "k", "fanout", (F.col("fanout") / F.col("half") - 1).alias("excess"))


def exchange_ablation(spark, edges: DataFrame, spec=PartitionSpec(arity=2, k=8)) -> DataFrame:
    """Plain, histogram, with nonpositive gains, with slack, with look-ahead."""
    variants = {
        "plain": spec,
        "ranked": spec.but(exchange="ranked"),
        "histogram": spec.but(exchange="histogram"),
        "nonpositive": spec.but(exchange="histogram", nonpositive=True),
        "slack": spec.but(exchange="histogram", nonpositive=True, slack=True),
        "lookahead": spec.but(exchange="histogram", nonpositive=True, slack=True, lookahead=True),
    }
    edges = stored(edges.select("qid", "vid"), "exchanges")

    def work(variant: tuple) -> tuple:
        name, s = variant
        got = partition(edges, s)
        row = name, measures.avg_fanout(edges, got.assign).first()["fanout"], measures.imbalance(got.assign, s.k).first()["imbalance"]
        forget(got.assign)
        return row

    rows = _together(work, variants.items(), AT_ONCE)
    forget(edges)
    return spark.createDataFrame(rows, "variant string, fanout double, imbalance double")


def incremental_study(spark, before: DataFrame, after: DataFrame, spec=PartitionSpec(k=8), damp: float = 0.5, penalty: float = 0.25) -> DataFrame:
    """A placement of the older edges, kept, refined with restraint, or redone for all edges: fanout on all, and share of vertices moved."""
    old = partition(before, spec)
    everyone = after.select("vid").distinct()
    kept = refine.init_from(old.assign, everyone, spec.k, spec.eps, spec.seed)
    rows = []
    for name, assign in (("kept", kept), ("refined", repartition(after, old.assign, spec, damp, penalty).assign), ("redone", partition(after, spec.but(seed=spec.seed + 1)).assign)):
        moved = assign.join(old.assign.select("vid", F.col("bucket").alias("was")), "vid").agg(F.avg((F.col("bucket") != F.col("was")).cast("double"))).first()[0]
        rows.append((name, measures.avg_fanout(after, assign).first()["fanout"], float(moved or 0)))
    return spark.createDataFrame(rows, "variant string, fanout double, moved_from_base double")
