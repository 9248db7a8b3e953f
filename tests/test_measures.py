import bisect
import itertools
import random

import pytest
from pyspark.sql import functions as F

from shardwise.functions.kernel import Kernel
from shardwise.model import PartitionSpec
from shardwise.operators import baselines, measures, refine
from shardwise.sources import build, workloads


def assign(spark, buckets):
    return spark.createDataFrame(sorted(buckets.items()), "vid long, bucket int")


def toy(spark, name="toy_shard"):
    edges = getattr(workloads, name)(spark)
    split = {v: int(v > 3) for v in range(1, 7)} if name == "toy_shard" else {v: int(v > 4) for v in range(1, 9)}
    return edges, assign(spark, split)


def gains(spark, edges, placed, kernel, t=1):
    state = placed.select("vid", F.lit(0).alias("parent"), "bucket")
    spread = refine.spread_counts(edges, state, refine.neighbor_counts(edges, state))
    return {(r.vid, r.dst): r.gain_fx / kernel.scale for r in refine.move_gains(spread, kernel, [t]).collect()}


def test_toy_shard_measures(spark):
    edges, placed = toy(spark)
    shares = measures.share(edges, placed)
    assert {r.qid: r.fanout for r in measures.query_fanout(shares).collect()} == {1: 2, 2: 2, 3: 1}
    assert {r.qid: r.pfanout for r in measures.query_pfanout(shares, 0.5).collect()} == {1: 1.25, 2: 1.375, 3: 0.875}
    assert measures.cut_measures(edges, placed).first().asDict() == {"volume": 2, "hyperedge_cut": 2, "soed": 7, "soed_external": 4}
    assert measures.clique_cut(edges, placed).first()[0] == 5 == measures.clique_cut_pairs(edges, placed).first()[0]
    assert measures.message_cost(edges, placed).first()["spread"] == 17


def test_toy_shard_gains(spark):
    edges, placed = toy(spark)
    half = {v: 0.5 * g for (v, _), g in gains(spark, edges, placed, Kernel()).items()}
    assert half == {1: -0.125, 2: -0.125, 3: -0.125, 4: 0.0625, 6: 0.0}  # no query of 5 uses the other bucket
    ahead = {v: 0.5 * g for (v, _), g in gains(spark, edges, placed, Kernel(), 2).items()}
    assert ahead == {1: -0.09375, 2: -0.09375, 3: -0.09375, 4: 0.0703125, 6: 0.0}


def test_plain_exchange_needs_a_counterpart(spark):
    edges, placed = toy(spark)
    state = placed.select("vid", F.lit(0).alias("parent"), "bucket")
    proposals = refine.best_targets(refine.spread_counts(edges, state, refine.neighbor_counts(edges, state)), Kernel())
    row = refine.swap_probability(refine.exchange_matrix(proposals)).collect()
    assert [(r.src, r.dst, r.candidates, r.threshold) for r in row] == [(1, 0, 1, 0)]


def test_toy_trap(spark):
    edges, placed = toy(spark, "toy_trap")
    got = gains(spark, edges, placed, Kernel())
    assert {v: 0.5 * g for (v, _), g in got.items()} == {1: 0.125, 2: 0.125, 3: 0.25, 4: 0.25, 5: 0.25, 6: 0.25, 7: 0.125, 8: 0.125}
    assert baselines.exhaustive(edges, 2, 0.0).first()[0] == 4
    assert measures.avg_fanout(edges, baselines.kl_serial(edges, 2)).first()["fanout"] == pytest.approx(4 / 3, abs=1e-6)


@pytest.mark.parametrize("objective", ["pfanout", "fanout", "clique"])
def test_gains_equal_differences(spark, objective):
    """Every gain is what the objective falls by when that one vertex moves."""
    rnd = random.Random(5)
    queries = {q: set(rnd.sample(range(8), rnd.randint(2, 5))) for q in range(7)}
    place = {v: rnd.randrange(3) for v in range(8)}
    edges = spark.createDataFrame([(q, v) for q, s in queries.items() for v in s], "qid long, vid long")

    def value(at):
        total = 0.0
        for s in queries.values():
            counts = [sum(at[v] == b for v in s) for b in range(3)]
            total += {"pfanout": sum(1 - 0.5**c for c in counts), "fanout": sum(c > 0 for c in counts), "clique": (len(s) ** 2 - sum(c * c for c in counts)) / 2}[objective]
        return total

    kernel = Kernel(objective)
    for (v, dst), g in gains(spark, edges, assign(spark, place), kernel).items():
        g = g * 0.5 if objective == "pfanout" else g
        assert g == pytest.approx(value(place) - value(place | {v: dst}), abs=1e-9)


@pytest.mark.parametrize("p, t", [(0.5, 64), (0.5, 70), (0.5, 256), (0.5, 4096), (0.001, 1), (0.01, 4096)])
def test_terms_of_large_counts(spark, p, t):
    """round((1 - p/t)^c * 2^40) for counts of any size, within one unit, never growing, and the same in SQL."""
    import decimal

    import duckdb

    kernel, exact = Kernel("pfanout", p), decimal.Context(prec=60)
    end = int(29 * t / p)
    counts = sorted({0, 1, 2, 1023, 1024, 1025, 3999, 4000, 4001, 4002, 5000, 14000, 1 << 20, (1 << 20) + 1, 10**8, 10**10} | {end * i // 50 for i in range(55)})
    df = spark.createDataFrame([(c,) for c in counts], "c long")
    got = {r.c: (r.a, r.l) for r in df.select("c", kernel.arrive(F.col("c"), t).alias("a"), kernel.leave(F.col("c") + 1, t).alias("l")).collect()}
    base = decimal.Decimal(kernel.base(t))
    for c in counts:
        assert abs(got[c][0] - exact.power(base, c) * (1 << 40)) <= 1
        assert got[c][0] == got[c][1]
    assert [got[c][0] for c in counts] == sorted((a for a, _ in got.values()), reverse=True)
    sql = duckdb.connect().sql(f"SELECT c, {kernel.arrive_sql('c', t)}, {kernel.leave_sql('(c + 1)', t)} FROM (SELECT unnest({counts}::BIGINT[]) AS c)").fetchall()
    assert {c: (a, l) for c, a, l in sql} == got


def test_histogram_bins(spark):
    """The worked bins: a falling sum ends the admitted head of both queues."""
    cols = "src int, dst int, gbin int, candidates long, gain_sum decimal(38,0)"
    from decimal import Decimal as D

    def run(last):
        rows = [(0, 1, 5, 10, D(200)), (0, 1, 3, 6, D(30)), (1, 0, 4, 8, D(80)), (1, 0, *last)]
        got = refine.histogram_match(spark.createDataFrame(rows, cols), nonpositive=True).collect()
        return {(r.src, r.gbin): r.admitted for r in got}

    assert run((-2, 9, D(-18))) == {(0, 5): 10, (0, 3): 6, (1, 4): 8, (1, -2): 8}
    assert run((-3, 9, D(-63))) == {(0, 5): 10, (0, 3): 0, (1, 4): 8, (1, -3): 2}


def test_edge_cases_of_graphs(spark):
    raw = spark.createDataFrame([(1, 1), (1, 1), (1, 2), (2, 5), (None, 3), (3, None)], "q long, v long")
    edges = build.edges_from(raw, "q", "v")
    assert edges.count() == 3
    assert sorted(map(tuple, build.prune_trivial(edges).collect())) == [(1, 1), (1, 2)]
    nothing = edges.where("false")
    assert build.graph_stats(nothing).first().asDict() == {"queries": 0, "edges": 0, "data": 0, "max_degree": None, "avg_degree": None}
    assert measures.avg_fanout(edges, assign(spark, {1: 0, 2: 0, 5: 0})).first()["fanout"] == 1.0
    same = build.from_hyperedges(build.to_hyperedges(edges))
    assert sorted(map(tuple, same.collect())) == sorted(map(tuple, edges.collect()))


def test_spec_domains():
    for bad in ({"k": 1}, {"eps": -0.1}, {"p": 0.0}, {"p": 1.5}, {"objective": "x"}, {"arity": 1}):
        with pytest.raises(ValueError):
            PartitionSpec(**{"k": 2} | bad)
    assert PartitionSpec(k=2, p=1.0).objective == "fanout"
    assert (PartitionSpec(k=2).rounds, PartitionSpec(k=2, arity=2).rounds) == (60, 20)


def test_limits(spark, sf):
    """p -> 1 is fanout, p -> 0 is the clique cut up to a constant, and p-fanout grows with p and stays below fanout."""
    edges = workloads.graph(spark, sf, "cust_part")
    placed = refine.init_random(edges.select("vid").distinct(), 4)
    f = measures.avg_fanout(edges, placed).first()["fanout"]
    values = [measures.avg_pfanout(edges, placed, p).first()[0] for p in (0.1, 0.5, 0.9, 1.0)]
    assert values == sorted(values) and values[-1] == pytest.approx(f, abs=1e-6)
    p, q = 1e-4, edges.select("qid").distinct().count()
    within = measures.share(edges, placed).agg(F.sum(F.expr("cnt * (cnt - 1) / 2"))).first()[0]
    raw = measures.share(edges, placed).agg(F.sum(1 - F.pow(F.lit(1 - p), F.col("cnt").cast("double")))).first()[0]
    assert (p * edges.count() - raw) / p**2 == pytest.approx(within, rel=1e-2)
    assert q > 0
    mc = measures.pfanout_mc(edges, placed, 0.5, 12).first()
    assert abs(mc["pfanout"] - values[1]) < 4 * mc["std_error"] + 1e-3


def test_random_fanout_closed_form(spark, sf):
    edges = workloads.graph(spark, sf, "order_part")
    placed = refine.init_random(edges.select("vid").distinct(), 40)
    got, want = measures.avg_fanout(edges, placed).first()["fanout"], measures.random_fanout(edges, 40).first()["fanout"]
    assert got == pytest.approx(want, rel=0.05)


def test_all_swaps_of_small_graph_exhaustive(spark):
    edges, _ = toy(spark)
    queries = {1: {1, 2, 6}, 2: {1, 2, 3, 4}, 3: {4, 5, 6}}
    best = min(sum(len({v in left for v in s}) for s in queries.values()) for left in itertools.combinations(range(1, 7), 3))
    assert baselines.exhaustive(edges, 2, 0.0).first()[0] == best == 5


@pytest.mark.parametrize("n, k", [(400_000, 8), (1003, 7), (5, 8)])
def test_ranges_of_many_keys_are_cut_at_their_exact_quantiles(spark, n, k):
    """More keys than approximate quantiles are exact for; and fewer keys than ranges."""
    vertices = spark.range(n).selectExpr("id * 7919 % 1000003 AS vid")
    keys = sorted(i * 7919 % 1000003 for i in range(n))
    cuts = [keys[-(-i * n // k) - 1] for i in range(1, k)]
    assert baselines.quantile_cuts(vertices, k).first()["c"] == cuts
    want = [0] * k
    for key in keys:
        want[bisect.bisect_left(cuts, key)] += 1
    got = {r["bucket"]: r["count"] for r in baselines.range_shards(vertices, k, exact=False).groupBy("bucket").count().collect()}
    assert [got.get(b, 0) for b in range(k)] == want
