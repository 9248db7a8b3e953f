import pytest
from pyspark.sql import functions as F

from shardwise.model import PartitionSpec
from shardwise.operators import measures, packed, refine
from shardwise.plans import experiments, multidim
from shardwise.plans import partition as plans
from shardwise.sources import generate, workloads


def sizes(assign, k):
    return {r.bucket: r["size"] for r in measures.bucket_sizes(assign, k).collect()}


def check_feasible(edges, got, k, eps):
    n = edges.select("vid").distinct().count()
    cap = max(int((1 + eps) * n / k + 1e-9), -(-n // k))
    held = sizes(got.assign, k)
    assert got.assign.count() == n == got.assign.select("vid").distinct().count()
    assert set(held) == set(range(k)) and sum(held.values()) == n
    assert max(held.values()) <= cap


def fan(edges, assign):
    return measures.avg_fanout(edges, assign).first()["fanout"]


@pytest.fixture(scope="module")
def carts(spark, sf):
    return workloads.graph(spark, sf, "brand_cart").cache()


@pytest.mark.parametrize("spec", [
    PartitionSpec(k=4, iterations=3),
    PartitionSpec(k=6, arity=2, iterations=3, lookahead=True),
    PartitionSpec(k=5, arity=3, iterations=2, lookahead=True, exchange="histogram", nonpositive=True, slack=True),
    PartitionSpec(k=4, arity=2, iterations=2, objective="clique"),
    PartitionSpec(k=4, arity=2, iterations=2, objective="fanout", p=1.0, init="ranked"),
    PartitionSpec(k=4, eps=0.0, iterations=2, exchange="ranked"),
])
def test_runs_are_feasible_and_better_than_random(carts, spec):
    got = plans.partition(carts, spec)
    check_feasible(carts, got, spec.k, spec.eps)
    assert fan(carts, got.assign) < fan(carts, refine.init_random(carts.select("vid").distinct(), spec.k))
    assert all(r["fanout"] >= 1 for r in got.progress)


def test_planted_groups_are_found(spark):
    edges, truth = generate.gen_planted(spark, 200, 4, 800, 5, 0.0)
    from shardwise.sources.build import prune_trivial

    edges = prune_trivial(edges).cache()
    assert fan(edges, truth) == 1.0
    got = plans.partition(edges, PartitionSpec(k=4, arity=2, iterations=8, lookahead=True))
    assert fan(edges, got.assign) < 1.35


def test_same_seed_same_result_on_any_partitioning(spark, carts):
    spec = PartitionSpec(k=4, iterations=2)
    a = plans.partition(carts, spec).assign.collect()
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    try:
        b = plans.partition(carts.repartition(5), spec).assign.collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert sorted(map(tuple, a)) == sorted(map(tuple, b))


def test_pruning_changes_nothing(carts):
    spec = PartitionSpec(k=4, arity=2, iterations=2, lookahead=True)
    a, b = plans.partition(carts, spec), plans.partition(carts, spec.but(prune=False))
    assert sorted(map(tuple, a.assign.collect())) == sorted(map(tuple, b.assign.collect()))
    assert [(r["fanout"], r["moved"]) for r in a.progress] == [(pytest.approx(r["fanout"]), r["moved"]) for r in b.progress]


@pytest.mark.parametrize("spec", [
    PartitionSpec(k=3, arity=2, iterations=2),
    PartitionSpec(k=3, arity=2, iterations=1, lookahead=True, exchange="histogram", nonpositive=True),
    PartitionSpec(k=2, iterations=1, objective="clique"),
])
def test_one_shuffle_for_two_children_gives_what_two_give(carts, spec, monkeypatch):
    """Levels of two children are counted in one shuffle if no query is large; the general way gives the same bit by bit."""
    called, plain = [], refine.pair_counts
    monkeypatch.setattr(refine, "pair_counts", lambda *a: called.append(1) or plain(*a))
    a = plans.partition(carts, spec)
    assert called
    monkeypatch.setattr(refine, "WHOLE_QUERY", 0)
    made = len(called)
    b = plans.partition(carts, spec)
    assert len(called) == made
    assert sorted(map(tuple, a.assign.collect())) == sorted(map(tuple, b.assign.collect()))
    same = lambda r: (r["level"], r["iter"], r["moved"], pytest.approx(r["fanout"]), pytest.approx(r["pfanout"]), r["shuffle_rows"])
    assert [(r["level"], r["iter"], r["moved"], r["fanout"], r["pfanout"], r["shuffle_rows"]) for r in a.progress] == [same(r) for r in b.progress]


def test_scaling_reads_with_so_many_tasks(spark, carts, monkeypatch):
    """A table that w tasks wrote is read by w tasks, not by one for each core; settings come back."""
    names = ("spark.sql.shuffle.partitions", "spark.sql.files.maxPartitionBytes", "spark.sql.files.openCostInBytes")
    spark.conf.set(names[2], "1")
    before, seen = [spark.conf.get(n) for n in names], []

    def run(edges, spec):
        table = experiments.stored(edges, "seen")
        seen.append((edges.rdd.getNumPartitions(), table.rdd.getNumPartitions(), edges.count()))
        experiments.forget(table)
        return plans.PartitionResult(None, [], spec)

    monkeypatch.setattr(experiments, "partition", run)
    try:
        rows = experiments.scaling_tasks(spark, carts, (1, 2)).collect()
        assert [spark.conf.get(n) for n in names] == before
    finally:
        spark.conf.unset(names[2])
    n = carts.count()
    assert seen == [(1, 1, n), (2, 2, n)] and [r.tasks for r in rows] == [1, 2]


@pytest.mark.parametrize("spec", [
    PartitionSpec(k=4, iterations=3),
    PartitionSpec(k=6, arity=2, iterations=2, lookahead=True, exchange="histogram", nonpositive=True, slack=True),
])
def test_updating_gives_what_counting_anew_gives(carts, spec):
    """Shares and gains kept from the first turn on, against a new count in every turn."""
    a, b = plans.partition(carts, spec.but(reuse=0.0)), plans.partition(carts, spec.but(reuse=1.0))
    assert sorted(map(tuple, a.assign.collect())) == sorted(map(tuple, b.assign.collect()))
    assert [(r["level"], r["iter"], r["moved"]) for r in a.progress] == [(r["level"], r["iter"], r["moved"]) for r in b.progress]
    assert [r["fanout"] for r in a.progress] == [pytest.approx(r["fanout"]) for r in b.progress]


def test_updates_read_less_as_fewer_vertices_move(spark):
    edges, _ = generate.gen_planted(spark, 400, 4, 1600, 4, 0.0)
    got = plans.partition(edges, PartitionSpec(k=2, iterations=6, reuse=1.0, keep_best=False, repair=False)).progress
    least, most = min(got[:-1], key=lambda r: r["moved"]), max(got[:-1], key=lambda r: r["moved"])
    assert least["moved"] < most["moved"] / 4 and least["shuffle_rows"] < most["shuffle_rows"] / 2


def test_fast_coins(carts):
    got = plans.partition(carts, PartitionSpec(k=4, iterations=2, coins="fast"))
    check_feasible(carts, got, 4, 0.05)


def test_observed_fanout_is_the_measured_one(carts):
    got = plans.partition(carts, PartitionSpec(k=4, iterations=2, keep_best=False, repair=False))
    assert got.progress[-1]["fanout"] == pytest.approx(fan(carts, got.assign), abs=1e-5)


def test_trap_keeps_trading_names_until_damped(spark):
    edges = workloads.toy_trap(spark)
    start = spark.createDataFrame([(v, int(v > 4)) for v in range(1, 9)], "vid long, bucket int")
    once = plans.partition(edges, PartitionSpec(k=2, iterations=1, keep_best=False, repair=False), start=start)
    assert {r.vid: r.bucket for r in once.assign.collect()} == {v: int(v <= 4) for v in range(1, 9)}
    long = plans.partition(edges, PartitionSpec(k=2, iterations=12), start=start)
    assert fan(edges, long.assign) <= 2.0


def test_incremental_bounds(carts):
    base = refine.init_random(carts.select("vid").distinct(), 4)
    was = sorted(map(tuple, base.collect()))
    spec = PartitionSpec(k=4, iterations=2)
    assert sorted(map(tuple, plans.repartition(carts, base, spec, damp=0).assign.collect())) == was
    assert sorted(map(tuple, plans.repartition(carts, base, spec, penalty=float("inf")).assign.collect())) == was
    held = plans.repartition(carts, base, spec.but(repair=False), penalty=1e6).assign
    assert sorted(map(tuple, held.collect())) == was
    row = plans.moved_from_base(plans.repartition(carts, base, spec, damp=0.5, penalty=0.25).assign, base).first()
    assert row.known == len(was) and 0 < row.moved < row.known


def test_new_vertices_fill_room(spark):
    base = spark.createDataFrame([(v, 0 if v < 6 else 1) for v in range(10)], "vid long, bucket int")
    got = refine.init_from(base, spark.range(20).select(F.col("id").alias("vid")), 4, 0.5)
    held = sizes(got, 4)
    assert sum(held.values()) == 20 and held[2] + held[3] > 5


def test_multidim_is_even_in_each_dimension(spark, sf, carts):
    weights = spark.read.parquet(f"{sf}/part.parquet").select(F.col("p_partkey").alias("vid"), F.array(F.lit(1.0), F.col("p_size").cast("double")).alias("dims"))
    got = multidim.partition_multidim(carts, weights, PartitionSpec(k=4, arity=2, iterations=1), c=4)
    assert all(r.imbalance < 0.35 for r in multidim.dimension_imbalance(got.assign, weights, 4).collect())


def test_repair_of_an_overfull_bucket(spark):
    """Exactly the excess goes, best bins first, and no bucket ends above its cap."""
    state = spark.range(5000).select(F.col("id").alias("vid"), F.lit(0).alias("parent"), F.when(F.col("id") < 4600, 0).otherwise(1 + F.col("id") % 3).cast("int").alias("bucket"))
    gains = spark.range(4600).select(F.col("id").alias("vid"), (F.col("id") % 50 - 20).cast("long").alias("gain_fx"))
    caps = spark.createDataFrame([(0, b, 1300) for b in range(4)], "parent int, bucket int, cap long")
    for g in (gains, None):
        out = {r.vid: r.bucket for r in refine.repair_to_cap(state, g, caps).collect()}
        held = [sum(b == x for b in out.values()) for x in range(4)]
        assert len(out) == 5000 and max(held) <= 1300 and held[0] == 1300
        assert all(out[v] == 1 + v % 3 for v in range(4600, 5000))
    left = {v for v, b in {r.vid: r.bucket for r in refine.repair_to_cap(state, gains, caps).collect()}.items() if b != 0 and v < 4600}
    assert all(v in left for v in range(4600) if v % 50 - 20 >= 16)  # the best bin


def test_numbers_are_consecutive(spark):
    df = spark.range(1000).select(F.col("id").alias("vid"), (F.col("id") % 3).alias("g"))
    got = {}
    for r in refine.numbered(df, ["g"], "n", parts=7).collect():
        got.setdefault(r.g, []).append(r.n)
    assert all(sorted(x) == list(range(len(x))) for x in got.values()) and len(got) == 3


def test_too_many_buckets(carts):
    with pytest.raises(ValueError):
        plans.partition(carts, PartitionSpec(k=100_000))


def test_level_plan_splits_evenly():
    assert plans.shares_of((0, 7), 2) == [(0, 4), (4, 3)]
    assert [len(level) for level in plans.level_plan(8, 2)] == [1, 2, 4]
    assert len(plans.level_plan(12, None)) == 1


def test_stored_edges_are_read_in_place_and_kept(spark, carts, monkeypatch):
    """Runs over one table do not each copy it, let alone build the graph anew, and leave it to the caller."""
    copied = []
    write = plans.stored
    monkeypatch.setattr(plans, "stored", lambda df, label: copied.append(label) or write(df, label))
    table = write(carts, "lent")
    spec = PartitionSpec(k=4, arity=2, iterations=1)
    a = plans.partition(table, spec)
    assert "edges" not in copied and table.count() == carts.count()
    assert sorted(map(tuple, a.assign.collect())) == sorted(map(tuple, plans.partition(carts, spec).assign.collect()))


def test_experiments_build_their_graph_once(spark, carts):
    seen = spark.sparkContext.accumulator(0)

    def read(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    n = carts.count()
    edges = carts.mapInArrow(read, carts.schema)
    spec = PartitionSpec(k=2, arity=2, iterations=1)
    rows = experiments.p_sweep(spark, edges, (0.3, 0.5), (2,), spec).collect()
    assert [r.p for r in rows] == [0.3, 0.5] and seen.value == n
    experiments.exchange_ablation(spark, edges, spec).collect()
    assert seen.value == 2 * n
    experiments.quality_grid(spark, {"carts": edges}, ("bisect", "random"), (2,), spec, at_once=2).collect()
    assert seen.value == 3 * n


def test_a_failure_is_no_result(spark, carts, monkeypatch):
    """An error in a cell is raised, with a time-out or without; only a run that is too late has a row, which says so."""

    def broken(spec):
        raise RuntimeError("broken cell")

    spec = PartitionSpec(k=2, arity=2, iterations=1)
    with monkeypatch.context() as m:
        m.setitem(experiments.METHODS, "bisect", broken)
        for work in (
            lambda: experiments.p_sweep(spark, carts, (0.3, 0.5), (2,), spec),
            lambda: experiments.quality_grid(spark, {"carts": carts}, ("random", "bisect"), (2,), spec),
            lambda: experiments.scaling_edges(spark, {"carts": carts}, (2,), spec),
            lambda: experiments.runtime_grid(spark, {"carts": carts}, ("bisect",), (2,), spec),
        ):
            with pytest.raises(RuntimeError, match="broken cell"):
                work()
    (late,) = experiments.runtime_grid(spark, {"carts": carts}, ("bisect",), (2,), spec.but(iterations=50), timeout_s=0.05).collect()
    assert late.status == "failed" and late.fanout != late.fanout


@pytest.mark.parametrize("spec", [
    PartitionSpec(k=6, arity=2, iterations=2, lookahead=True, exchange="histogram", nonpositive=True, slack=True),
    PartitionSpec(k=5, arity=3, iterations=1, objective="clique", prune=False),
    PartitionSpec(k=5, iterations=2),
])
def test_packed_graph_gives_what_edges_give(spark, carts, spec, monkeypatch):
    """Placement, progress and fanout are the same bit by bit; blocks end inside batches."""
    monkeypatch.setattr(packed, "PACK_EDGES", 0)
    monkeypatch.setattr(packed, "BLOCK", 500)
    edges = plans.stored(carts.select("qid", "vid"), "lent")
    a = plans.partition(edges, spec)
    want = fan(edges, a.assign)
    edges._packed = packed.pack(edges)
    b = plans.partition(edges, spec)
    assert sorted(map(tuple, a.assign.collect())) == sorted(map(tuple, b.assign.collect()))
    assert fan(edges, b.assign) == want
    line = lambda got: [(x["level"], x["iter"], x["moved"], round(x["fanout"], 9), round(x["pfanout"], 9)) for x in got.progress]
    assert line(a) == line(b)


def test_quality_grid_does_not_send_edges_in_turns(spark, carts, monkeypatch):
    """Turns and fanouts of a large grid read the packed graph: no edge is joined or shuffled after it is packed."""
    monkeypatch.setattr(packed, "PACK_EDGES", 0, raising=False)
    travelled = []
    for place, name in ((refine, "pair_counts"), (refine, "pair_shares"), (refine, "spread_counts"), (measures, "share")):
        monkeypatch.setattr(place, name, lambda *a, f=getattr(place, name), name=name: travelled.append(name) or f(*a))
    rows = experiments.quality_grid(spark, {"carts": carts}, ("direct", "clique_net", "random"), (2, 3), PartitionSpec(iterations=1, repair=False), at_once=2).collect()
    assert len(rows) == 6 and all(r.status == "ok" for r in rows) and not travelled
