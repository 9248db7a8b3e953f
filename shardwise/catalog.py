"""The engine's queries by name, and the SQL that each can be compared with."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracle as sql
from .functions.coin import coin, coin_sql
from .functions.kernel import Kernel, gain_bin
from .model import PartitionSpec
from .operators import baselines, measures, refine
from .plans import experiments, multidim, multilevel
from .plans import partition as plans
from .session import stored
from .sources import build, generate, workloads
from .sources.workloads import graph, table

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
K, SEED = 8, 42


def query(name: str, text: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if text:
            SQL[name] = text
        return f

    return keep


def everyone(edges: DataFrame) -> DataFrame:
    return edges.select("vid").distinct()


def placed(spark, sf, key: str, k: int = K) -> tuple[DataFrame, DataFrame]:
    edges = graph(spark, sf, key)
    return edges, refine.init_random(everyone(edges), k, SEED)


# graphs and their forms

for _key in workloads.GRAPHS:
    query(
        f"graph_stats_{_key}",
        f"WITH {sql.edge(_key)}, d AS (SELECT qid, count(*) AS d FROM edge GROUP BY qid) SELECT count(*) AS queries, (SELECT count(DISTINCT vid) FROM edge) AS data, CAST(coalesce(sum(d), 0) AS BIGINT) AS edges, max(d) AS max_degree, round(avg(d), 6) AS avg_degree FROM d",
    )(lambda s, d, key=_key: build.graph_stats(graph(s, d, key)))

query("prune_trivial", f"WITH {sql.edge('order_part')} SELECT qid, vid FROM edge")(lambda s, d: graph(s, d, "order_part"))
query("hyperedge_view", f"WITH {sql.edge('order_part')} SELECT qid, string_agg(CAST(vid AS VARCHAR), ',' ORDER BY vid) AS members FROM edge GROUP BY qid")(
    lambda s, d: build.to_hyperedges(graph(s, d, "order_part")).select("qid", F.array_join(F.transform("members", lambda x: x.cast("string")), ",").alias("members"))
)
query("hyperedge_round_trip", f"WITH {sql.edge('order_part')} SELECT qid, vid FROM edge")(lambda s, d: build.from_hyperedges(build.to_hyperedges(graph(s, d, "order_part"))))
query("dual_graph", f"WITH {sql.edge('cust_part')} SELECT vid AS qid, qid AS vid FROM edge")(lambda s, d: build.dual(graph(s, d, "cust_part")))
query("friend_edges", "SELECT DISTINCT a AS qid, b AS vid FROM (SELECT l_suppkey AS a, l_partkey AS b FROM lineitem UNION ALL SELECT l_partkey, l_suppkey FROM lineitem) WHERE a <> b")(
    lambda s, d: build.friend_edges(table(s, d, "lineitem"), "l_suppkey", "l_partkey")
)


@query("collapse_queries", f"WITH {sql.edge('order_part')}, m AS (SELECT qid, string_agg(CAST(vid AS VARCHAR), ',' ORDER BY vid) AS m FROM edge GROUP BY qid), w AS (SELECT m, min(qid) AS qid, count(*) AS qw FROM m GROUP BY m) SELECT w.qid, qw, vid FROM w JOIN edge USING (qid)")
def _collapse(s, d):
    edges, weights = build.collapse_queries(graph(s, d, "order_part"))
    return edges.join(weights, "qid").select("qid", "qw", "vid")


@query("collapsed_avg_fanout", sql.over("order_part", K, "SELECT count(*) AS queries, round(avg(fanout), 6) AS fanout FROM fan"))
def _collapsed(s, d):
    """Merged queries that count as often as they stand for give the average of all."""
    edges, assign = placed(s, d, "order_part")
    merged, weights = build.collapse_queries(edges)
    return measures.avg_fanout(merged, assign, weights)


query("sample_queries", f"WITH {sql.edge('order_part')} SELECT qid, vid FROM edge WHERE {coin_sql('qid', '42')} < {int(0.1 * (1 << 32))}")(lambda s, d: build.sample_queries(graph(s, d, "order_part"), 0.1))


# measures over a random placement of customers' parts in 8 buckets

def measured(name: str, body: str, f: Callable[[DataFrame, DataFrame], DataFrame], *more: str, key: str = "cust_part", k: int = K):
    query(name, sql.over(key, k, body, *more))(lambda s, d: f(*placed(s, d, key, k)))


def _pf(p: float, t: int = 1, name: str = "pfanout") -> str:
    return f"round(sum({float(t)} * (1 - pow({1 - p / t}, cnt))) / (SELECT count(DISTINCT qid) FROM edge), 6) AS {name}"


measured("share_counts", "SELECT qid, bucket, cnt FROM share", measures.share)
measured("query_fanout", "SELECT qid, fanout FROM fan", lambda e, a: measures.query_fanout(measures.share(e, a)))
measured("avg_fanout", "SELECT count(*) AS queries, round(avg(fanout), 6) AS fanout FROM fan", measures.avg_fanout)
measured("avg_fanout_order_part", "SELECT count(*) AS queries, round(avg(fanout), 6) AS fanout FROM fan", measures.avg_fanout, key="order_part", k=40)
measured("query_pfanout", "SELECT qid, round(sum(1 - pow(0.5, cnt)), 6) AS pfanout FROM share GROUP BY qid", lambda e, a: measures.query_pfanout(measures.share(e, a), 0.5))
measured("pfanout_half", f"SELECT {_pf(0.5)} FROM share", lambda e, a: measures.avg_pfanout(e, a, 0.5))
measured("pfanout_lookahead", f"SELECT {_pf(0.5, 4)} FROM share", lambda e, a: measures.avg_pfanout(e, a, 0.5, 4))
measured("fanout_limit_p1", f"SELECT {_pf(1.0)} FROM share", lambda e, a: measures.avg_pfanout(e, a, 1.0))
measured("clique_cut", "SELECT CAST(sum((d * d - s) // 2) AS BIGINT) AS clique_cut FROM (SELECT qid, sum(cnt) AS d, sum(cnt * cnt) AS s FROM share GROUP BY qid)", measures.clique_cut)
_CUT = "SELECT CAST(count(*) AS BIGINT) AS clique_cut FROM edge x JOIN edge y ON x.qid = y.qid AND x.vid < y.vid JOIN assign a ON a.vid = x.vid JOIN assign b ON b.vid = y.vid WHERE a.bucket <> b.bucket"
measured("clique_cut_pairs", _CUT, measures.clique_cut_pairs, key="order_part")
measured("pair_weights", "SELECT x.vid AS u, y.vid AS v, count(*) AS w FROM edge x JOIN edge y ON x.qid = y.qid AND x.vid < y.vid GROUP BY 1, 2", lambda e, a: measures.pair_weights(e), key="order_part")
measured(
    "cut_measures",
    "SELECT CAST(sum(fanout - 1) AS BIGINT) AS volume, count(*) FILTER (WHERE fanout > 1) AS hyperedge_cut, CAST(sum(fanout) + count(*) FILTER (WHERE fanout > 1) AS BIGINT) AS soed, CAST(sum(fanout - 1) + count(*) FILTER (WHERE fanout > 1) AS BIGINT) AS soed_external FROM fan",
    measures.cut_measures,
    key="order_part",
)
measured("imbalance", f"SELECT CAST(max(n) AS BIGINT) AS largest, CAST(min(n) AS BIGINT) AS smallest, round(max(n) * {K} / sum(n) - 1, 6) AS imbalance FROM (SELECT count(vid) AS n FROM range({K}) b(b) LEFT JOIN assign ON bucket = b GROUP BY b)", lambda e, a: measures.imbalance(a, K))
measured("message_cost", "SELECT CAST(sum(d) AS BIGINT) AS collect, CAST(sum(fanout * d) AS BIGINT) AS spread, (SELECT count(*) FROM assign) AS propose, (SELECT count(*) FROM assign) AS answer FROM fan", measures.message_cost)
measured("message_bound", f"SELECT count(*) * {K} AS bound FROM edge", lambda e, a: measures.message_bound(e, K))
measured("message_bound_recursive", "SELECT count(*) * 2 AS bound FROM edge", lambda e, a: measures.message_bound(e, K, 2))
measured("space_cost", f"SELECT count(*) + {K} * count(DISTINCT vid) AS state, CAST({K * K} AS BIGINT) AS matrix FROM edge", lambda e, a: measures.space_cost(e, K))
measured("request_skew", "SELECT qid, max(cnt) AS largest, round(max(cnt) / avg(cnt), 6) AS skew FROM share GROUP BY qid", lambda e, a: measures.request_skew(measures.share(e, a)))
measured("random_fanout", "SELECT round(sum(n * 40 * (1 - pow(0.975, d))) / sum(n), 6) AS fanout FROM (SELECT d, count(*) AS n FROM (SELECT qid, count(*) AS d FROM edge GROUP BY qid) GROUP BY d)", lambda e, a: measures.random_fanout(e, 40))
_CAP = "(SELECT greatest(floor(1.05 * count(DISTINCT vid) / 8), ceil(count(DISTINCT vid) / 8)) FROM edge)"
measured("fanout_bounds", f"SELECT qid, CAST(ceil(count(*) / {_CAP}) AS BIGINT) AS least, least(8, count(*)) AS most FROM edge GROUP BY qid", lambda e, a: measures.fanout_bounds(e, K, 0.05))


@query("pfanout_sweep", sql.over("cust_part", K, "SELECT p, round(sum(n * (1 - pow(1 - p, cnt))) / (SELECT count(DISTINCT qid) FROM edge), 6) AS pfanout FROM (SELECT cnt, count(*) AS n FROM share GROUP BY cnt) CROSS JOIN (SELECT unnest([0.1, 0.2, 0.3, 0.4, 0.5, 0.6, 0.7, 0.8, 0.9, 1.0])::DOUBLE AS p) GROUP BY p"))
def _sweep(s, d):
    e, a = placed(s, d, "cust_part")
    sizes = measures.share(e, a).groupBy("cnt").agg(F.count("*").alias("n"))
    each = sizes.withColumn("p", F.explode(F.array(*[F.lit(i / 10) for i in range(1, 11)])))
    q = e.agg(F.count_distinct("qid").alias("q"))
    return each.groupBy("p").agg(F.sum(F.col("n") * (1 - F.pow(1 - F.col("p"), F.col("cnt").cast("double")))).alias("x")).crossJoin(q).select("p", F.round(F.col("x") / F.col("q"), 6).alias("pfanout"))


@query("pfanout_mc", sql.over("order_part", K, f"SELECT round(avg(f), 6) AS pfanout, round(stddev(f) / sqrt(count(*)), 6) AS std_error FROM (SELECT t, count(DISTINCT (qid, bucket)) / (SELECT count(DISTINCT qid) FROM edge) AS f FROM edge JOIN assign USING (vid) CROSS JOIN range(10) r(t) WHERE {coin_sql('qid', 'vid', 't', '42')} < {1 << 31} GROUP BY t)"))
def _mc(s, d):
    return measures.pfanout_mc(*placed(s, d, "order_part"), 0.5, 10)


# latency

_COUNTS = "c AS (SELECT value, count(*) AS c FROM events WHERE value IS NOT NULL GROUP BY value), r AS (SELECT value, sum(c) OVER (ORDER BY value) AS hi, sum(c) OVER (ORDER BY value) - c AS lo, (SELECT sum(c) FROM c) AS n FROM c), f AS (SELECT value, f, pow(hi / n, f) AS up, pow(lo / n, f) AS down FROM r CROSS JOIN (SELECT unnest([1, 2, 5, 10, 20, 35, 40]) AS f))"
query("latency_exact", f"WITH {_COUNTS} SELECT f AS fanout, round(sum(value * (up - down)), 6) AS mean, " + ", ".join(f"round(min(value) FILTER (WHERE up >= {u}), 6) AS p{int(u * 100)}" for u in (0.5, 0.9, 0.95, 0.99)) + " FROM f GROUP BY f")(lambda s, d: experiments.latency_exact(table(s, d, "events").select("value")))
query(
    "latency_simulated",
    f"WITH pool AS (SELECT value, row_number() OVER (ORDER BY value, event_id) - 1 AS i FROM events WHERE value IS NOT NULL), d AS (SELECT t, f, unnest(range(1, f + 1)) AS call FROM range(200) r(t) CROSS JOIN (SELECT unnest([1, 2, 5, 10, 20, 35, 40]) AS f)), m AS (SELECT f, t, max(value) AS m FROM d JOIN pool ON i = {coin_sql('t', 'f', 'call', '42')} % (SELECT count(*) FROM pool) GROUP BY f, t) SELECT f AS fanout, round(avg(m), 6) AS mean, round(max(m), 6) AS largest FROM m GROUP BY f",
)(lambda s, d: experiments.latency_simulated(table(s, d, "events")))
_DRAW = f"-ln(({coin_sql('qid', 'bucket', '42')} + 1) / 4294967297.0)"
measured("random_sharding_latency", f"SELECT fanout, count(*) AS queries, round(avg(latency), 6) AS latency FROM (SELECT qid, count(*) AS fanout, max({_DRAW} + 0.01 * cnt) AS latency FROM share GROUP BY qid) WHERE fanout <= 35 GROUP BY fanout", lambda e, a: experiments.sharded_traffic(e, a), k=40)


@query("store_random_k40", sql.over("cust_part", 40, f"SELECT fanout, count(*) AS queries, round(avg(latency), 6) AS latency FROM (SELECT qid, count(*) AS fanout, max({_DRAW} + 0.01 * cnt) AS latency FROM share WHERE {coin_sql('qid', '42')} < {1 << 31} GROUP BY qid) WHERE fanout <= 35 GROUP BY fanout"))
def _store_random(s, d):
    """Sampled traffic on 40 servers with records at random: latency by fanout."""
    return experiments.sharded_traffic(*placed(s, d, "cust_part", 40), rate=0.5)


@query(
    "store_partitioned_k40",
    sql.unrolled("cust_part", 40, 2, arity=2, lookahead=True, body=f"SELECT fanout, count(*) AS queries, round(avg(latency), 6) AS latency FROM (SELECT qid, count(*) AS fanout, max({_DRAW} + 0.01 * cnt) AS latency FROM (SELECT qid, bucket, count(*) AS cnt FROM edge JOIN assign USING (vid) WHERE {coin_sql('qid', '42')} < {1 << 31} GROUP BY qid, bucket) GROUP BY qid) WHERE fanout <= 35 GROUP BY fanout"),
)
def _store_partitioned(s, d):
    """The same traffic on the same servers after a bisection of two turns a level."""
    edges = graph(s, d, "cust_part")
    return experiments.sharded_traffic(edges, plans.partition(edges, _BARE.but(k=40, arity=2, lookahead=True, iterations=2)).assign, rate=0.5)


@query("partitioned_latency")
def _partitioned_latency(s, d):
    """The same traffic after partitioning: fanout, and so latency, move down."""
    edges = graph(s, d, "brand_cart")
    return experiments.sharded_traffic(edges, plans.partition(edges, PartitionSpec(k=8, arity=2, iterations=4, lookahead=True)).assign)


# one iteration, step by step, from a random start on orders' parts

def _state(s, d, key="order_part", k=K):
    e, a = placed(s, d, key, k)
    return e, a.select("vid", F.lit(0).alias("parent"), "bucket")


_STATE = f"s_0 AS MATERIALIZED (SELECT DISTINCT vid, 0 AS parent, CAST({coin_sql('vid', '42')} % {K} AS INTEGER) AS bucket FROM edge)"


def _spread(s, d):
    e, st = _state(s, d)
    return refine.spread_counts(e, st, refine.neighbor_counts(e, st))


query("init_random", f"WITH {sql.edge('order_part')}, {sql.assign(K)} SELECT vid, bucket FROM assign")(lambda s, d: refine.init_random(everyone(graph(s, d, "order_part")), K))
query("init_ranked", f"WITH {sql.edge('order_part')} SELECT vid, CAST((row_number() OVER (ORDER BY {coin_sql('vid', '42')}, vid) - 1) % {K} AS INTEGER) AS bucket FROM (SELECT DISTINCT vid FROM edge)")(lambda s, d: refine.init_ranked(everyone(graph(s, d, "order_part")), K))
query("spread_counts", f"WITH {sql.edge('supp_part')}, {_STATE}, h AS (SELECT qid, bucket, count(*) AS cnt FROM edge JOIN s_0 USING (vid) GROUP BY ALL) SELECT s.bucket AS src, h.bucket, CAST(sum(cnt) AS BIGINT) AS cnt, count(*) AS n FROM edge JOIN s_0 s USING (vid) JOIN h ON h.qid = edge.qid GROUP BY ALL")(
    lambda s, d: (lambda e, st: refine.spread_counts(e, st, refine.neighbor_counts(e, st)).groupBy("src", "bucket").agg(F.sum("cnt").alias("cnt"), F.count("*").alias("n")))(*_state(s, d, "supp_part"))
)
for _name, _kernel, _t in (("half", Kernel(), 1), ("p1", Kernel("fanout"), 1), ("clique", Kernel("clique"), 1), ("lookahead", Kernel(), 4), ("p03", Kernel("pfanout", 0.3), 1)):
    query(f"move_gains_{_name}", f"WITH {sql.edge('order_part')}, {_STATE}, {sql.gains(_kernel, '0', _t)} SELECT vid, src, dst, gain_fx FROM gain_0")(
        lambda s, d, kernel=_kernel, t=_t: refine.move_gains(_spread(s, d), kernel, [t]).select("vid", "src", "dst", "gain_fx")
    )
_UP = f"WITH {sql.edge('order_part')}, {_STATE}, {sql.gains(Kernel(), '0')}, {sql.proposals('0')}"


def _proposals(s, d):
    return refine.best_targets(_spread(s, d), Kernel())


query("best_targets", f"{_UP} SELECT vid, src, dst, gain_fx, gbin::INTEGER AS gbin FROM prop_0")(lambda s, d: _proposals(s, d).select("vid", "src", "dst", "gain_fx", "gbin"))
query("exchange_matrix", f"{_UP} SELECT src, dst, count(*) AS candidates, CAST(sum(gain_fx) AS BIGINT) AS gain_sum FROM prop_0 GROUP BY src, dst")(lambda s, d: refine.exchange_matrix(_proposals(s, d)).withColumn("gain_sum", F.col("gain_sum").cast("long")))
query("swap_probability", f"{_UP}, {sql.plain('0')} SELECT src, dst, candidates, CAST(admitted AS BIGINT) AS admitted, threshold FROM th_0")(lambda s, d: refine.swap_probability(refine.exchange_matrix(_proposals(s, d))))
query("gain_histogram", f"{_UP} SELECT src, dst, gbin::INTEGER AS gbin, count(*) AS candidates FROM prop_0 GROUP BY src, dst, gbin")(lambda s, d: refine.exchange_matrix(_proposals(s, d), True).select("src", "dst", "gbin", "candidates"))
query("histogram_match", f"{_UP}, {sql.histogram('0')} SELECT src, dst, gbin::INTEGER AS gbin, candidates, CAST(admitted AS BIGINT) AS admitted, threshold FROM th_0")(
    lambda s, d: refine.histogram_match(refine.exchange_matrix(_proposals(s, d), True)).select("src", "dst", "gbin", "candidates", "admitted", "threshold")
)
query("exchange_ranked", f"{_UP}, rk AS (SELECT *, row_number() OVER (PARTITION BY src, dst ORDER BY gain_fx DESC, vid) AS rn FROM prop_0) SELECT a.vid, a.src, a.dst FROM rk a JOIN rk b ON b.src = a.dst AND b.dst = a.src AND a.rn = b.rn")(lambda s, d: refine.exchange_ranked(_proposals(s, d)))


@query(
    "slack_moves",
    f"{_UP}, {sql.histogram('0')}, z AS (SELECT bucket, count(*) AS size FROM s_0 GROUP BY bucket), w AS (SELECT t.*, greatest(floor(1.05 * (SELECT count(*) FROM s_0) / {K}) - z.size, 0) AS room, CASE WHEN gbin > 0 THEN candidates - admitted ELSE 0 END AS spare FROM th_0 t JOIN z ON z.bucket = t.dst), "
    "v AS (SELECT *, coalesce(sum(spare) OVER (PARTITION BY dst ORDER BY gbin DESC, src ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM w) "
    "SELECT src, dst, gbin::INTEGER AS gbin, candidates, CAST(admitted + greatest(least(spare, room - before), 0) AS BIGINT) AS admitted FROM v",
)
def _slack(s, d):
    ex = refine.histogram_match(refine.exchange_matrix(_proposals(s, d), True))
    _, st = _state(s, d)
    n = st.count()
    sizes = st.groupBy("bucket").agg(F.count("*").alias("size")).withColumn("cap", F.floor(F.lit(1.05 * n / K)))
    return refine.slack_moves(ex, sizes).select("src", "dst", "gbin", "candidates", "admitted")


_MOVES = f"{_UP}, {sql.plain('0')}, {sql.moved('0', '1', SEED, 1, 1, 'plain')}, mv AS (SELECT vid, a.bucket AS src, b.bucket AS dst FROM s_0 a JOIN s_1 b USING (vid) WHERE a.bucket <> b.bucket)"


def _moves(s, d):
    """The moves (vid, parent, src, dst) of the first turn."""
    proposals = _proposals(s, d)
    taken = refine.accepted(proposals, refine.swap_probability(refine.exchange_matrix(proposals)), SEED, 1, 1).select("vid")
    return proposals.join(taken, "vid", "left_semi").select("vid", "parent", "src", "dst")


query("accepted_moves", f"{_MOVES} SELECT vid, src, dst FROM mv")(lambda s, d: _moves(s, d).select("vid", "src", "dst"))


@query("delta_counts", f"{_MOVES} SELECT qid, bucket, count(*) AS cnt FROM edge JOIN s_1 USING (vid) GROUP BY qid, bucket")
def _delta(s, d):
    """Shares after the first turn's moves by signed deltas; the SQL counts them anew."""
    e, st = _state(s, d)
    return refine.delta_counts(measures.share(e, st.select("vid", "bucket")), e, _moves(s, d))


@query("dirty_vertices", f"{_MOVES} SELECT DISTINCT vid FROM edge WHERE qid IN (SELECT qid FROM edge WHERE vid IN (SELECT vid FROM mv))")
def _dirty(s, d):
    return refine.dirty_vertices(graph(s, d, "order_part"), _moves(s, d))


@query("changed_counts", f"{_MOVES}, n AS (SELECT qid, bucket, count(*) AS cnt FROM edge JOIN s_1 USING (vid) GROUP BY qid, bucket) SELECT qid, coalesce(o.bucket, n.bucket) AS bucket, coalesce(o.cnt, 0)::BIGINT AS old, coalesce(n.cnt, 0)::BIGINT AS new FROM share_0 o FULL JOIN n USING (qid, bucket) WHERE coalesce(o.cnt, 0) <> coalesce(n.cnt, 0)")
def _changed(s, d):
    e, st = _state(s, d)
    return refine.changed_counts(refine.neighbor_counts(e, st), e, _moves(s, d)).select("qid", "bucket", "old", "new")


@query("updated_targets", f"{_MOVES}, {sql.gains(Kernel(), '1')}, {sql.proposals('1')} SELECT vid, src, dst, gain_fx FROM prop_1")
def _updated(s, d):
    """Proposals after the first turn's moves from updated shares and parts; the SQL counts all anew."""
    e, st = _state(s, d)
    e, moves, shares = stored(e, "edges"), stored(_moves(s, d), "moves"), refine.neighbor_counts(e, st)
    parts = refine.gain_parts(refine.spread_counts(e, st, shares), Kernel())
    after = refine.apply_moves(st, moves.select("vid", "dst")).drop("moved")
    changed = refine.changed_counts(shares, e, moves)
    new = refine.updated_parts(parts, e, after, moves, changed, refine.updated_counts(shares, changed), Kernel(), lambda rows: rows)
    return refine.best_of_parts(new).select("vid", "src", "dst", "gain_fx")


@query("gain_state", f"WITH {sql.edge('order_part')}, {_STATE}, {sql.gains(Kernel(), '0')} SELECT vid, src, dst, round(gain_fx / 1099511627776.0 * 0.5, 6) AS gain FROM gain_0")
def _gain_state(s, d):
    e, st = _state(s, d)
    a = st.select("vid", "bucket")
    state = refine.gain_state(e, measures.share(e, a), 0.5)
    return refine.gain_from_state(state, a, e.groupBy("vid").agg(F.count("*").alias("deg")), 0.5).withColumn("gain", F.round("gain", 6))


# iterations written out in SQL

_BARE = PartitionSpec(k=K, repair=False, keep_best=False, prune=False)


def _written_out(key: str, spec: PartitionSpec, turns: int, **more) -> str:
    free = spec.nonpositive and spec.exchange != "plain"
    return sql.unrolled(key, spec.k, turns, spec.objective, spec.p, spec.arity, spec.lookahead, spec.exchange, nonpositive=free, room=spec.eps if spec.slack else None, **more)


def unrolled(name: str, key: str, spec: PartitionSpec, turns: int, **more):
    query(name, _written_out(key, spec, turns, **more))(lambda s, d: plans.partition(graph(s, d, key), spec.but(iterations=turns)).assign)


unrolled("direct_k8_t1", "order_part", _BARE, 1)
unrolled("direct_k8_t3", "order_part", _BARE, 3)
unrolled("direct_k4_p1_t3", "order_part", _BARE.but(k=4, objective="fanout", p=1.0), 3)
unrolled("direct_k4_clique_t3", "order_part", _BARE.but(k=4, objective="clique"), 3)
unrolled("bisect_k4_t2", "brand_cart", _BARE.but(k=4, arity=2), 2)
unrolled("bisect_k8_lookahead_t1", "order_part", _BARE.but(arity=2, lookahead=True), 1)
unrolled("recursive_r4_k16_t1", "cust_part", _BARE.but(k=16, arity=4), 1)
unrolled("direct_ranked_t2", "order_part", _BARE.but(exchange="ranked"), 2)
unrolled("direct_hist_t2", "order_part", _BARE.but(exchange="histogram"), 2)


unrolled("bisect_k6_uneven_t2", "brand_cart", _BARE.but(k=6, arity=2, lookahead=True), 2)
unrolled("nonpositive_k4_t2", "order_part", _BARE.but(k=4, exchange="histogram", nonpositive=True), 2)
unrolled("advanced_direct_k6_t2", "brand_cart", _BARE.but(k=6, exchange="histogram", nonpositive=True, slack=True), 2)
unrolled("advanced_bisect_k4_t2", "brand_cart", _BARE.but(k=4, arity=2, lookahead=True, exchange="histogram", nonpositive=True, slack=True), 2)
unrolled("advanced_bisect_k6_t1", "brand_cart", _BARE.but(k=6, arity=2, lookahead=True, exchange="histogram", nonpositive=True, slack=True), 1)
unrolled("recursive_r3_k9_clique_t1", "order_part", _BARE.but(k=9, arity=3, objective="clique"), 1)


@query("weighted_k4_t2", sql.unrolled("order_part", 4, 2, weight="SELECT p_partkey AS vid, p_size AS w FROM part"))
def _weighted(s, d):
    """Vertices of different size: opposite crowds move equal weight."""
    sizes = table(s, d, "part").select(F.col("p_partkey").alias("vid"), F.col("p_size").cast("long").alias("w"))
    return plans.partition(graph(s, d, "order_part"), _BARE.but(k=4, iterations=2), weights=sizes).assign


@query("updates_from_the_first_turn", sql.unrolled("order_part", K, 3))
def _reused(s, d):
    """Three turns in which shares and gains are updated, never counted anew."""
    return plans.partition(graph(s, d, "order_part"), _BARE.but(iterations=3, reuse=1.0)).assign


@query("incremental_t2", sql.unrolled("order_part", K, 2, damp=0.5, penalty=1 << 38, start="home"))
def _incremental(s, d):
    e, a = placed(s, d, "order_part")
    return plans.repartition(e, a, _BARE.but(iterations=2), damp=0.5, penalty=0.25).assign


# whole runs: compared by properties in the tests

def summary(edges: DataFrame, got, k: int) -> DataFrame:
    """One row per bucket: size, queries that touch it, average fanout before (random) and after."""
    before = measures.avg_fanout(edges, refine.init_random(everyone(edges), k)).select(F.col("fanout").alias("fanout_before"))
    after = measures.avg_fanout(edges, got.assign).select(F.col("fanout").alias("fanout_after"))
    touch = measures.share(edges, got.assign).groupBy("bucket").agg(F.count("*").alias("queries"))
    return measures.bucket_sizes(got.assign, k).join(touch, "bucket", "left").crossJoin(before).crossJoin(after)


def whole(name: str, key: str, spec: PartitionSpec):
    @query(name)
    def run(s, d):
        edges = stored(graph(s, d, key), "graph")
        return summary(edges, plans.partition(edges, spec), spec.k)


whole("direct_k8_full", "order_part", PartitionSpec(k=8, iterations=6))
whole("bisect_k8_full", "order_part", PartitionSpec(k=8, arity=2, iterations=4, lookahead=True))
whole("bisect_k32_full", "token_doc", PartitionSpec(k=32, arity=2, iterations=3, lookahead=True, init="ranked"))
whole("recursive_r4_k16", "brand_cart", PartitionSpec(k=16, arity=4, iterations=4, lookahead=True))
whole("advanced_bisect_k8", "brand_cart", PartitionSpec(k=8, arity=2, iterations=4, lookahead=True, exchange="histogram", nonpositive=True, slack=True))
whole("advanced_direct_k8", "brand_cart", PartitionSpec(k=8, iterations=4, exchange="histogram", nonpositive=True, slack=True))
whole("bisect_k6_uneven", "brand_cart", PartitionSpec(k=6, arity=2, iterations=3, lookahead=True))
whole("clique_net_bisect", "brand_cart", PartitionSpec(k=8, arity=2, iterations=4, objective="clique"))
whole("fanout_p1_bisect", "brand_cart", PartitionSpec(k=8, arity=2, iterations=4, objective="fanout", p=1.0))


@query("multidim_k8")
def _multidim(s, d):
    edges = graph(s, d, "brand_cart")
    weights = workloads.part_weights(s, d)
    got = multidim.partition_multidim(edges, weights, PartitionSpec(k=8, arity=2, iterations=2), c=2)
    return multidim.dimension_imbalance(got.assign, weights, 8)


@query("multilevel_k8")
def _multilevel(s, d):
    edges = graph(s, d, "order_part")
    return summary(edges, multilevel.multilevel(edges, PartitionSpec(k=8, arity=2, iterations=2), levels=1), 8)


@query("explicit_clique_cut")
def _explicit(s, d):
    """The clique graph made explicit, refined on its cut: the baseline that the limit kernel replaces."""
    edges = graph(s, d, "order_part")
    got = multilevel.cut_refine(baselines.clique_graph(edges), PartitionSpec(k=8, iterations=3))
    return measures.avg_fanout(edges, got.assign)


@query("best_of")
def _best(s, d):
    edges = graph(s, d, "brand_cart")
    base = PartitionSpec(k=4, arity=2, iterations=2)
    got = plans.best_of(edges, [base, base.but(objective="clique"), base.but(objective="fanout", p=1.0)])
    return measures.avg_fanout(edges, got.assign)


query("convergence_trace")(lambda s, d: experiments.convergence(s, graph(s, d, "brand_cart"), 8, (0.5, 1.0), 10))
query("p_sweep")(lambda s, d: experiments.p_sweep(s, graph(s, d, "brand_cart"), tuple(i / 10 for i in range(1, 11)), (4,), PartitionSpec(arity=2, iterations=2, lookahead=True)))
query("objective_ablation")(lambda s, d: experiments.objective_ablation(s, {"brand_cart": graph(s, d, "brand_cart")}, (2, 8), PartitionSpec(arity=2, iterations=2, lookahead=True)))
query("exchange_ablation")(lambda s, d: experiments.exchange_ablation(s, graph(s, d, "brand_cart"), PartitionSpec(k=4, arity=2, iterations=2)))
def _with_relative(grid: DataFrame) -> DataFrame:
    return grid.join(experiments.quality_relative(grid).select("graph", "method", "k", "excess", "reduction"), ["graph", "method", "k"], "left")


query("scaling_tasks")(lambda s, d: experiments.scaling_tasks(s, graph(s, d, "brand_cart"), (1, 2, 4), PartitionSpec(k=4, arity=2, iterations=2)))
query("quality_grid")(lambda s, d: _with_relative(experiments.quality_grid(s, {"order_part": graph(s, d, "order_part"), "brand_cart": graph(s, d, "brand_cart")}, ("direct", "bisect", "clique_net", "random"), (2, 8), PartitionSpec(iterations=3), at_once=experiments.AT_ONCE)))
query("scaling_edges")(lambda s, d: experiments.scaling_edges(s, {x: graph(s, d, x) for x in ("hour_user", "cust_part")}, (2, 8), PartitionSpec(arity=2, iterations=2)))
query("runtime_grid")(lambda s, d: experiments.runtime_grid(s, {"cust_part": graph(s, d, "cust_part")}, ("direct", "bisect"), (32,), PartitionSpec(iterations=2)))


# the experiments again with one turn a level, which SQL can write out cell by cell

def _measured(k: int) -> str:
    return (
        "SELECT (SELECT count(DISTINCT qid) FROM edge) AS queries, (SELECT round(avg(f), 6) FROM (SELECT count(DISTINCT bucket) AS f FROM edge JOIN assign USING (vid) GROUP BY qid)) AS fanout, "
        f"(SELECT round(max(c) * {k} / sum(c) - 1, 6) FROM (SELECT count(*) AS c FROM assign GROUP BY bucket)) AS imbalance"
    )


def _cells(cells: list[tuple[str, str]]) -> str:
    """One row per (columns, text of a cell): the columns and what is measured in the cell."""
    return "cells AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT {columns}, * FROM ({text})" for columns, text in cells) + ")"


def _cell(key: str, spec: PartitionSpec) -> str:
    return _written_out(key, spec, 1, body=_measured(spec.k))


_ONE = _BARE.but(iterations=1)
_HALVES = _ONE.but(arity=2, lookahead=True)
_TENTHS = tuple(i / 10 for i in range(1, 11))
_OBJECTIVES = {"half": {}, "p1": {"objective": "fanout", "p": 1.0}, "clique": {"objective": "clique"}}
_GRID = {"direct": _ONE, "bisect": _HALVES, "direct_p1": _ONE.but(objective="fanout", p=1.0), "clique_net": _ONE.but(arity=2, objective="clique")}
_EXCHANGES = {"plain": {}, "ranked": {"exchange": "ranked"}}
_EXCHANGES["histogram"] = {"exchange": "histogram"}
_EXCHANGES["nonpositive"] = _EXCHANGES["histogram"] | {"nonpositive": True}
_EXCHANGES["slack"] = _EXCHANGES["nonpositive"] | {"slack": True}
_EXCHANGES["lookahead"] = _EXCHANGES["slack"] | {"lookahead": True}

query("p_sweep_t1", "WITH " + _cells([(f"4 AS k, CAST({p} AS DOUBLE) AS p", _cell("brand_cart", _HALVES.but(k=4, p=p))) for p in _TENTHS]) + f", ref AS (WITH {sql.edge('brand_cart')} SELECT round(avg(4 * (1 - pow(0.75, d))), 6) AS r FROM (SELECT count(*) AS d FROM edge GROUP BY qid)) SELECT k, p, fanout, round(1 - fanout / r, 6) AS reduction FROM cells, ref")(
    lambda s, d: experiments.p_sweep(s, graph(s, d, "brand_cart"), _TENTHS, (4,), _HALVES).withColumn("reduction", F.round("reduction", 6))
)
query(
    "objective_ablation_t1",
    "WITH " + _cells([(f"'brand_cart' AS graph, '{name}' AS method, {k} AS k", _cell("brand_cart", _HALVES.but(k=k, **o))) for k in (2, 8) for name, o in _OBJECTIVES.items()]) + " SELECT graph, method, k, fanout, round(fanout / max(CASE WHEN method = 'half' THEN fanout END) OVER (PARTITION BY graph, k) - 1, 6) AS excess FROM cells",
)(lambda s, d: experiments.objective_ablation(s, {"brand_cart": graph(s, d, "brand_cart")}, (2, 8), _HALVES).withColumn("excess", F.round("excess", 6)))
query("exchange_ablation_t1", "WITH " + _cells([(f"'{name}' AS variant", _cell("brand_cart", _ONE.but(k=4, arity=2, **x))) for name, x in _EXCHANGES.items()]) + " SELECT variant, fanout, imbalance FROM cells")(
    lambda s, d: experiments.exchange_ablation(s, graph(s, d, "brand_cart"), _ONE.but(k=4, arity=2))
)
query("best_of_t1", "WITH " + _cells([(f"'{name}' AS method", _cell("brand_cart", _HALVES.but(k=4, **o))) for name, o in _OBJECTIVES.items()]) + " SELECT queries, min(fanout) AS fanout FROM cells GROUP BY queries")(
    lambda s, d: (lambda e: measures.avg_fanout(e, plans.best_of(e, [_HALVES.but(k=4, **o) for o in _OBJECTIVES.values()]).assign))(graph(s, d, "brand_cart"))
)
query(
    "quality_grid_t1",
    "WITH "
    + _cells(
        [(f"'{g}' AS graph, '{m}' AS method, {k} AS k", _cell(g, x.but(k=k))) for g in ("order_part", "brand_cart") for m, x in _GRID.items() for k in (4,)]
        + [(f"'{g}' AS graph, 'random' AS method, {k} AS k", f"WITH {sql.edge(g)}, {sql.assign(k)} {_measured(k)}") for g in ("order_part", "brand_cart") for k in (4,)]
    )
    + " SELECT graph, method, k, fanout, imbalance, round(fanout / min(fanout) OVER (PARTITION BY graph, k) - 1, 6) AS excess, round(1 - fanout / max(CASE WHEN method = 'random' THEN fanout END) OVER (PARTITION BY graph, k), 6) AS reduction FROM cells",
)(lambda s, d: _with_relative(experiments.quality_grid(s, {x: graph(s, d, x) for x in ("order_part", "brand_cart")}, (*_GRID, "random"), (4,), _ONE, at_once=experiments.AT_ONCE)).select("graph", "method", "k", "fanout", "imbalance", "excess", "reduction"))


@query("incremental_study")
def _study(s, d):
    days = table(s, d, "orders").select(F.col("o_orderkey").alias("qid"), F.unix_date(F.col("o_orderdate").cast("date")).alias("day"))
    cut = days.agg(F.percentile_approx("day", 0.8)).first()[0]
    every = workloads.order_part(s, d)
    before = build.prune_trivial(every.join(days.where(F.col("day") < cut).select("qid"), "qid", "left_semi"))
    return experiments.incremental_study(s, before, build.prune_trivial(every), PartitionSpec(k=8, iterations=3))


# baselines

query("range_sharding", f"WITH {sql.edge('order_part')} SELECT vid, CAST(ntile(8) OVER (ORDER BY vid) - 1 AS INTEGER) AS bucket FROM (SELECT DISTINCT vid FROM edge)")(lambda s, d: baselines.range_shards(everyone(graph(s, d, "order_part")), 8))
query("range_sharding_approx", f"WITH {sql.edge('order_part')}, v AS (SELECT DISTINCT vid FROM edge), r AS (SELECT vid, row_number() OVER (ORDER BY vid) AS r, (SELECT count(*) FROM v) AS n FROM v), c AS (SELECT min(vid) AS cut FROM r CROSS JOIN range(1, 8) i(i) WHERE r >= i * n / 8 GROUP BY i), b AS (SELECT vid, (SELECT count(*) FROM c WHERE cut < vid) AS b FROM v), z AS (SELECT count(vid) AS n FROM range(8) k(k) LEFT JOIN b ON b.b = k GROUP BY k) SELECT max(n) AS largest, min(n) AS smallest, round(max(n) * 8 / sum(n) - 1, 6) AS imbalance FROM z")(lambda s, d: measures.imbalance(baselines.range_shards(everyone(graph(s, d, "order_part")), 8, exact=False), 8))
query(
    "planted_truth_fanout",
    f"WITH {sql.edge('brand_cart')}, assign AS (SELECT p_partkey AS vid, dense_rank() OVER (ORDER BY p_brand) - 1 AS bucket FROM part) SELECT count(*) AS queries, round(avg(f), 6) AS fanout FROM (SELECT qid, count(DISTINCT bucket) AS f FROM edge JOIN assign USING (vid) GROUP BY qid)",
)(lambda s, d: measures.avg_fanout(graph(s, d, "brand_cart"), baselines.truth_shards(table(s, d, "part").select(F.col("p_partkey").alias("vid"), "p_brand"), "p_brand")))
_PAIRS = f"WITH {sql.edge('order_part')}, w AS MATERIALIZED (SELECT x.vid AS u, y.vid AS v, count(*) AS w FROM edge x JOIN edge y ON x.qid = y.qid AND x.vid < y.vid GROUP BY 1, 2)"
query("clique_graph_topm", f"{_PAIRS}, e AS (SELECT u, v, w, u AS e FROM w UNION ALL SELECT u, v, w, v FROM w), r AS (SELECT *, row_number() OVER (PARTITION BY e ORDER BY w DESC, u, v) AS r FROM e) SELECT DISTINCT u, v, w FROM r WHERE r <= 5")(lambda s, d: baselines.clique_graph(graph(s, d, "order_part"), top_m=5))
query("clique_graph_sampled", f"{_PAIRS} SELECT u, v, CAST(round(w / 0.25) AS BIGINT) AS w FROM w WHERE {coin_sql('u', 'v', '42')} < {1 << 30}")(lambda s, d: baselines.clique_graph(graph(s, d, "order_part"), keep=0.25))
query("clique_graph_min_weight", f"{_PAIRS} SELECT u, v, w FROM w WHERE w >= 2")(lambda s, d: baselines.clique_graph(graph(s, d, "order_part"), min_weight=2))
_KINDS = (
    "kinds AS (SELECT p_type, row_number() OVER (ORDER BY p_type) - 1 AS kind FROM (SELECT DISTINCT p_type FROM part)), sets AS (SELECT m, count(*) AS w FROM "
    "(SELECT l_orderkey, bit_or(1 << kind) AS m FROM lineitem JOIN part ON p_partkey = l_partkey JOIN kinds USING (p_type) GROUP BY 1) WHERE bit_count(m) > 1 GROUP BY m), "
    "halves AS (SELECT p, full_set - p AS o FROM (SELECT CAST((1 << (SELECT count(*) FROM kinds)) - 1 AS BIGINT) AS full_set) CROSS JOIN range(64) x(p) WHERE bit_count(p) = 3 AND p <= full_set), "
    "t AS MATERIALIZED (SELECT p, sum(w * (CAST(m & p <> 0 AS INTEGER) + CAST(m & o <> 0 AS INTEGER))) AS total, sum(w * (2 - pow(0.5, bit_count(m & p)) - pow(0.5, bit_count(m & o)))) AS cost FROM sets CROSS JOIN halves GROUP BY p)"
)


def _kinds(s, d) -> tuple[DataFrame, DataFrame]:
    """Orders and the kinds of their parts, equal orders merged: as many queries at most as there are sets of kinds."""
    edges, weights = build.collapse_queries(build.prune_trivial(workloads.order_type(s, d)))
    merged = stored(edges.join(weights, "qid"), "kinds")
    return merged.select("qid", "vid"), merged.select("qid", "qw").distinct()


query(
    "kl_serial_toy",
    f"WITH RECURSIVE {_KINDS}, nxt AS MATERIALIZED (SELECT a.p, arg_min(b.p, b.cost) AS q FROM t a JOIN t b ON bit_count(xor(a.p, b.p)) = 2 AND b.cost < a.cost - 1e-12 GROUP BY a.p), "
    "walk AS (SELECT CAST(56 AS BIGINT) AS p UNION ALL SELECT q FROM walk JOIN nxt USING (p)) SELECT CAST((SELECT sum(w) FROM sets) AS BIGINT) AS queries, round(arg_min(total, cost) / (SELECT sum(w) FROM sets), 6) AS fanout FROM walk JOIN t USING (p)",
)(lambda s, d: (lambda e, w: measures.avg_fanout(e, baselines.kl_serial(e, 2, weights=w), w))(*_kinds(s, d)))
query("exhaustive_toy", f"WITH {_KINDS} SELECT CAST(min(total) AS BIGINT) AS total FROM t")(lambda s, d: (lambda e, w: baselines.exhaustive(e, 2, 0.0, weights=w))(*_kinds(s, d)))


@query(
    "gen_planted_fanout",
    f"WITH n AS (SELECT max(p_partkey) + 1 AS n FROM part), raw AS (SELECT DISTINCT q AS qid, CASE WHEN {coin_sql('q', 'i', '42', '1')} < {int(0.1 * (1 << 32))} THEN {coin_sql('q', 'i', '42', '2')} % n ELSE least(q % 8 * (n // 8) + {coin_sql('q', 'i', '42')} % (n // 8), n - 1) END AS vid FROM (SELECT DISTINCT o_orderkey AS q FROM orders) CROSS JOIN range(1, 7) b(i) CROSS JOIN n), "
    "edge AS (SELECT * FROM raw WHERE qid IN (SELECT qid FROM raw GROUP BY qid HAVING count(*) > 1)) SELECT count(*) AS queries, round(avg(f), 6) AS fanout FROM (SELECT qid, count(DISTINCT least(vid // (n // 8), 7)) AS f FROM edge CROSS JOIN n GROUP BY qid)",
)
def _planted(s, d):
    """Planted groups of the parts, and members drawn for every order."""
    n = table(s, d, "part").agg(F.max("p_partkey") + 1).first()[0]
    edges, truth = generate.gen_planted(s, n, 8, 0, 6, 0.1, asked=table(s, d, "orders").select(F.col("o_orderkey").alias("id")).distinct())
    return measures.avg_fanout(build.prune_trivial(edges), truth)


@query(
    "gen_friendship_stats",
    f"WITH n AS (SELECT max(o_custkey) + 1 AS n FROM orders), named AS (SELECT a, CASE WHEN {coin_sql('a', 'i', '42', '2')} < {int(0.1 * (1 << 32))} THEN {coin_sql('a', 'i', '42', '1')} % n ELSE least(a - a % (n // 10) + {coin_sql('a', 'i', '42')} % (n // 10), n - 1) END AS b FROM (SELECT DISTINCT o_custkey AS a FROM orders) CROSS JOIN range(1, 16) y(i) CROSS JOIN n), "
    "raw AS (SELECT DISTINCT qid, vid FROM (SELECT a AS qid, b AS vid FROM named UNION ALL SELECT b, a FROM named) WHERE qid <> vid), edge AS (SELECT * FROM raw WHERE qid IN (SELECT qid FROM raw GROUP BY qid HAVING count(*) > 1)), d AS (SELECT qid, count(*) AS d FROM edge GROUP BY qid) "
    "SELECT count(*) AS queries, (SELECT count(DISTINCT vid) FROM edge) AS data, CAST(sum(d) AS BIGINT) AS edges, max(d) AS max_degree, round(avg(d), 6) AS avg_degree FROM d",
)
def _friendship(s, d):
    """Friends drawn for every customer with an order."""
    people = table(s, d, "orders").select(F.col("o_custkey").alias("id")).distinct()
    n = people.agg(F.max("id") + 1).first()[0]
    return build.graph_stats(build.prune_trivial(generate.gen_friendship(s, n, 30, people=people)))


query(
    "cut_refine_t1",
    f"{_PAIRS}, {sql.assign(8, name='a0')}, ends AS (SELECT u AS vid, v AS o, w FROM w UNION ALL SELECT v, u, w FROM w), far AS (SELECT x.vid, a.bucket AS b, sum(w) AS w FROM ends x JOIN a0 a ON a.vid = x.o GROUP BY x.vid, a.bucket), "
    "gain AS (SELECT a.vid, a.bucket AS src, f.b AS dst, f.w - coalesce(h.w, 0) AS g FROM a0 a JOIN far f ON f.vid = a.vid AND f.b <> a.bucket LEFT JOIN far h ON h.vid = a.vid AND h.b = a.bucket), "
    "prop AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY vid ORDER BY g DESC, dst) AS r FROM gain) WHERE r = 1 AND g > 0), ex AS (SELECT src, dst, count(*) AS c FROM prop GROUP BY src, dst), "
    f"th AS (SELECT x.src, x.dst, (least(x.c, coalesce(y.c, 0))::HUGEINT * {1 << 32}) // x.c AS threshold FROM ex x LEFT JOIN ex y ON y.src = x.dst AND y.dst = x.src), "
    f"a1 AS (SELECT a.vid, coalesce(m.dst, a.bucket) AS bucket FROM a0 a LEFT JOIN (SELECT p.vid, p.dst FROM prop p JOIN th USING (src, dst) WHERE {coin_sql('p.vid', '42', '1', '1')} < threshold) m USING (vid)), "
    "cut AS (SELECT sum(w) FILTER (WHERE x0.bucket <> y0.bucket) AS before, sum(w) FILTER (WHERE x1.bucket <> y1.bucket) AS after FROM w JOIN a0 x0 ON x0.vid = u JOIN a0 y0 ON y0.vid = v JOIN a1 x1 ON x1.vid = u JOIN a1 y1 ON y1.vid = v) "
    "SELECT a0.vid, CAST(CASE WHEN after < before THEN a1.bucket ELSE a0.bucket END AS INTEGER) AS bucket FROM a0 JOIN a1 USING (vid) CROSS JOIN cut",
)(lambda s, d: multilevel.cut_refine(baselines.clique_graph(graph(s, d, "order_part")), PartitionSpec(k=8, iterations=1)).assign.select("vid", "bucket"))

# a table of results: fanouts of placements that need no refinement, measured on two graphs

_RESULT_GRAPHS, _RESULT_KS = ("hour_user", "supp_part"), (2, 8, 32)
_PLACEMENTS = {"random": lambda k: coin("vid", SEED) % k, "modulo": lambda k: F.col("vid") % k, "range": lambda k: F.expr(f"vid * {k} div n")}
_PLACEMENTS_SQL = {"random": lambda k: f"{coin_sql('vid', str(SEED))} % {k}", "modulo": lambda k: f"vid % {k}", "range": lambda k: f"vid * {k} // n"}
_RESULT_CELLS = [(m, k) for m in _PLACEMENTS for k in _RESULT_KS]


def _values_of(key: str) -> str:
    cells = " UNION ALL ".join(f"SELECT '{key}' AS graph, '{m}' AS method, {k} AS k, round(avg(f), 6) AS fanout FROM (SELECT qid, count(DISTINCT {_PLACEMENTS_SQL[m](k)}) AS f FROM edge CROSS JOIN n GROUP BY qid)" for m, k in _RESULT_CELLS)
    return f"SELECT * FROM (WITH {sql.edge(key)}, n AS (SELECT max(vid) + 1 AS n FROM edge) {cells})"


_VALUES = "r AS MATERIALIZED (" + " UNION ALL ".join(_values_of(g) for g in _RESULT_GRAPHS) + ")"


def results(s: SparkSession, d: str) -> DataFrame:
    """(graph, method, k, fanout): the buckets that a query touches are one bit mask per placement, so all placements of a graph are measured in one aggregate."""
    out = None
    for key in _RESULT_GRAPHS:
        edges = graph(s, d, key)
        edges = edges.crossJoin(F.broadcast(edges.agg((F.max("vid") + 1).alias("n"))))
        masks = edges.groupBy("qid").agg(*[F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), _PLACEMENTS[m](k).cast("int"))).alias(f"{m}_{k}") for m, k in _RESULT_CELLS])
        means = masks.agg(*[F.round(F.avg(F.bit_count(f"{m}_{k}")), 6).alias(f"{m}_{k}") for m, k in _RESULT_CELLS])
        rows = F.array(*[F.struct(F.lit(key).alias("graph"), F.lit(m).alias("method"), F.lit(k).alias("k"), F.col(f"{m}_{k}").alias("fanout")) for m, k in _RESULT_CELLS])
        cells = means.select(F.inline(rows))
        out = cells if out is None else out.union(cells)
    return stored(out, "results")


query("relative_quality", f"WITH {_VALUES} SELECT graph, method, k, fanout, round(fanout / min(fanout) OVER (PARTITION BY graph, k) - 1, 6) AS excess FROM r")(lambda s, d: measures.relative_quality(results(s, d)))
query("reduction", f"WITH {_VALUES} SELECT r.graph, r.method, r.k, r.fanout, round(1 - r.fanout / x.fanout, 6) AS reduction FROM r JOIN r x ON x.graph = r.graph AND x.k = r.k AND x.method = 'random'")(lambda s, d: measures.reduction(results(s, d), "random"))
query("results_pivot", f"WITH {_VALUES} SELECT graph, k, " + ", ".join(f"max(fanout) FILTER (WHERE method = '{m}') AS {m}" for m in _PLACEMENTS) + " FROM r GROUP BY graph, k")(
    lambda s, d: results(s, d).groupBy("graph", "k").pivot("method", list(_PLACEMENTS)).agg(F.max("fanout"))
)
query("results_cube", f"WITH {_VALUES} SELECT coalesce(graph, 'all') AS graph, coalesce(method, 'all') AS method, round(avg(fanout), 6) AS fanout FROM r GROUP BY CUBE (graph, method)")(
    lambda s, d: results(s, d).cube("graph", "method").agg(F.round(F.avg("fanout"), 6).alias("fanout")).select(F.coalesce("graph", F.lit("all")).alias("graph"), F.coalesce("method", F.lit("all")).alias("method"), "fanout")
)
query("results_rollup", f"WITH {_VALUES} SELECT coalesce(graph, 'all') AS graph, coalesce(method, 'all') AS method, count(*) AS n FROM r GROUP BY ROLLUP (graph, method)")(
    lambda s, d: results(s, d).rollup("graph", "method").agg(F.count("*").alias("n")).select(F.coalesce("graph", F.lit("all")).alias("graph"), F.coalesce("method", F.lit("all")).alias("method"), "n")
)
query("results_unpivot", f"WITH {_VALUES} SELECT graph, method, k, fanout FROM r")(
    lambda s, d: results(s, d).groupBy("graph", "k").pivot("method", list(_PLACEMENTS)).agg(F.max("fanout")).unpivot(["graph", "k"], list(_PLACEMENTS), "method", "fanout")
)

# operators around the methods

query("heaviest_queries", f"WITH {sql.edge('order_part')} SELECT qid, count(*) AS d FROM edge GROUP BY qid ORDER BY d DESC, qid LIMIT 20")(lambda s, d: graph(s, d, "order_part").groupBy("qid").agg(F.count("*").alias("d")).orderBy(F.desc("d"), "qid").limit(20))
query("top_members", f"WITH {sql.edge('cust_part')}, n AS (SELECT vid, count(*) AS n FROM edge GROUP BY vid), r AS (SELECT qid, vid, n, row_number() OVER (PARTITION BY qid ORDER BY n DESC, vid) AS r FROM edge JOIN n USING (vid)) SELECT qid, vid, n, CAST(r AS INTEGER) AS r FROM r WHERE r <= 3")(
    lambda s, d: (lambda e: e.join(e.groupBy("vid").agg(F.count("*").alias("n")), "vid").withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("n"), "vid"))).where("r <= 3").select("qid", "vid", "n", "r"))(graph(s, d, "cust_part"))
)
query("placement_diff", f"WITH {sql.edge('order_part')}, {sql.assign(8)}, {sql.assign(8, 7, 'other')} SELECT coalesce(a.bucket, -1) AS was, coalesce(b.bucket, -1) AS now, count(*) AS n FROM assign a FULL JOIN (SELECT * FROM other WHERE vid % 10 <> 0) b USING (vid) GROUP BY 1, 2")(
    lambda s, d: (lambda v: refine.init_random(v, 8).withColumnRenamed("bucket", "a").join(refine.init_random(v, 8, 7).where("vid % 10 <> 0").withColumnRenamed("bucket", "b"), "vid", "full_outer").groupBy(F.coalesce("a", F.lit(-1)).alias("was"), F.coalesce("b", F.lit(-1)).alias("now")).agg(F.count("*").alias("n")))(everyone(graph(s, d, "order_part")))
)
query("new_vertices", "SELECT DISTINCT l_partkey AS vid FROM lineitem WHERE l_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_orderkey % 20 = 0)")(
    lambda s, d: (lambda l: l.select("l_partkey").distinct().join(l.where("l_orderkey % 20 = 0").select("l_partkey"), "l_partkey", "left_anti").select(F.col("l_partkey").alias("vid")))(table(s, d, "lineitem"))
)
query("edge_set_operations", "WITH a AS (SELECT DISTINCT l_orderkey AS qid FROM lineitem WHERE l_quantity > 25), b AS (SELECT DISTINCT l_orderkey AS qid FROM lineitem WHERE l_discount > 0.05) SELECT (SELECT count(*) FROM (SELECT * FROM a UNION SELECT * FROM b)) AS either, (SELECT count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b)) AS both, (SELECT count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)) AS first_only")(
    lambda s, d: (lambda a, b: a.union(b).distinct().agg(F.count("*").alias("either")).crossJoin(a.intersect(b).agg(F.count("*").alias("both"))).crossJoin(a.subtract(b).agg(F.count("*").alias("first_only"))))(
        table(s, d, "lineitem").where("l_quantity > 25").select(F.col("l_orderkey").alias("qid")).distinct(), table(s, d, "lineitem").where("l_discount > 0.05").select(F.col("l_orderkey").alias("qid")).distinct()
    )
)
query("size_ranks", f"WITH {sql.edge('order_part')}, {sql.assign(8)}, z AS (SELECT bucket, count(*) AS size FROM assign GROUP BY bucket) SELECT bucket, size, CAST(rank() OVER (ORDER BY size) AS INTEGER) AS r, CAST(dense_rank() OVER (ORDER BY size) AS INTEGER) AS dr, round(percent_rank() OVER (ORDER BY size), 6) AS pr, round(cume_dist() OVER (ORDER BY size), 6) AS cd, coalesce(size - lag(size) OVER (ORDER BY size, bucket), 0) AS step FROM z")(
    lambda s, d: measures.bucket_sizes(placed(s, d, "order_part")[1], 8).select("bucket", "size", F.rank().over(Window.orderBy("size")).alias("r"), F.dense_rank().over(Window.orderBy("size")).alias("dr"), F.round(F.percent_rank().over(Window.orderBy("size")), 6).alias("pr"), F.round(F.cume_dist().over(Window.orderBy("size")), 6).alias("cd"), F.coalesce(F.col("size") - F.lag("size").over(Window.orderBy("size", "bucket")), F.lit(0)).alias("step"))
)
query("hourly_traffic", "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) // 3600 AS hour, count(DISTINCT user_id) AS users, count(*) AS events, count(*) FILTER (WHERE CAST(json_extract(props, '$.k') AS BIGINT) >= 50) AS high_keys FROM events GROUP BY 1")(
    lambda s, d: table(s, d, "events").groupBy(F.expr("unix_seconds(cast(date_trunc('HOUR', ts) as timestamp)) div 3600").alias("hour")).agg(F.count_distinct("user_id").alias("users"), F.count("*").alias("events"), F.count_if(F.get_json_object("props", "$.k").cast("long") >= 50).alias("high_keys"))
)
query("region_report", f"WITH {sql.edge('cust_part')}, {sql.assign(8)}, {sql.SHARE}, f AS (SELECT qid, count(*) AS fanout FROM share GROUP BY qid) SELECT r_name, count(*) AS queries, round(avg(fanout), 6) AS fanout FROM f JOIN customer ON c_custkey = qid JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY r_name")(
    lambda s, d: measures.query_fanout(measures.share(*placed(s, d, "cust_part"))).join(table(s, d, "customer"), F.col("qid") == F.col("c_custkey")).join(F.broadcast(table(s, d, "nation")), F.col("n_nationkey") == F.col("c_nationkey")).join(F.broadcast(table(s, d, "region")), F.col("r_regionkey") == F.col("n_regionkey")).groupBy("r_name").agg(F.count("*").alias("queries"), F.round(F.avg("fanout"), 6).alias("fanout"))
)
query("placement_as_of", f"WITH v AS (SELECT unnest([0, 1, 2]) AS version, unnest([0, 30, 60]) AS since), a AS (SELECT c_custkey, version, since, {coin_sql('c_custkey', 'version')} % 8 AS bucket FROM customer CROSS JOIN v), o AS (SELECT o_orderkey, o_custkey, o_orderkey % 90 AS day FROM orders) SELECT o_orderkey, max(version)::INTEGER AS version, CAST(arg_max(bucket, version) AS BIGINT) AS bucket FROM o JOIN a ON c_custkey = o_custkey AND since <= day GROUP BY o_orderkey")(
    lambda s, d: _as_of(s, d)
)


def _as_of(s, d):
    """Latest version of a placement at the time of a query."""
    from .functions.coin import coin

    versions = s.createDataFrame([(0, 0), (1, 30), (2, 60)], "version int, since int")
    a = table(s, d, "customer").select("c_custkey").crossJoin(F.broadcast(versions)).withColumn("bucket", coin("c_custkey", "version") % 8)
    o = table(s, d, "orders").select("o_orderkey", "o_custkey", (F.col("o_orderkey") % 90).alias("day"))
    hit = o.join(a, (F.col("o_custkey") == F.col("c_custkey")) & (F.col("since") <= F.col("day")))
    return hit.groupBy("o_orderkey").agg(F.max("version").alias("version"), F.max_by("bucket", "version").alias("bucket"))


@query("sql_functions", sql.over("cust_part", K, f"SELECT {_pf(0.5)} FROM share"))
def _sql_functions(s, d):
    """The same measure through the SQL surface."""
    from .functions.sqlapi import register

    e, a = placed(s, d, "cust_part")
    register(s, e, a)
    return s.sql("SELECT round(sum(pf_term(cnt, 0.5D)) / max(q), 6) AS pfanout FROM (SELECT qid, bucket, count(*) AS cnt FROM edge JOIN assign USING (vid) GROUP BY qid, bucket) CROSS JOIN (SELECT count(DISTINCT qid) AS q FROM edge)")


@query("expand_path", f"SELECT bucket, l AS level, CAST(bucket >> (3 - l) AS INTEGER) AS code, size FROM (SELECT CAST({coin_sql('vid', '42')} % 8 AS INTEGER) AS bucket, count(*) AS size FROM (SELECT DISTINCT l_partkey AS vid FROM lineitem) GROUP BY 1) CROSS JOIN (SELECT CAST(unnest([1, 2, 3]) AS INTEGER) AS l)")
def _expand(s, d):
    """The buckets of the parts on lines, placed at random, with their ancestors under halving."""
    from .functions.sqlapi import register

    parts = refine.init_random(table(s, d, "lineitem").select(F.col("l_partkey").alias("vid")).distinct(), 8, SEED)
    register(s, assign=parts)
    return s.sql("SELECT b.bucket, p.level, p.code, b.size FROM (SELECT bucket, count(*) AS size FROM assign GROUP BY bucket) b, LATERAL expand_path(b.bucket, 3) p")


@query("gain_bins", f"WITH {sql.edge('order_part')}, {_STATE}, {sql.gains(Kernel(), '0')} SELECT CASE WHEN gain_fx > 0 THEN length(bin(gain_fx)) WHEN gain_fx < 0 THEN -length(bin(-gain_fx)) ELSE 0 END::INTEGER AS gbin, count(*) AS moves, min(gain_fx) AS least, max(gain_fx) AS most FROM gain_0 GROUP BY 1")
def _bins(s, d):
    """The bins of all moves' gains, of either sign."""
    edges, state = _state(s, d)
    gains = refine.move_gains(refine.spread_counts(edges, state, refine.neighbor_counts(edges, state)), Kernel())
    return gains.groupBy(gain_bin(F.col("gain_fx")).alias("gbin")).agg(F.count("*").alias("moves"), F.min("gain_fx").alias("least"), F.max("gain_fx").alias("most"))


# streams over the events, run to their end on files in the order of time; a last event without key, days later, moves the watermark past all windows but its own

def _stream(s, d, plan, mode: str = "append") -> DataFrame:
    import uuid

    from .session import shared_dir
    from .streaming import traffic

    root = f"{shared_dir(s)}/streams/{uuid.uuid4().hex}"
    events = table(s, d, "events").select(F.col("event_id").cast("long"), "ts", F.col("user_id").cast("long"), "event_type", "value", "props")
    events.repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(f"{root}/in")
    close = events.agg((F.max("ts") + F.expr("INTERVAL 9 DAYS")).alias("ts"), F.min("user_id").alias("user_id"))
    close.select(F.lit(None).cast("long").alias("event_id"), "ts", "user_id", F.lit(None).cast("string").alias("event_type"), F.lit(None).cast("double").alias("value"), F.lit(None).cast("string").alias("props")).coalesce(1).write.mode("append").parquet(f"{root}/in")
    out = plan(traffic, traffic.edge_stream(s, f"{root}/in", 4))
    sink = out.writeStream.option("checkpointLocation", f"{root}/state").outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        run = sink.format("parquet").option("path", f"{root}/out").start()
    else:  # a table per batch, which a batch that is run again replaces
        run = sink.foreachBatch(lambda batch, number: batch.write.mode("overwrite").parquet(f"{root}/out/batch={number}")).start()
    run.awaitTermination()
    return s.read.schema(out.schema).parquet(f"{root}/out")


def _users(s, d):
    return refine.init_random(table(s, d, "events").select(F.col("user_id").cast("long").alias("vid")).distinct(), 8)


_SECONDS = "CAST(epoch(date_trunc('second', ts)) AS BIGINT)"
_PLACED = f"p AS (SELECT {_SECONDS} AS s, ts, user_id AS vid, CAST(json_extract(props, '$.k') AS BIGINT) AS key, {coin_sql('user_id', '42')} % 8 AS bucket, event_id FROM events WHERE user_id IS NOT NULL)"


def _windows(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.unix_seconds("start")).withColumn("end", F.unix_seconds("end"))


query("stream_tumbling", f"WITH {_PLACED} SELECT s // 3600 * 3600 AS start, s // 3600 * 3600 + 3600 AS end, count(DISTINCT bucket) AS fanout, count(*) AS events FROM p GROUP BY 1, 2")(
    lambda s, d: _windows(_stream(s, d, lambda t, e: t.windowed_fanout(e, _users(s, d)))).withColumn("fanout", F.col("fanout").cast("long"))
)
query("stream_sliding", f"WITH {_PLACED} SELECT w AS start, w + 7200 AS end, count(DISTINCT bucket) AS fanout, count(*) AS events FROM (SELECT *, s // 1800 * 1800 - 1800 * unnest(range(4)) AS w FROM p) GROUP BY 1, 2")(
    lambda s, d: _windows(_stream(s, d, lambda t, e: t.windowed_fanout(e, _users(s, d), "2 hours", "30 minutes"))).withColumn("fanout", F.col("fanout").cast("long"))
)
query(
    "stream_sessions",
    f"WITH {_PLACED}, g AS (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY vid ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM p), n AS (SELECT *, sum(new) OVER (PARTITION BY vid ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS number FROM g) "
    "SELECT CAST(epoch(date_trunc('second', min(ts))) AS BIGINT) AS start, vid, string_agg(DISTINCT CAST(key AS VARCHAR), ',' ORDER BY CAST(key AS VARCHAR)) AS members FROM n GROUP BY vid, number",
)(lambda s, d: _stream(s, d, lambda t, e: t.session_edges(e.where("vid is not null"))).select(F.unix_seconds("start").alias("start"), "vid", F.array_join(F.array_sort(F.transform("members", lambda x: x.cast("string"))), ",").alias("members")))
query("stream_dedup", f"WITH {_PLACED} SELECT DISTINCT key, vid FROM p WHERE key IS NOT NULL")(lambda s, d: _stream(s, d, lambda t, e: t.deduplicated(e)).where("vid is not null and key is not null").select("key", "vid"))
query("stream_state", f"WITH {_PLACED} SELECT key AS qid, count(DISTINCT bucket) AS fanout FROM p WHERE key IS NOT NULL GROUP BY key")(
    lambda s, d: _stream(s, d, lambda t, e: t.stateful_share(e, _users(s, d)), "update").groupBy("qid").agg(F.max("fanout").alias("fanout"))
)
query("stream_interval_join", f"WITH {_PLACED} SELECT event_id AS a_id, event_id % 20 * 60000000 AS micros FROM p WHERE event_id % 20 <= 10")(
    lambda s, d: _stream(s, d, lambda t, e: t.reply_latency(e.where("event_id is not null"), e.where("event_id is not null").select("event_id", (F.col("ts") + F.make_dt_interval(mins=(F.col("event_id") % 20).cast("int"))).alias("ts"))))
)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bisection of orders' parts into 8 buckets."""
    edges = graph(spark, sf_dir, "order_part")
    return summary(edges, plans.partition(edges, PartitionSpec(k=8, arity=2, iterations=4, lookahead=True)), 8)
