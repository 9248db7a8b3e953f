"""What a placement costs: fanout, its smoothed form and limits, cuts, imbalance, messages, bounds.

edges: (qid, vid); assign: (vid, bucket); share: (qid, bucket, cnt) with cnt > 0 only.
"""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.coin import FULL, coin
from ..functions.kernel import pfanout_term
from ..session import small

DIGITS = 6


def share(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Members of each query in each bucket."""
    return edges.join(assign, "vid").groupBy("qid", "bucket").agg(F.count("*").alias("cnt"))


def query_fanout(shares: DataFrame) -> DataFrame:
    return shares.groupBy("qid").agg(F.count("*").alias("fanout"))


def avg_fanout(edges: DataFrame, assign: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """One row: average number of buckets that a query touches. weights: (qid, qw) of merged queries, each of which counts qw times."""
    packed = getattr(edges, "_packed", None)
    touched = packed.fanout(assign) if packed is not None and weights is None else None
    if touched is not None:
        return edges.sparkSession.createDataFrame([(packed.queries, touched)], "queries long, f long").select("queries", F.round(F.col("f") / F.col("queries"), DIGITS).alias("fanout"))
    per = query_fanout(share(edges, assign))
    if weights is None:
        return per.agg(F.count("*").alias("queries"), F.round(F.avg("fanout"), DIGITS).alias("fanout"))
    return per.join(weights, "qid").agg(F.sum("qw").alias("queries"), F.round(F.sum(F.col("fanout") * F.col("qw")) / F.sum("qw"), DIGITS).alias("fanout"))


def avg_pfanout(edges: DataFrame, assign: DataFrame, p: float, t: int = 1) -> DataFrame:
    """Average expected fanout if each member is needed with probability p; t > 1: look-ahead to t final buckets below each.

    Shares are counted by size first, so the floating-point sum has few terms.
    """
    sizes = share(edges, assign).groupBy("cnt").agg(F.count("*").alias("n"))
    total = F.sum(F.col("n") * F.lit(float(t)) * pfanout_term(F.col("cnt"), p / t))
    return sizes.agg(total.alias("s")).crossJoin(edges.agg(F.count_distinct("qid").alias("q"))).select(F.round(F.col("s") / F.col("q"), DIGITS).alias("pfanout"))


def query_pfanout(shares: DataFrame, p: float) -> DataFrame:
    return shares.groupBy("qid").agg(F.round(F.sum(pfanout_term(F.col("cnt"), p)), DIGITS).alias("pfanout"))


def pfanout_mc(edges: DataFrame, assign: DataFrame, p: float, trials: int, seed: int = 42) -> DataFrame:
    """Mean and standard error over trials of the average fanout when every edge is kept with probability p."""
    tried = edges.join(assign, "vid").select("qid", "vid", "bucket", F.explode(F.sequence(F.lit(0), F.lit(trials - 1))).alias("trial"))
    kept = tried.where(coin("qid", "vid", "trial", seed) < int(p * FULL)).groupBy("trial").agg(F.count_distinct("qid", "bucket").alias("n"))
    queries = edges.agg(F.count_distinct("qid").alias("q"))
    per = kept.crossJoin(queries).select((F.col("n") / F.col("q")).alias("f"))
    return per.agg(F.round(F.avg("f"), DIGITS).alias("pfanout"), F.round(F.stddev("f") / F.sqrt(F.count("*")), DIGITS).alias("std_error"))


def clique_cut(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Weight of the cut pairs if each query were a clique: per query (deg^2 - sum of squares) / 2, no pair is made."""
    per = share(edges, assign).groupBy("qid").agg(F.sum("cnt").alias("d"), F.sum(F.col("cnt") * F.col("cnt")).alias("s"))
    return per.agg(F.coalesce(F.sum(F.expr("(d * d - s) div 2")), F.lit(0)).cast("long").alias("clique_cut"))


def pair_weights(edges: DataFrame, max_degree: int | None = None) -> DataFrame:
    """(u, v, w): queries common to two vertices, u < v. Quadratic in a query's degree: for small graphs, or with the degree bounded."""
    if max_degree:
        few = edges.groupBy("qid").agg(F.count("*").alias("d")).where(F.col("d") <= max_degree).select("qid")
        edges = edges.join(few, "qid", "left_semi")
    pairs = edges.select("qid", F.col("vid").alias("u")).join(edges.select("qid", F.col("vid").alias("v")), "qid").where("u < v")
    return pairs.groupBy("u", "v").agg(F.count("*").alias("w"))


def clique_cut_pairs(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """The same as clique_cut, from the pairs."""
    a, b = assign.select(F.col("vid").alias("u"), F.col("bucket").alias("bu")), assign.select(F.col("vid").alias("v"), F.col("bucket").alias("bv"))
    return pair_weights(edges).join(a, "u").join(b, "v").where("bu <> bv").agg(F.coalesce(F.sum("w"), F.lit(0)).cast("long").alias("clique_cut"))


def cut_measures(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """One row: communication volume, hyperedge cut, and both readings of the sum of external degrees."""
    f = query_fanout(share(edges, assign))
    cut = F.count_if(F.col("fanout") > 1)
    return f.agg(
        F.sum(F.col("fanout") - 1).alias("volume"),
        cut.alias("hyperedge_cut"),
        (F.sum("fanout") + cut).alias("soed"),
        (F.sum(F.col("fanout") - 1) + cut).alias("soed_external"),
    )


def bucket_sizes(assign: DataFrame, k: int, weight: DataFrame | None = None) -> DataFrame:
    """(bucket, size) of all k buckets, empty ones too. weight: optional (vid, w)."""
    if weight is None:
        sizes = assign.groupBy("bucket").agg(F.count("*").alias("size"))
    else:
        sizes = assign.join(weight, "vid").groupBy("bucket").agg(F.sum("w").alias("size"))
    every = assign.sparkSession.range(k).select(F.col("id").cast("int").alias("bucket"))
    return every.join(small(sizes, k), "bucket", "left").select("bucket", F.coalesce("size", F.lit(0)).alias("size"))


def imbalance(assign: DataFrame, k: int, weight: DataFrame | None = None) -> DataFrame:
    """One row: largest bucket against the average, less one."""
    return bucket_sizes(assign, k, weight).agg(F.max("size").alias("largest"), F.min("size").alias("smallest"), F.round(F.max("size") * k / F.sum("size") - 1, DIGITS).alias("imbalance"))


def message_cost(edges: DataFrame, assign: DataFrame) -> DataFrame:
    """Messages of one iteration's four steps: to queries, to vertices, proposals, answers."""
    per = share(edges, assign).groupBy("qid").agg(F.count("*").alias("f"), F.sum("cnt").alias("d"))
    n = assign.agg(F.count("*").alias("n"))
    return per.agg(F.sum("d").alias("collect"), F.sum(F.col("f") * F.col("d")).alias("spread")).crossJoin(n).select("collect", "spread", F.col("n").alias("propose"), F.col("n").alias("answer"))


def message_bound(edges: DataFrame, k: int, arity: int | None = None) -> DataFrame:
    """Bound on the second step's messages: edges times the candidates per vertex (k, or the arity under recursion)."""
    return edges.agg((F.count("*") * (arity or k)).alias("bound"))


def space_cost(edges: DataFrame, k: int) -> DataFrame:
    """Cells held: edges plus k per data vertex; the proposal matrix has up to k^2."""
    return edges.agg((F.count("*") + F.lit(k) * F.count_distinct("vid")).alias("state"), F.lit(k * k).cast("long").alias("matrix"))


def request_skew(shares: DataFrame) -> DataFrame:
    """Per query the largest request and its excess over an even split."""
    return shares.groupBy("qid").agg(F.max("cnt").alias("largest"), F.round(F.max("cnt") / F.avg("cnt"), DIGITS).alias("skew"))


def random_fanout(edges: DataFrame, k: int) -> DataFrame:
    """Expected average fanout of random sharding: k (1 - (1 - 1/k)^degree)."""
    degrees = edges.groupBy("qid").agg(F.count("*").alias("d")).groupBy("d").agg(F.count("*").alias("n"))
    return degrees.agg(F.round(F.sum(F.col("n") * k * (1 - F.pow(F.lit(1 - 1 / k), F.col("d").cast("double")))) / F.sum("n"), DIGITS).alias("fanout"))


def fanout_bounds(edges: DataFrame, k: int, eps: float) -> DataFrame:
    """Per query the least and the largest fanout any feasible placement can give it."""
    n = edges.agg(F.count_distinct("vid").alias("n"))
    cap = F.greatest(F.floor(F.lit(1 + eps) * F.col("n") / k), F.ceil(F.col("n") / k))
    return edges.groupBy("qid").agg(F.count("*").alias("d")).crossJoin(n).select("qid", F.ceil(F.col("d") / cap).alias("least"), F.least(F.lit(k).cast("long"), "d").alias("most"))


def relative_quality(results: DataFrame) -> DataFrame:
    """results(graph, method, k, fanout) with the excess over the best of each graph and k."""
    best = results.groupBy("graph", "k").agg(F.min("fanout").alias("best"))
    return results.join(best, ["graph", "k"]).select("graph", "method", "k", "fanout", F.round(F.col("fanout") / F.col("best") - 1, DIGITS).alias("excess"))


def reduction(results: DataFrame, ref_method: str) -> DataFrame:
    """Share of the reference method's fanout that each method saves."""
    ref = results.where(F.col("method") == ref_method).select("graph", "k", F.col("fanout").alias("ref"))
    return results.join(ref, ["graph", "k"]).select("graph", "method", "k", "fanout", F.round(1 - F.col("fanout") / F.col("ref"), DIGITS).alias("reduction"))


def timed(fn: Callable[[], object], workers: int = 1) -> dict:
    """Wall-clock seconds, and those times the number of machines."""
    began = time.perf_counter()
    value = fn()
    took = time.perf_counter() - began
    return {"value": value, "run_s": took, "total_s": took * workers}
