"""Placements to compare with: random, range and given groups; cliques and their cut; serial and exhaustive search."""

from __future__ import annotations

from itertools import product

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.coin import FULL, coin
from .measures import pair_weights
from .refine import init_random


def baseline_random(vertices: DataFrame, k: int, seed: int = 42) -> DataFrame:
    return init_random(vertices, k, seed)


def range_shards(vertices: DataFrame, k: int, exact: bool = True) -> DataFrame:
    """Contiguous key ranges of equal size. exact ranks all keys in one sort; otherwise the range is cut at its exact quantiles, for large data."""
    if exact:
        return vertices.select("vid", (F.ntile(k).over(Window.orderBy("vid")) - 1).cast("int").alias("bucket"))
    cuts = quantile_cuts(vertices, k)
    return vertices.crossJoin(F.broadcast(cuts)).select("vid", F.size(F.filter("c", lambda x: x < F.col("vid"))).alias("bucket"))


def quantile_cuts(vertices: DataFrame, k: int, parts: int = 256) -> DataFrame:
    """One row (c): the keys of ranks ceil(i n / k), i = 1 to k - 1. Approximate quantiles only split the keys into parts: counts of the parts tell in which ones the ranks lie, and those alone are sorted."""
    rough = vertices.agg(F.percentile_approx("vid", [i / parts for i in range(1, parts)], 10_000).alias("_cuts"))
    dealt = vertices.where("vid is not null").crossJoin(F.broadcast(rough)).select("vid", F.size(F.filter("_cuts", lambda x: x < F.col("vid"))).alias("part"))
    ends = Window.orderBy("part")  # as many rows as parts
    held = dealt.groupBy("part").agg(F.count("*").alias("c")).withColumn("hi", F.sum("c").over(ends)).withColumn("n", F.sum("c").over(ends.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)))
    ranks = held.withColumn("i", F.explode(F.sequence(F.lit(1), F.lit(k - 1)))).withColumn("rank", F.expr(f"(i * n + {k - 1}) div {k}"))
    wanted = ranks.where("rank > hi - c and rank <= hi").groupBy("part").agg(F.first(F.col("hi") - F.col("c")).alias("before"), F.collect_list("rank").alias("ranks"))
    place = F.row_number().over(Window.partitionBy("part").orderBy("vid"))
    found = dealt.join(F.broadcast(wanted), "part").withColumn("r", F.col("before") + place).where("array_contains(ranks, r)")
    per = found.select("vid", F.explode(F.filter("ranks", lambda x: x == F.col("r"))))  # several ranks may share a key
    return per.agg(F.array_sort(F.collect_list("vid")).alias("c"))


def truth_shards(vertices: DataFrame, label: str) -> DataFrame:
    """One bucket per value of a column, numbered in its order. Values are few: they are ranked on their own."""
    names = vertices.select(label).distinct().withColumn("bucket", F.row_number().over(Window.orderBy(label)) - 1)
    return vertices.join(F.broadcast(names), label).select("vid", F.col("bucket").cast("int").alias("bucket"))


def clique_graph(edges: DataFrame, max_degree: int | None = None, min_weight: int = 1, top_m: int | None = None, keep: float | None = None, seed: int = 42) -> DataFrame:
    """(u, v, w), u < v: the clique expansion, thinned by a least weight, the top m of each vertex, or a coin whose survivors are reweighted."""
    pairs = pair_weights(edges, max_degree).where(F.col("w") >= min_weight)
    if keep is not None:
        pairs = pairs.where(coin("u", "v", seed) < int(keep * FULL)).withColumn("w", F.round(F.col("w") / keep).cast("long"))
    if top_m is not None:
        ends = pairs.select("u", "v", "w", F.col("u").alias("e")).union(pairs.select("u", "v", "w", F.col("v")))
        rank = F.row_number().over(Window.partitionBy("e").orderBy(F.desc("w"), "u", "v"))
        pairs = ends.withColumn("r", rank).where(F.col("r") <= top_m).select("u", "v", "w").distinct()
    return pairs


def graph_cut(graph: DataFrame, assign: DataFrame) -> DataFrame:
    a, b = assign.select(F.col("vid").alias("u"), F.col("bucket").alias("bu")), assign.select(F.col("vid").alias("v"), F.col("bucket").alias("bv"))
    return graph.join(a, "u").join(b, "v").agg(F.coalesce(F.sum(F.when(F.col("bu") != F.col("bv"), F.col("w"))), F.lit(0)).cast("long").alias("cut"))


def cut_gains(graph: DataFrame, assign: DataFrame) -> DataFrame:
    """(vid, src, dst, gain_fx): weight to the target less weight to the own bucket."""
    both = graph.select(F.col("u").alias("vid"), F.col("v").alias("o"), "w").union(graph.select("v", "u", "w"))
    far = both.join(assign.select(F.col("vid").alias("o"), F.col("bucket").alias("b")), "o").groupBy("vid", "b").agg(F.sum("w").alias("w"))
    own = far.join(assign, "vid").withColumn("here", F.coalesce(F.max(F.when(F.col("b") == F.col("bucket"), F.col("w"))).over(Window.partitionBy("vid")), F.lit(0)))
    return own.where("b <> bucket").select("vid", F.col("bucket").alias("src"), F.col("b").alias("dst"), (F.col("w") - F.col("here")).alias("gain_fx"))


def _all(edges: DataFrame, limit: int) -> DataFrame:
    """All edges as one group, after a look whether the graph is small enough for one task."""
    if edges.select("vid").distinct().limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} vertices")
    return edges.groupBy(F.lit(0).alias("g"))


def _weighted(edges: DataFrame, weights: DataFrame | None) -> DataFrame:
    """Edges with the weight qw of their query, 1 if none are given."""
    return edges.withColumn("qw", F.lit(1).cast("long")) if weights is None else edges.join(weights.select("qid", "qw"), "qid")


def kl_serial(edges: DataFrame, k: int, p: float = 0.5, limit: int = 200, weights: DataFrame | None = None) -> DataFrame:
    """The classical swap heuristic: the best pair at a time while it helps. One task; for graphs of up to limit vertices. weights: (qid, qw) of merged queries."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        queries = [set(g) for _, g in rows.groupby("qid").vid]
        times = rows.groupby("qid").qw.first().tolist()
        vids = sorted(set(rows.vid))
        place = {v: i * k // len(vids) for i, v in enumerate(vids)}

        def cost(touched) -> float:
            total = 0.0
            for q in touched:
                counts: dict[int, int] = {}
                for v in queries[q]:
                    counts[place[v]] = counts.get(place[v], 0) + 1
                total += times[q] * sum(1 - (1 - p) ** c for c in counts.values())
            return total

        of = {v: [q for q, s in enumerate(queries) if v in s] for v in vids}
        while True:
            best = (1e-12, None)
            for i, a in enumerate(vids):
                for b in vids[i + 1 :]:
                    if place[a] != place[b]:
                        touched = set(of[a]) | set(of[b])
                        before = cost(touched)
                        place[a], place[b] = place[b], place[a]
                        gain = before - cost(touched)
                        place[a], place[b] = place[b], place[a]
                        if gain > best[0]:
                            best = (gain, (a, b))
            if best[1] is None:
                break
            a, b = best[1]
            place[a], place[b] = place[b], place[a]
        return pd.DataFrame({"vid": vids, "bucket": [place[v] for v in vids]})

    return _all(_weighted(edges, weights), limit).applyInPandas(run, "vid long, bucket int")


def exhaustive(edges: DataFrame, k: int, eps: float, limit: int = 10, weights: DataFrame | None = None) -> DataFrame:
    """(total): the lowest sum of fanouts over all feasible placements, for up to limit vertices. weights: (qid, qw) of merged queries."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        queries = [list(g) for _, g in rows.groupby("qid").vid]
        times = rows.groupby("qid").qw.first().tolist()
        vids = sorted(set(rows.vid))
        cap = max(int((1 + eps) * len(vids) / k), -(-len(vids) // k))
        best = None
        for choice in product(range(k), repeat=len(vids)):
            if max(choice.count(b) for b in range(k)) <= cap:
                place = dict(zip(vids, choice))
                total = sum(w * len({place[v] for v in q}) for q, w in zip(queries, times))
                best = total if best is None else min(best, total)
        return pd.DataFrame({"total": [best]})

    return _all(_weighted(edges, weights), limit).applyInPandas(run, "total long")
