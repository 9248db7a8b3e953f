"""A generic multilevel partitioner as a stand-in for external tools, and local search on a weighted graph's cut."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.coin import coin
from ..model import PartitionResult, PartitionSpec
from ..operators import baselines, refine
from ..session import forget, stored
from .partition import partition


def coarsen(edges: DataFrame, max_degree: int = 64, seed: int = 42) -> DataFrame:
    """(vid, coarse): vertices whose heaviest common-query partner prefers them too become one."""
    pairs = baselines.clique_graph(edges, max_degree=max_degree)
    both = pairs.select("u", "v", "w").union(pairs.select("v", "u", "w"))
    order = Window.partitionBy("u").orderBy(F.desc("w"), coin(F.least("u", "v"), F.greatest("u", "v"), seed), "v")
    first = stored(both.withColumn("r", F.row_number().over(order)).where("r = 1").select("u", "v"), "heaviest")
    mutual = first.alias("a").join(first.alias("b"), (F.col("a.u") == F.col("b.v")) & (F.col("a.v") == F.col("b.u"))).select(F.col("a.u").alias("vid"), F.least("a.u", "a.v").alias("coarse"))
    return edges.select("vid").distinct().join(mutual, "vid", "left").select("vid", F.coalesce("coarse", "vid").alias("coarse"))


def multilevel(edges: DataFrame, spec: PartitionSpec, coarsest: int = 200, levels: int = 4) -> PartitionResult:
    """Coarsen, partition the coarse graph, project back and refine at each level."""
    maps, graphs = [], [edges]
    while len(maps) < levels and graphs[-1].select("vid").distinct().count() > max(coarsest, 4 * spec.k):
        matched = stored(coarsen(graphs[-1], seed=spec.seed + len(maps)), "coarse")
        maps.append(matched)
        graphs.append(stored(graphs[-1].join(matched, "vid").select("qid", F.col("coarse").alias("vid")).distinct(), "coarse-edges"))
    result = partition(graphs[-1], spec)
    assign, progress = result.assign, list(result.progress)
    for graph, matched in zip(graphs[-2::-1], maps[::-1]):
        fine = stored(matched.join(assign.select(F.col("vid").alias("coarse"), "bucket"), "coarse").select("vid", "bucket"), "projected")
        got = partition(graph, spec.but(arity=None, iterations=min(spec.rounds, 4)), start=fine)
        forget(fine, assign)
        assign, progress = got.assign, progress + got.progress
    forget(*maps, *graphs[1:])
    return PartitionResult(assign, progress, spec)


def cut_refine(graph: DataFrame, spec: PartitionSpec) -> PartitionResult:
    """Local search on the weighted edge cut of an explicit graph (u, v, w), with the same exchange of coins."""
    vertices = graph.select(F.col("u").alias("vid")).union(graph.select("v")).distinct()
    assign = stored(refine.init_random(vertices, spec.k, spec.seed), "cut")
    best, lowest, log = assign, baselines.graph_cut(graph, assign).first()["cut"], []
    n = vertices.count()
    for turn in range(1, spec.rounds + 1):
        gains = baselines.cut_gains(graph, assign)
        proposals = gains.groupBy("vid", "src").agg(F.max_by(F.struct("dst", "gain_fx"), F.struct("gain_fx", -F.col("dst"))).alias("b")).select("vid", "src", "b.dst", "b.gain_fx").where("gain_fx > 0")
        moves = refine.accepted(proposals, refine.swap_probability(refine.exchange_matrix(proposals)), spec.seed, 1, turn, spec.damp, rows=min(spec.k**2, n))
        nxt = stored(refine.apply_moves(assign, moves), "cut")
        moved = nxt.where("moved").count()
        nxt_state = nxt.select("vid", "bucket")
        nxt_state._stored_path = nxt._stored_path
        cut = baselines.graph_cut(graph, nxt_state).first()["cut"]
        log.append({"level": 1, "iter": turn, "moved": moved, "moved_frac": moved / max(n, 1), "fanout": float("nan"), "pfanout": float(cut), "shuffle_rows": 0})
        if assign is not best:
            forget(assign)
        assign = nxt_state
        if cut < lowest:
            forget(best)
            best, lowest = assign, cut
        if moved == 0:
            break
    if assign is not best:
        forget(assign)
    return PartitionResult(best, log, spec)
