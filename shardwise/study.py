"""The experiments on their full grids, from the command line: python -m shardwise.study NAME [--sf DIR] [--out FOLDER] ...

Without further arguments a study has the grid that it stands for: all graphs, all k up to half the data vertices, all
methods, the spec's own numbers of iterations. The registered queries of the catalogue run smaller ones.
"""

from __future__ import annotations

import argparse

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import PartitionSpec
from .operators import measures
from .plans import experiments, multidim
from .plans import partition as plans
from .session import session
from .sources import generate, workloads
from .sources.build import prune_trivial

# The grids of the published experiments.
QUALITY_KS, TIME_KS, COMPARE_KS = (2, 8, 32, 128, 512), (32, 512, 8192), (2, 8, 32)
LADDER_KS = (2, 32, 512, 8192, 131072)
PS = tuple(i / 10 for i in range(1, 11))
QUALITY_GRAPHS = ("order_part", "cust_part", "brand_cart", "token_doc", "link_page", "vec_knn", "supp_part", "hour_user")


def _graphs(spark: SparkSession, a, default: tuple[str, ...]) -> dict[str, DataFrame]:
    return {g: workloads.graph(spark, a.sf, g) for g in (a.graphs or default)}


def quality(spark, a) -> DataFrame:
    """Average fanout by method, graph and k, with the excess over the best and the saving against random sharding."""
    grid = experiments.quality_grid(spark, _graphs(spark, a, QUALITY_GRAPHS), a.methods or ("direct", "bisect", "clique_net", "multilevel", "random"), a.k or QUALITY_KS, a.spec, a.timeout)
    return grid.join(experiments.quality_relative(grid).select("graph", "method", "k", "excess", "reduction"), ["graph", "method", "k"], "left")


def runtime(spark, a) -> DataFrame:
    """Run time of straight, bisecting and multilevel runs; what takes longer than the time-out has failed."""
    return experiments.runtime_grid(spark, _graphs(spark, a, ("cust_part", "token_doc")), a.methods or ("direct", "bisect", "multilevel"), a.k or TIME_KS, a.spec, a.timeout or 36_000.0)


def edges(spark, a) -> DataFrame:
    """Time of bisection against the number of edges: a ladder of generated friendships."""
    ladder = {f"friends-{n}": prune_trivial(generate.gen_friendship(spark, n, a.degree)) for n in a.people}
    return experiments.scaling_edges(spark, ladder, a.k or LADDER_KS, a.spec.but(arity=2))


def tasks(spark, a) -> DataFrame:
    """Time of bisection against the number of tasks at once."""
    (graph,) = _graphs(spark, a, ("cust_part",)).values()
    return experiments.scaling_tasks(spark, graph, (1, 2, 4, 8), a.spec.but(k=(a.k or [32])[0], arity=2))


def fetch_probability(spark, a) -> DataFrame:
    """Share of random sharding's fanout that bisection saves, by p and k."""
    out = None
    for name, graph in _graphs(spark, a, ("brand_cart", "token_doc")).items():
        frame = experiments.p_sweep(spark, graph, PS, a.k or QUALITY_KS[:3], a.spec.but(arity=2, lookahead=True)).withColumn("graph", F.lit(name))
        out = frame if out is None else out.unionByName(frame)
    return out


def convergence(spark, a) -> DataFrame:
    """Fanout and moved vertices by iteration of straight runs, p = 0.5 against p = 1."""
    out = None
    for name, graph in _graphs(spark, a, ("token_doc", "cust_part")).items():
        frame = experiments.convergence(spark, graph, (a.k or [8])[0], (0.5, 1.0), a.spec.iterations or 60, a.spec).withColumn("graph", F.lit(name))
        out = frame if out is None else out.unionByName(frame)
    return out


def objectives(spark, a) -> DataFrame:
    """Excess of p = 1 and of the clique-net limit over p = 0.5."""
    return experiments.objective_ablation(spark, _graphs(spark, a, QUALITY_GRAPHS), a.k or COMPARE_KS, a.spec.but(arity=2, lookahead=True))


def exchanges(spark, a) -> DataFrame:
    """The exchange policies, one after the other."""
    (graph,) = _graphs(spark, a, ("brand_cart",)).values()
    return experiments.exchange_ablation(spark, graph, a.spec.but(arity=2, k=(a.k or [8])[0]))


def store(spark, a) -> DataFrame:
    """Sampled traffic on 40 servers: latency by fanout, records at random and partitioned."""
    (graph,) = _graphs(spark, a, ("cust_part",)).values()
    k, everyone = (a.k or [40])[0], graph.select("vid").distinct()
    from .operators.refine import init_random

    placed = {"random": init_random(everyone, k), "partitioned": plans.partition(graph, a.spec.but(k=k, arity=2, lookahead=True)).assign}
    parts = [experiments.sharded_traffic(graph, x, rate=a.rate).withColumn("placement", F.lit(n)).crossJoin(measures.avg_fanout(graph, x).select(F.col("fanout").alias("avg_fanout"))) for n, x in placed.items()]
    return parts[0].unionByName(parts[1])


def dimensions(spark, a) -> DataFrame:
    """Imbalance in each of four dimensions after over-splitting by 2 and by 4."""
    graph = workloads.graph(spark, a.sf, "brand_cart")
    out = None
    for c in (2, 4):
        weights = workloads.part_weights(spark, a.sf)
        got = multidim.partition_multidim(graph, weights, a.spec.but(k=(a.k or [8])[0], arity=2, lookahead=True), c=c)
        frame = multidim.dimension_imbalance(got.assign, weights, got.spec.k).withColumn("c", F.lit(c)).crossJoin(measures.avg_fanout(graph, got.assign).select("fanout"))
        out = frame if out is None else out.unionByName(frame)
    return out


STUDIES = {f.__name__: f for f in (quality, runtime, edges, tasks, fetch_probability, convergence, objectives, exchanges, store, dimensions)}


def main(argv: list[str] | None = None) -> DataFrame:
    p = argparse.ArgumentParser(description=__doc__.splitlines()[0])
    p.add_argument("name", choices=sorted(STUDIES))
    p.add_argument("--sf", default="/root/testdata/sf0.01")
    p.add_argument("--out", help="folder for the results as Parquet")
    p.add_argument("--master")
    p.add_argument("--graphs", nargs="+", choices=sorted(workloads.GRAPHS))
    p.add_argument("--methods", nargs="+", choices=sorted(experiments.METHODS))
    p.add_argument("--k", nargs="+", type=int)
    p.add_argument("--iterations", type=int, help="per level; the defaults are 60 for straight runs and 20 per split")
    p.add_argument("--timeout", type=float, help="seconds of one run")
    p.add_argument("--people", nargs="+", type=int, default=[1000, 10_000, 100_000])
    p.add_argument("--degree", type=int, default=330)
    p.add_argument("--rate", type=float, default=0.5)
    a = p.parse_args(argv)
    a.spec = PartitionSpec(iterations=a.iterations)
    spark = session(master=a.master)
    out = STUDIES[a.name](spark, a)
    if a.out:
        out.write.mode("overwrite").parquet(a.out)
    out.show(1000, truncate=False)
    return out


if __name__ == "__main__":
    main()
