"""Edges of query-data graphs from tables, and the forms a graph can take."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _column(x: str | Column) -> Column:
    return F.col(x) if isinstance(x, str) else x


def edges_from(df: DataFrame, q: str | Column, v: str | Column) -> DataFrame:
    """(qid, vid), each pair once; rows with a null end are no edges."""
    return df.select(_column(q).cast("long").alias("qid"), _column(v).cast("long").alias("vid")).where("qid is not null and vid is not null").dropDuplicates(["qid", "vid"])


def prune_trivial(edges: DataFrame, min_degree: int = 2) -> DataFrame:
    """Without queries of fewer members: they touch one bucket wherever it is."""
    kept = edges.groupBy("qid").agg(F.count("*").alias("_d")).where(F.col("_d") >= min_degree)
    return edges.join(kept.select("qid"), "qid", "left_semi")


def to_hyperedges(edges: DataFrame) -> DataFrame:
    return edges.groupBy("qid").agg(F.array_sort(F.collect_set("vid")).alias("members"))


def from_hyperedges(hyperedges: DataFrame) -> DataFrame:
    return hyperedges.select("qid", F.explode("members").alias("vid")).dropDuplicates(["qid", "vid"])


def dual(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("vid").alias("qid"), F.col("qid").alias("vid"))


def friend_edges(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Each person is a query over friends and a datum: both directions of every pair."""
    both = pairs.select(F.col(a).alias("x"), F.col(b).alias("y")).union(pairs.select(F.col(b), F.col(a)))
    return edges_from(both.where("x <> y"), "x", "y")


def graph_stats(edges: DataFrame, approx: bool = False) -> DataFrame:
    """One row: queries, data vertices, edges, largest and average query degree."""
    count = F.approx_count_distinct if approx else F.count_distinct
    degrees = edges.groupBy("qid").agg(F.count("*").alias("d"))
    left = degrees.agg(F.count("*").alias("queries"), F.coalesce(F.sum("d"), F.lit(0)).alias("edges"), F.max("d").alias("max_degree"), F.round(F.avg("d"), 6).alias("avg_degree"))
    return left.crossJoin(edges.agg(count("vid").alias("data"))).select("queries", "data", "edges", "max_degree", "avg_degree")


def collapse_queries(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Queries with equal members as one with a weight: (edges, (qid, qw)). Equality is checked on the members, not on a hash alone."""
    sets = edges.groupBy("qid").agg(F.array_sort(F.collect_list("vid")).alias("m"))
    merged = sets.withColumn("h", F.xxhash64("m")).groupBy("h", "m").agg(F.min("qid").alias("qid"), F.count("*").alias("qw"))
    return merged.select("qid", F.explode("m").alias("vid")), merged.select("qid", "qw")


def sample_queries(edges: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """Whole queries with a hash coin, so a query is in or out with all its members."""
    from ..functions.coin import FULL, coin

    return edges.where(coin("qid", seed) < int(rate * FULL))


def encode_keys(df: DataFrame, column: str, out: str) -> DataFrame:
    """64-bit ids of string keys; unique_keys() tells whether two keys share one."""
    return df.withColumn(out, F.xxhash64(column))


def unique_keys(df: DataFrame, column: str, out: str) -> DataFrame:
    """Ids that stand for more than one key (expected to be empty)."""
    return df.select(column, out).distinct().groupBy(out).agg(F.count("*").alias("n")).where("n > 1")
