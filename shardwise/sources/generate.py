"""Generated graphs, from hash coins: the same whatever the partitioning."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.coin import FULL, coin
from .build import edges_from, friend_edges


def gen_friendship(spark: SparkSession, n: int, avg_degree: int, communities: int = 10, mix: float = 0.1, seed: int = 42, people: DataFrame | None = None) -> DataFrame:
    """People in communities of equal size; each names friends, mostly from its own; friendship goes both ways. people: (id) of those from 0 to n - 1 who name friends, all if not given."""
    size = max(1, n // communities)
    names = (spark.range(n) if people is None else people).select(F.col("id").alias("a"), F.explode(F.sequence(F.lit(1), F.lit(max(1, avg_degree // 2)))).alias("i"))
    own = (F.col("a") - F.col("a") % size) + coin("a", "i", seed) % size
    far = coin("a", "i", seed, 1) % n
    picked = names.select("a", F.when(coin("a", "i", seed, 2) < int(mix * FULL), far).otherwise(F.least(own, F.lit(n - 1))).alias("b"))
    return friend_edges(picked, "a", "b")


def gen_planted(spark: SparkSession, n: int, k: int, queries: int, size: int, noise: float = 0.1, seed: int = 42, asked: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Queries draw their members from one of k groups, a share of the members from anywhere: (edges, truth). asked: (id) of the queries in place of 0 to queries - 1."""
    per = max(1, n // k)
    slots = (spark.range(queries) if asked is None else asked).select(F.col("id").alias("q"), F.explode(F.sequence(F.lit(1), F.lit(size))).alias("i"))
    home = F.col("q") % k
    inside = F.least(home * per + coin("q", "i", seed) % per, F.lit(n - 1))
    member = F.when(coin("q", "i", seed, 1) < int(noise * FULL), coin("q", "i", seed, 2) % n).otherwise(inside)
    truth = spark.range(n).select(F.col("id").alias("vid"), F.least(F.floor(F.col("id") / per), F.lit(k - 1)).cast("int").alias("bucket"))
    return edges_from(slots, "q", member), truth
