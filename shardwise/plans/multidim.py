"""Several dimensions of balance: over-split, then merge buckets by their loads."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import PartitionResult, PartitionSpec
from ..session import small, stored
from .partition import partition


def bucket_loads(assign: DataFrame, weights: DataFrame) -> DataFrame:
    """(bucket, d, load) for each dimension d of (vid, dims); vertices without weights count as zero."""
    each = assign.join(weights, "vid", "left").select("bucket", F.posexplode_outer("dims").alias("d", "w"))
    return each.where("d is not null").groupBy("bucket", "d").agg(F.sum("w").alias("load"))


def merge_plan(loads: DataFrame, pieces: int, k: int) -> DataFrame:
    """(bucket, target): pieces in order of their largest relative load go to the target whose largest load stays lowest.

    Serial over at most c * k rows of loads, whatever the number of vertices, so in one task.
    """

    def pack(rows: pd.DataFrame) -> pd.DataFrame:
        table = rows.pivot_table(index="bucket", columns="d", values="load", aggfunc="sum").reindex(range(pieces)).fillna(0.0)
        share = table / table.sum().where(lambda s: s > 0, 1.0) * k  # an even target has 1 in each dimension
        held = [[0.0] * share.shape[1] for _ in range(k)]
        target = {}
        for bucket in share.max(axis=1).sort_values(ascending=False, kind="stable").index:
            own = share.loc[bucket].tolist()
            best = min(range(k), key=lambda j: (max(a + b for a, b in zip(held[j], own)), j))
            held[best] = [a + b for a, b in zip(held[best], own)]
            target[bucket] = best
        return pd.DataFrame({"bucket": list(target), "target": list(target.values())})

    return loads.withColumn("one", F.lit(0)).groupBy("one").applyInPandas(pack, "bucket int, target int")


def partition_multidim(edges: DataFrame, weights: DataFrame, spec: PartitionSpec, c: int = 4) -> PartitionResult:
    """Partition into c * k pieces, then merge them into k buckets that are even in every dimension of weights (vid, dims)."""
    fine = partition(edges, spec.but(k=c * spec.k), vertices=weights)
    plan = merge_plan(bucket_loads(fine.assign, weights), c * spec.k, spec.k)
    merged = fine.assign.join(small(plan, c * spec.k), "bucket").select("vid", F.col("target").alias("bucket"))
    return PartitionResult(stored(merged, "merged"), fine.progress, spec)


def dimension_imbalance(assign: DataFrame, weights: DataFrame, k: int) -> DataFrame:
    """(d, imbalance) per dimension."""
    loads = bucket_loads(assign, weights)
    return loads.groupBy("d").agg(F.round(F.max("load") * k / F.sum("load") - 1, 6).alias("imbalance"))
