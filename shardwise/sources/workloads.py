"""Query-data graphs on the given tables. Every builder takes (spark, sf_dir) and gives unpruned edges."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .build import dual, edges_from, prune_trivial


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def order_part(spark, sf):
    return edges_from(table(spark, sf, "lineitem"), "l_orderkey", "l_partkey")


def _bought(spark, sf):
    lines = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey")
    return lines.join(table(spark, sf, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey", "o_orderdate"), "l_orderkey")


def cust_part(spark, sf):
    return edges_from(_bought(spark, sf), "o_custkey", "l_partkey")


def supp_part(spark, sf):
    return edges_from(table(spark, sf, "lineitem"), "l_suppkey", "l_partkey")


def hour_user(spark, sf):
    hours = F.expr("unix_seconds(cast(date_trunc('HOUR', ts) as timestamp)) div 3600")
    return edges_from(table(spark, sf, "events"), hours, "user_id")


def brand_cart(spark, sf):
    """Parts of one brand in a customer's orders; each query lies in one of 25 brands."""
    part = table(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), F.regexp_extract("p_brand", "([0-9]+)", 1).cast("long").alias("brand"))
    return edges_from(_bought(spark, sf).join(part, "l_partkey"), F.col("o_custkey") * 100 + F.col("brand"), "l_partkey")


def _words(df: DataFrame, key: str) -> DataFrame:
    words = df.select(F.col(key).alias("k"), F.explode(F.array_distinct(F.split(F.lower("text"), "[^a-z0-9]+"))).alias("w")).where("w <> ''")
    return words.select("k", F.xxhash64("w").alias("w"))


def token_doc(spark, sf):
    return edges_from(_words(table(spark, sf, "documents"), "doc_id"), "w", "k")


def conv_token(spark, sf):
    return edges_from(_words(table(spark, sf, "conversations"), "conv_id"), "k", "w")


def page_link(spark, sf):
    links = table(spark, sf, "pages").select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)")).alias("href"))
    return edges_from(links, "page_id", F.xxhash64("href"))


def vec_knn(spark, sf, k: int = 10, rows: int = 1024):
    """Each vector queries its k nearest by cosine, ties to the smaller id: blocks of vectors against blocks."""
    vectors = table(spark, sf, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    blocks = max(1, -(-vectors.count() // rows))
    dealt = vectors.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks).cast("long")))
    other = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
    left, right = dealt.withColumn("c", other), dealt.withColumnRenamed("b", "c").withColumn("b", other)

    def near(a: pa.Table, b: pa.Table) -> pa.Table:
        ia, ib = a.column("vec_id").to_numpy(), b.column("vec_id").to_numpy()
        if not len(ia) or not len(ib):
            return pa.table({"qid": pa.array([], pa.int64()), "vid": pa.array([], pa.int64()), "sim": pa.array([], pa.float64())})
        unit = lambda t: (lambda m: m / np.linalg.norm(m, axis=1, keepdims=True))(np.array(t.column("x").to_pylist(), float))
        s = np.round(unit(a) @ unit(b).T, 6)
        s[ia[:, None] == ib[None, :]] = -np.inf
        top = np.lexsort((np.broadcast_to(ib, s.shape), -s), axis=1)[:, :k]
        q, v, x = np.repeat(ia, top.shape[1]), ib[top.ravel()], np.take_along_axis(s, top, 1).ravel()
        keep = np.isfinite(x)
        return pa.table({"qid": q[keep], "vid": v[keep], "sim": x[keep]})

    parts = left.groupBy("b", "c").cogroup(right.groupBy("b", "c")).applyInArrow(near, "qid long, vid long, sim double")
    ranked = parts.withColumn("r", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("sim"), "vid")))
    return edges_from(ranked.where(F.col("r") <= k), "qid", "vid")


def order_type(spark, sf):
    """Kinds of parts that an order has, numbered in the order of their names: few data, for searches of all placements."""
    part = table(spark, sf, "part").select(F.col("p_partkey").alias("l_partkey"), "p_type")
    kinds = part.select("p_type").distinct().withColumn("kind", F.row_number().over(Window.orderBy("p_type")) - 1)
    lines = table(spark, sf, "lineitem").select("l_orderkey", "l_partkey").join(part.join(F.broadcast(kinds), "p_type"), "l_partkey")
    return edges_from(lines, "l_orderkey", "kind")


def part_weights(spark, sf) -> DataFrame:
    """(vid, dims) of the parts: one each, size, price, lines they are on."""
    lines = table(spark, sf, "lineitem").groupBy(F.col("l_partkey").alias("vid")).agg(F.count("*").cast("double").alias("n"))
    weights = table(spark, sf, "part").select(F.col("p_partkey").alias("vid"), "p_size", "p_retailprice").join(lines, "vid", "left")
    return weights.select("vid", F.array(F.lit(1.0), F.col("p_size").cast("double"), "p_retailprice", F.coalesce("n", F.lit(0.0))).alias("dims"))


def toy_shard(spark, sf=None):
    """Three queries over six records."""
    return _literal(spark, {1: (1, 2, 6), 2: (1, 2, 3, 4), 3: (4, 5, 6)})


def toy_trap(spark, sf=None):
    """Three queries over eight records in which no single move or swap lowers the plain fanout."""
    return _literal(spark, {1: (1, 2, 5, 6), 2: (3, 4, 5, 6), 3: (3, 4, 7, 8)})


def _literal(spark, queries: dict[int, tuple[int, ...]]) -> DataFrame:
    return spark.createDataFrame([(q, v) for q, vs in queries.items() for v in vs], "qid long, vid long")


GRAPHS: dict[str, Callable[..., DataFrame]] = {
    "order_part": order_part,
    "cust_part": cust_part,
    "part_cust": lambda s, d: dual(cust_part(s, d)),
    "supp_part": supp_part,
    "hour_user": hour_user,
    "brand_cart": brand_cart,
    "token_doc": token_doc,
    "doc_token": lambda s, d: dual(token_doc(s, d)),
    "conv_token": conv_token,
    "page_link": page_link,
    "link_page": lambda s, d: dual(page_link(s, d)),
    "vec_knn": vec_knn,
}


def graph(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """Edges of a graph without queries of one member."""
    return prune_trivial(GRAPHS[key](spark, sf_dir))
