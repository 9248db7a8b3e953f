"""Edge lists from and to files, the double layout, and sinks of assignments."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import EDGE
from .build import edges_from


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", q: str = "qid", v: str = "vid", sep: str = "\t") -> DataFrame:
    """kind: parquet, orc, csv (with sep; lines that start with # are comments), json (a record a line) or text ('q v' per line)."""
    if kind == "csv":
        return edges_from(spark.read.csv(path, schema=EDGE, sep=sep, comment="#"), "qid", "vid")
    if kind == "json":
        return edges_from(spark.read.schema(f"`{q}` long, `{v}` long").json(path), q, v)
    if kind == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.col("value").startswith("#") & (F.size(parts) >= 2))
        return edges_from(lines, F.try_element_at(parts, F.lit(1)).try_cast("long"), F.try_element_at(parts, F.lit(2)).try_cast("long"))
    return edges_from(spark.read.format(kind).load(path), q, v)


def write_edges(edges: DataFrame, path: str, kind: str = "parquet", sep: str = "\t") -> None:
    out = edges.select("qid", "vid").write.mode("overwrite")
    if kind == "csv":
        out.csv(path, sep=sep)
    elif kind == "text":
        edges.select(F.concat_ws(" ", "qid", "vid").alias("value")).write.mode("overwrite").text(path)
    else:
        out.format(kind).save(path)


@dataclass(frozen=True)
class Layout:
    """Two bucketed copies of the edges: by query for counting shares, by vertex for summing gains."""

    by_query: str
    by_vertex: str
    buckets: int

    def read(self, spark: SparkSession) -> tuple[DataFrame, DataFrame]:
        return spark.table(self.by_query), spark.table(self.by_vertex)


def write_dual_layout(edges: DataFrame, name: str, num_buckets: int = 64) -> Layout:
    """Each copy is shuffled once here; joins on its key then need no shuffle."""
    layout = Layout(f"{name}_by_query", f"{name}_by_vertex", num_buckets)
    for key, target in (("qid", layout.by_query), ("vid", layout.by_vertex)):
        edges.repartition(num_buckets, key).write.mode("overwrite").bucketBy(num_buckets, key).sortBy(key).saveAsTable(target)
    return layout


def write_assignment(assign: DataFrame, path: str, level: int | None = None, iteration: int | None = None) -> None:
    """A snapshot; with level and iteration as a partition of a history, of which a rerun replaces its own part only."""
    if level is None:
        assign.write.mode("overwrite").parquet(path)
    else:
        tagged = assign.withColumn("level", F.lit(level)).withColumn("iter", F.lit(iteration))
        tagged.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("level", "iter").parquet(path)


def read_assignment(spark: SparkSession, path: str, level: int | None = None, iteration: int | None = None) -> DataFrame:
    df = spark.read.parquet(path)
    if level is not None:
        df = df.where((F.col("level") == level) & (F.col("iter") == iteration))
    return df.select("vid", "bucket")
