"""A session with the settings that the engine is tuned for, and checked broadcasts and stored tables."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of a small table (a bucket, a pair of buckets) up to which it is broadcast.
BROADCAST_ROWS = 1_000_000


def session(app: str = "shardwise", master: str | None = None, shuffle_partitions: int | None = None) -> SparkSession:
    b = SparkSession.builder.appName(app).config("spark.sql.adaptive.enabled", "true").config("spark.sql.adaptive.skewJoin.enabled", "true").config("spark.sql.session.timeZone", "UTC")
    if master:
        b = b.master(master)
    if shuffle_partitions:
        b = b.config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    return b.getOrCreate()


def small(df: DataFrame, rows: int) -> DataFrame:
    """Broadcast a side whose row count is known to be within the limit; leave a shuffle join otherwise."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir, which all executors share; a temporary folder only where none is set on a local master, an error elsewhere."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        done = spark.sparkContext._jsc.sc().getCheckpointDir()
        if done.isDefined():
            found = done.get()
        elif not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        else:
            found = "file://" + tempfile.mkdtemp(prefix="shardwise-")
            spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def stored(df: DataFrame, label: str) -> DataFrame:
    """Cut the lineage by a table in the shared folder, which outlives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/tables/{label}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    back._stored_path = path
    return back


def forget(*frames: DataFrame | None) -> None:
    """Delete stored tables that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_stored_path", None)
        if path:
            context = df.sparkSession.sparkContext
            where = context._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(context._jsc.hadoopConfiguration()).delete(where, True)
