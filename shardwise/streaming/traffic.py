"""Query traffic as streams: windowed fanout under a placement, sessions, kept shares, incremental placement."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import PartitionSpec

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def edge_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Events as they arrive in files: (ts, vid, key); key is the number in the properties."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return events_as_edges(raw)


def events_as_edges(events: DataFrame) -> DataFrame:
    return events.select(F.col("event_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("vid"), F.get_json_object("props", "$.k").cast("long").alias("key"), "value")


def windowed_fanout(stream: DataFrame, assign: DataFrame, window: str = "1 hour", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """Buckets touched in each window, a window being one query; edges later than the watermark are dropped."""
    placed = stream.withWatermark("ts", watermark).join(assign, "vid")
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    per = placed.groupBy(w.alias("w")).agg(F.size(F.collect_set("bucket")).alias("fanout"), F.count("*").alias("events"))
    return per.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "fanout", "events")


def deduplicated(stream: DataFrame, watermark: str = "1 hour") -> DataFrame:
    """One edge per (key, vid) within the watermark."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["key", "vid"])


def session_edges(stream: DataFrame, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """Sessions of users as queries over property keys: (start, vid, members)."""
    per = stream.withWatermark("ts", watermark).groupBy(F.session_window("ts", gap).alias("w"), "vid").agg(F.array_sort(F.collect_set("key")).alias("members"))
    return per.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "vid", "members")


def stateful_share(stream: DataFrame, assign: DataFrame, ttl_ms: int = 3_600_000, watermark: str = "1 hour") -> DataFrame:
    """Counts per (query, bucket) kept as state; a row (qid, fanout) for each query whose fanout changed in a batch. State idle for ttl_ms of event time goes."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    placed = stream.withWatermark("ts", watermark).where("key is not null").join(assign, "vid").select(F.col("key").alias("qid"), "bucket", "ts")

    def update(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        counts = dict(zip(*state.get)) if state.exists else {}
        before, last = len(counts), 0
        for part in rows:
            last = max(last, int(part.ts.max().timestamp() * 1000))
            for bucket, c in part.bucket.value_counts().items():
                counts[int(bucket)] = counts.get(int(bucket), 0) + int(c)
        state.update((list(counts), list(counts.values())))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + ttl_ms)
        if len(counts) != before:
            yield pd.DataFrame({"qid": [key[0]], "fanout": [len(counts)]})

    return placed.groupBy("qid").applyInPandasWithState(update, "qid long, fanout long", "buckets array<int>, counts array<long>", "update", GroupStateTimeout.EventTimeTimeout)


def reply_latency(issued: DataFrame, replied: DataFrame, within: str = "10 minutes", watermark: str = "1 hour") -> DataFrame:
    """issued and replied (event_id, ts): time between a query and its reply, joined within an interval."""
    a = issued.withWatermark("ts", watermark).select(F.col("event_id").alias("a_id"), F.col("ts").alias("sent"))
    b = replied.withWatermark("ts", watermark).select(F.col("event_id").alias("b_id"), F.col("ts").alias("got"))
    near = (F.col("a_id") == F.col("b_id")) & (F.col("got") >= F.col("sent")) & (F.col("got") <= F.col("sent") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select("a_id", (F.unix_micros("got") - F.unix_micros("sent")).alias("micros"))


class IncrementalSink:
    """For foreachBatch: new edges join those seen, and the placement is refined with restraint."""

    def __init__(self, base: DataFrame, spec: PartitionSpec, damp: float = 0.5, penalty: float = 0.25):
        self.assign, self.spec, self.damp, self.penalty, self.edges, self.batches = base, spec, damp, penalty, None, 0

    def __call__(self, batch: DataFrame, number: int) -> None:
        from ..plans.partition import repartition
        from ..session import forget, stored
        from ..sources.build import edges_from

        new = edges_from(batch, "key", "vid")
        edges = stored(new if self.edges is None else self.edges.union(new).distinct(), "stream-edges")
        forget(self.edges)
        self.edges = edges
        if not edges.isEmpty():
            former = self.assign
            self.assign = repartition(edges, former, self.spec, self.damp, self.penalty).assign
            forget(former)
        self.batches += 1
