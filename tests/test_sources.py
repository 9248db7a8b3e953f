from shardwise.sources import formats, workloads
from shardwise.streaming import traffic


def pairs(df):
    return sorted(map(tuple, df.select("qid", "vid").collect()))


def test_formats_round_trip(spark, tmp_path):
    edges = workloads.toy_shard(spark)
    for kind in ("parquet", "orc", "json", "csv", "text"):
        path = str(tmp_path / kind)
        formats.write_edges(edges, path, kind)
        assert pairs(formats.read_edges(spark, path, kind)) == pairs(edges)


def test_text_lists_skip_comments_and_bad_lines(spark, tmp_path):
    (tmp_path / "g.txt").write_text("# a comment\n1 2\n1\tx\n\n3 4 5\n")
    assert pairs(formats.read_edges(spark, str(tmp_path / "g.txt"), "text")) == [(1, 2), (3, 4)]


def test_dual_layout_joins_without_shuffle(spark):
    edges = workloads.toy_shard(spark)
    layout = formats.write_dual_layout(edges, "toy_layout", 2)
    by_query, by_vertex = layout.read(spark)
    assert pairs(by_query) == pairs(by_vertex) == pairs(edges)
    plan = by_query.join(spark.table(layout.by_query).withColumnRenamed("vid", "other"), "qid").hint("merge")._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning" not in plan
    for t in (layout.by_query, layout.by_vertex):
        spark.sql(f"DROP TABLE {t}")


def test_assignment_history(spark, tmp_path):
    path = str(tmp_path / "h")
    a = spark.createDataFrame([(1, 0), (2, 1)], "vid long, bucket int")
    formats.write_assignment(a, path, 1, 1)
    formats.write_assignment(a.where("vid = 1"), path, 1, 2)
    formats.write_assignment(a.where("vid = 1"), path, 1, 2)
    assert formats.read_assignment(spark, path, 1, 1).count() == 2
    assert formats.read_assignment(spark, path, 1, 2).count() == 1


def test_stateful_share_counts_buckets(spark, sf, tmp_path):
    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props").limit(200)
    events.coalesce(1).write.parquet(str(tmp_path / "in"))
    assign = spark.createDataFrame([(u, u % 3) for u in range(1, 2000)], "vid long, bucket int")
    out = traffic.stateful_share(traffic.edge_stream(spark, str(tmp_path / "in")), assign)
    run = out.writeStream.format("memory").queryName("fan").outputMode("update").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    run.awaitTermination()
    got = {r.qid: r.fanout for r in spark.table("fan").collect()}
    edges = traffic.events_as_edges(events).join(assign, "vid").select("key", "bucket").distinct().groupBy("key").count()
    assert got == {r.key: r["count"] for r in edges.collect()}


def test_incremental_sink_refines_with_each_batch(spark, sf, tmp_path):
    from shardwise.model import PartitionSpec
    from shardwise.operators import measures, refine

    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    events.repartition(2).write.parquet(str(tmp_path / "in"))
    users = events.selectExpr("user_id as vid").distinct()
    sink = traffic.IncrementalSink(refine.init_random(users, 2), PartitionSpec(k=2, iterations=1))
    run = traffic.edge_stream(spark, str(tmp_path / "in")).writeStream.foreachBatch(sink).option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert sink.batches == 2
    assert sink.assign.count() == users.count()
    assert sum(r["size"] for r in measures.bucket_sizes(sink.assign, 2).collect()) == users.count()


def test_replies_join_their_queries_in_time(spark, tmp_path):
    from pyspark.sql import functions as F

    rows = spark.range(6).select(F.col("id").alias("event_id"), F.timestamp_seconds(F.lit(1_700_000_000) + F.col("id") * 60).alias("ts"))
    rows.coalesce(1).write.parquet(str(tmp_path / "a"))
    rows.select("event_id", (F.col("ts") + F.expr("INTERVAL 1 SECOND") * F.when(F.col("event_id") < 4, 5).otherwise(5000)).alias("ts")).coalesce(1).write.parquet(str(tmp_path / "b"))
    schema = "event_id long, ts timestamp"
    out = traffic.reply_latency(spark.readStream.schema(schema).parquet(str(tmp_path / "a")), spark.readStream.schema(schema).parquet(str(tmp_path / "b")))
    run = out.writeStream.format("memory").queryName("replies").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    run.awaitTermination()
    assert sorted(map(tuple, spark.table("replies").collect())) == [(i, 5_000_000) for i in range(4)]


def test_sql_surface(spark):
    from shardwise.functions.sqlapi import pfanout_agg, register
    from shardwise.operators import measures

    edges = workloads.toy_shard(spark)
    assign = spark.createDataFrame([(v, int(v > 3)) for v in range(1, 7)], "vid long, bucket int")
    register(spark, edges, assign)
    assert spark.sql("SELECT round(sum(pf_term(c, 0.5D)), 6) FROM (SELECT count(*) AS c FROM edge JOIN assign USING (vid) GROUP BY qid, bucket)").first()[0] == 3.5
    got = measures.share(edges, assign).groupBy("qid").agg(pfanout_agg(0.5)("cnt").alias("x")).collect()
    assert {r.qid: r.x for r in got} == {1: 1.25, 2: 1.375, 3: 0.875}
