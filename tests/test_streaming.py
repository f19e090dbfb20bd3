import tempfile

from pyspark.sql import functions as F

from deltamatch import workloads
from deltamatch.operators import engines
from deltamatch.plans.query import pattern
from deltamatch.sources import graphs, streams
from deltamatch.streaming import live


def _batches(spark, updates, folder, parts):
    rows = updates.where("seq > 0").select("op", "src", "dst", F.timestamp_seconds("seq").alias("ts"), F.col("seq").alias("event_id"))
    last = rows.agg(F.max("event_id")).first()[0]
    for i in range(parts):
        part = rows.where((F.col("event_id") > last * i // parts) & (F.col("event_id") <= last * (i + 1) // parts))
        part.coalesce(1).write.mode("append").parquet(folder)


def test_live_matches_equal_the_batch_plan_and_replays_change_nothing(spark, sf):
    edges = graphs.copurchase_edges(spark, sf).cache()
    vertices = graphs.part_vertices(spark, sf, 4).cache()
    updates = streams.mixed_stream(edges).cache()
    folder = tempfile.mkdtemp()
    _batches(spark, updates, f"{folder}/in", 3)
    matcher = live.LiveMatcher(spark, [pattern("triangle")], vertices, f"{folder}/state", gated=True)
    matcher.load(updates.where("seq = 0"))
    matcher.start(live.read_updates(spark, f"{folder}/in"), f"{folder}/checkpoint").awaitTermination()
    versions = streams.edge_versions(updates).cache()
    order = {r.seq: i + 1 for i, r in enumerate(updates.where("seq > 0").select("seq").orderBy("seq").collect())}
    want = sorted((order[r.seq], r.sign, r.matches) for s in (1, -1) for r in engines.match_counts(engines.delta([pattern("triangle")], versions, vertices, sign=s)).collect())
    got = sorted((r.seq, r.sign, r.matches) for r in matcher.matches().collect())
    assert got == want
    last = max(b for b, _ in matcher._committed())
    rows = spark.read.schema(live.UPDATES).parquet(f"{folder}/in")
    before = sorted(map(tuple, matcher.state()[0].collect()))
    parts = [r.f for r in rows.select(F.input_file_name().alias("f")).distinct().collect()]
    newest = max(parts, key=lambda f: spark.read.schema(live.UPDATES).parquet(f).agg(F.max("event_id")).first()[0])
    matcher.process(spark.read.schema(live.UPDATES).parquet(newest), last)
    assert sorted(map(tuple, matcher.state()[0].collect())) == before
    assert sorted((r.seq, r.sign, r.matches) for r in matcher.matches().collect()) == want


def test_event_edges_and_counters(spark, sf):
    folder = tempfile.mkdtemp()
    events = spark.read.parquet(f"{sf}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    events.coalesce(1).write.mode("append").parquet(f"{folder}/events")
    stream = spark.readStream.schema(events.schema).parquet(f"{folder}/events")
    query = live.event_edges(stream).writeStream.format("memory").queryName("live_edges").outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{folder}/c1").start()
    query.awaitTermination()
    got = {(r.src, r.dst) for r in spark.table("live_edges").collect()}
    want = {(r.src, r.dst) for r in graphs.temporal_edges(spark, sf).collect()}
    assert got == want
    spark.createDataFrame([(1, i) for i in range(1, 8)] + [(2, 1)], "center bigint, seq bigint").coalesce(1).write.parquet(f"{folder}/touch")
    touches = spark.readStream.schema("center bigint, seq bigint").parquet(f"{folder}/touch")
    query = live.touch_counters(touches, 2).writeStream.format("memory").queryName("live_touch").outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{folder}/c2").start()
    query.awaitTermination()
    rows = spark.table("live_touch").collect()
    assert sorted((r.seq, r.touch) for r in rows if r.center == 1) == [(i, i) for i in range(1, 8)]
    assert [r.seq for r in sorted(rows) if r.refresh and r.center == 1] == [3, 6]


def test_twin_users_count_like_each_user_alone(spark, tmp_path):
    """Triangles over classes of users with equal events against every user by itself; no class is joined with itself."""
    kinds = ["a", "a", "a", "b", "b", "c", None]
    rows = [(None if u == 9 else 10 * copy + u, kinds[(u + i) % 7], f"p{i % 2}", 600 * ((7 * u + 31 * i) % 150) * (1 + i)) for copy in range(4) for u in range(10) for i in range(6) if copy < 3 or u < 4]
    rows += rows[:5]
    events = spark.createDataFrame(rows, "user_id bigint, event_type string, props string, s bigint").selectExpr("user_id", "event_type", "props", "CASE WHEN s > 0 THEN timestamp_seconds(s) END AS ts")
    events.write.parquet(f"{tmp_path}/events.parquet")
    versions = streams.edge_versions(streams.expiring_stream(graphs.temporal_edges(spark, str(tmp_path)))).cache()
    want = engines.lifetimes(pattern("triangle"), versions, spark.createDataFrame([], "id bigint, label int")).count()
    classes, edges = graphs.temporal_twins(spark, str(tmp_path))
    assert {r.n for r in classes.collect()} == {3, 4} and edges.count() < versions.count() / 5
    assert [tuple(r) for r in workloads.temporal_triangles(spark, str(tmp_path)).collect()] == [(want,)] and want > 500
