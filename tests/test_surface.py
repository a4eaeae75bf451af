"""Sources, plans, streams and SQL names."""

from __future__ import annotations

import datetime as dt

import pytest
from pyspark.sql import functions as F

from attrgraph import streaming
from attrgraph.functions.sql import register, register_graph
from attrgraph.operators import diffusion, graph
from attrgraph.plans import advise, diffuse_pruned
from attrgraph.sources import planted, read, read_edge_list, read_edges, table, write_edges

DATA = "/root/testdata/sf0.001"


def ring(spark, n=60):
    return graph.from_edges(spark.createDataFrame([(i, (i + 1) % n) for i in range(n)], "a long, b long")).kept()


def test_layout_prunes_buckets_and_gives_the_same_diffusion(spark, tmp_path):
    g = ring(spark)
    path = f"{tmp_path}/edges"
    write_edges(g, path, 16)
    plan = read_edges(spark, path, [3]).edges._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in plan and "src_bucket" in plan.split("PartitionFilters: [")[1].split("]")[0]
    start = diffusion.start_unit(spark.createDataFrame([(5,)], "seed_id long"))
    state, log = diffuse_pruned(spark, path, g.degrees, start, eps=0.01, buckets=16)
    plain = {r.node_id: r.reserve for r in diffusion.diffuse(g, start, eps=0.01, strategy="threshold").collect()}
    assert {r.node_id: r.reserve for r in state.collect()} == pytest.approx(plain)
    assert log[0]["buckets"] == 1 and max(x["buckets"] for x in log) < 16
    assert advise(1e-3, 0.8, 1, 64).broadcast and not advise(1e-8, 0.8, 500, 64).broadcast


def test_scans_read_only_what_they_need(spark):
    plan = table(spark, DATA, "lineitem", ["l_orderkey", "l_partkey"]).where("l_partkey = 3")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_partkey), EqualTo(l_partkey,3)]" in plan and "l_comment" not in plan and "l_quantity" not in plan


def test_formats(spark, tmp_path):
    (tmp_path / "edges.txt").write_text("# a comment\n1 2\n2 3 0.5\nbad line\n\n")
    assert sorted((r.src, r.dst, r.w) for r in read_edge_list(spark, str(tmp_path / "edges.txt")).edges.where("src < dst").collect()) == [(1, 2, 1.0), (2, 3, 0.5)]
    rows = spark.createDataFrame([(1, "x")], "a long, b string")
    for kind in ("csv", "json", "orc"):
        rows.write.format(kind).save(f"{tmp_path}/{kind}")
        assert read(spark, f"{tmp_path}/{kind}", kind, "a long, b string").collect() == rows.collect()
    planted.register(spark)
    made = spark.read.format("planted_partition").option("nodes", 200).option("groups", 4).option("inside", 0.9).load()
    share = made.agg(F.avg((F.col("b") % 4 == F.col("group")).cast("int"))).first()[0]
    assert made.count() > 500 and share > 0.85


def test_sql_names(spark):
    register(spark)
    assert spark.sql("select vec_dot(array(1d, 2d), array(3d, 4d)) as v").first().v == 11
    g = ring(spark, 12)
    register_graph(spark, g)
    near = {r.node_id: r.hop for r in spark.sql("select * from neighbors_within(0, 2)").collect()}
    assert near == {0: 0, 1: 1, 11: 1, 2: 2, 10: 2}
    own = {r.node_id: (r.reserve, r.residual) for r in spark.sql("select * from diffuse_local(0, 0.8, 0.01)").collect()}
    start = diffusion.start_unit(spark.createDataFrame([(0,)], "seed_id long"))
    for r in diffusion.diffuse(g, start, eps=0.01, strategy="threshold").collect():
        assert own[r.node_id] == (pytest.approx(r.reserve), pytest.approx(r.residual))


def test_streams_equal_batches_and_drop_late_rows(spark, tmp_path):
    events = table(spark, DATA, "events").where("ts < '2024-01-03'")
    rows = events.orderBy("ts").collect()
    half = len(rows) // 2
    for i, part in enumerate((rows[:half], rows[half:])):
        spark.createDataFrame(part, events.schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in/{i}")
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/in/*")
    path = f"{tmp_path}/edges"
    sink = streaming.merge_snapshot(path)
    edges = streaming.timed_events(stream)

    def handle(batch, number):
        sink(streaming.window_edges(batch, "1 minute").select("a", "b"), number)

    q = edges.writeStream.foreachBatch(handle).option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start()
    q.awaitTermination()
    whole = {(r.a, r.b) for r in streaming.window_edges(streaming.timed_events(spark.createDataFrame(rows, events.schema)), "1 minute").collect()}
    got = {(r.a, r.b) for r in streaming.read_snapshot(spark, path).collect()}
    assert got <= whole and len(whole) - len(got) <= 1  # a minute that the two files share
    counts = streaming.window_activity(streaming.timed_events(stream), "1 hour")
    q = counts.writeStream.format("memory").queryName("activity").outputMode("complete").option("checkpointLocation", f"{tmp_path}/cp2").trigger(availableNow=True).start()
    q.awaitTermination()
    assert {(r.start, r.user_id, r.n) for r in spark.table("activity").collect()} == {(r.start, r.user_id, r.n) for r in streaming.window_activity(streaming.timed_events(events)).collect()}


def test_late_rows(spark, tmp_path):
    base = dt.datetime(2024, 1, 1, 12)
    schema = "event_id long, ts timestamp, user_id long, value double"
    batches = [[(1, base, 7, 1.0)], [(2, base + dt.timedelta(hours=3), 7, 1.0)], [(6, base + dt.timedelta(hours=3, minutes=2), 7, 1.0)], [(3, base + dt.timedelta(minutes=5), 7, 1.0), (4, base + dt.timedelta(hours=3, minutes=1), 7, 1.0)], [(5, base + dt.timedelta(hours=9), 7, 1.0)]]
    for i, b in enumerate(batches):
        spark.createDataFrame(b, schema).coalesce(1).write.parquet(f"{tmp_path}/late/{i}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/late/*")
    q = streaming.window_activity(streaming.timed_events(stream)).writeStream.format("memory").queryName("late").outputMode("append").option("checkpointLocation", f"{tmp_path}/cp3").trigger(availableNow=True).start()
    q.awaitTermination()
    out = {r.start.hour: r.n for r in spark.table("late").collect()}
    assert out == {12: 1, 15: 3}  # event 3 came after its window had closed


def test_running_histograms_and_affected_seeds(spark, tmp_path):
    events = table(spark, DATA, "events")
    events.limit(300).coalesce(1).write.parquet(f"{tmp_path}/h/0")
    stream = spark.readStream.schema(events.schema).parquet(f"{tmp_path}/h/*")
    q = streaming.running_histograms(stream).writeStream.format("memory").queryName("hist").outputMode("update").option("checkpointLocation", f"{tmp_path}/cp4").trigger(availableNow=True).start()
    q.awaitTermination()
    want = {(r.user_id, r.event_type): r["count"] for r in spark.read.parquet(f"{tmp_path}/h/0").groupBy("user_id", "event_type").count().collect()}
    assert {(r.user_id, r.attr): r.value for r in spark.table("hist").collect()} == want
    supports = spark.createDataFrame([(1, 5), (1, 6), (2, 9)], "seed_id long, node_id long")
    assert [r.seed_id for r in streaming.affected_seeds(supports, spark.createDataFrame([(6, 100)], "a long, b long")).collect()] == [1]


def test_as_of_join(spark):
    t = lambda m: dt.datetime(2024, 1, 1, 0, m)
    labels = spark.createDataFrame([(1, t(1), "a"), (1, t(5), "b")], "user_id long, ts timestamp, label string")
    events = spark.createDataFrame([(10, 1, t(0)), (11, 1, t(1)), (12, 1, t(4)), (13, 1, t(9)), (14, 2, t(9))], "event_id long, user_id long, ts timestamp")
    assert {r.event_id: r.label for r in streaming.label_before(events, labels).collect()} == {10: None, 11: "a", 12: "a", 13: "b", 14: None}


def test_entry_and_catalog(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
