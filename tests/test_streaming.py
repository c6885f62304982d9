"""Streams against batches."""

from starwatch import streaming
from starwatch.plans.patterns import Patterns, parse
from starwatch.sources import io, synth

REC = io.RECORD


def records(spark):
    rows = [("2024-01-01 00:00:01", "+", 1, 2, 1, 2, 1), ("2024-01-01 00:00:02", "+", 2, 3, 2, 1, 1), ("2024-01-01 00:00:03", "+", 1, 3, 1, 1, 1), ("2024-01-01 00:00:04", "-", 1, 3, 1, 1, 1)]
    return spark.createDataFrame(rows, "ts string, op string, u long, v long, u_label int, v_label int, elabel int").selectExpr("CAST(ts AS TIMESTAMP) AS ts", "op", "u", "v", "u_label", "v_label", "elabel")


def test_stream_monitor(spark, tmp_path):
    src = f"{tmp_path}/in"
    records(spark).limit(3).coalesce(1).write.parquet(src)
    patterns = Patterns([parse("tri", "a:1-b:2, b-c:1, a-c")])
    vertices = spark.createDataFrame([], "v long, label int")
    m = streaming.StreamMonitor(spark, patterns, vertices)
    m.start(io.stream_updates(spark, src), f"{tmp_path}/cp").awaitTermination()
    assert m.monitor.answers().count() == 2
    m.epoch(records(spark).limit(3), 0)  # a repeated batch is skipped
    assert m.monitor.answers().count() == 2
    m.epoch(records(spark).filter("op = '-'"), 1)
    assert m.monitor.answers().count() == 0
    m.epoch(records(spark).limit(1), 2)  # older than what was seen
    assert m.late_rows == 1


def test_stateful_histogram(spark, tmp_path):
    src = f"{tmp_path}/in"
    records(spark).coalesce(1).write.parquet(src)
    got = streaming.run_to_end(streaming.stateful_histogram(io.stream_updates(spark, src)), "hist_state", "update").collect()
    assert {(r.v, r.nlabel): r.cnt for r in got} == {(1, 2): 1, (2, 1): 2, (3, 2): 1, (1, 1): 0, (3, 1): 0}


def test_generators(spark):
    g = synth.nws(spark, 300)
    n = g.edge_life.count()
    assert 300 * 2 <= n <= 300 * 3
    assert g.edge_life.filter("u >= v").count() == 0
    patterns = synth.sample_patterns(g.stored(), 3, 5, 2.5)
    assert len(patterns) == 3 and all(len(p.labels) == 5 for _, p in patterns)


def test_files_round_trip(spark, tmp_path):
    records(spark).coalesce(1).write.option("header", True).csv(f"{tmp_path}/c")
    records(spark).coalesce(1).write.json(f"{tmp_path}/j")
    assert sorted(io.read_updates(spark, f"{tmp_path}/c", "csv").select("op", "u", "v").collect()) == sorted(io.read_updates(spark, f"{tmp_path}/j", "json").select("op", "u", "v").collect())


def test_stream_monitor_restarts_and_keeps_what_it_leaves_out(spark, tmp_path):
    patterns = Patterns([parse("tri", "a:1-b:2, b-c:1, a-c")])
    vertices = spark.createDataFrame([], "v long, label int")
    store = f"file://{tmp_path}/store"
    first = streaming.StreamMonitor(spark, patterns, vertices, store=store)
    first.epoch(records(spark).limit(2), 0)
    bad = records(spark).limit(1).selectExpr("ts + INTERVAL 1 HOUR AS ts", "op", "1L AS u", "9L AS v", "2 AS u_label", "1 AS v_label", "elabel")
    again = streaming.StreamMonitor(spark, patterns, vertices, store=store)  # a new driver
    assert again.last_batch == 0 and again.monitor.edge_life.count() == 2
    again.epoch(records(spark).limit(2), 0)
    again.epoch(records(spark).filter("u = 1 AND v = 3 AND op = '+'").unionByName(bad), 1)
    assert again.monitor.answers().count() == 2
    assert [(r.u, r.v) for r in again.rejected.collect()] == [(1, 9)] and again.monitor.edge_life.count() == 3
    again.epoch(records(spark).limit(1), 2)
    third = streaming.StreamMonitor(spark, patterns, vertices, store=store)
    assert third.last_batch == 2 and third.monitor.answers().count() == 2
    assert [(r.u, r.v, r.epoch) for r in third.late.collect()] == [(1, 2, 2)]
