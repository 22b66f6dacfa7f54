"""Streams give the rows of their batch twins; repeats change nothing."""

import pytest
from conftest import DATA
from pyspark.sql import functions as F

from meshcut.plans.stream_queries import FIXED
from meshcut.sources import points
from meshcut.streaming import events as S

SF = f"{DATA}/sf0.001"


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    out = str(tmp_path_factory.mktemp("events"))
    e = points.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    for lo, hi in ((0, 300), (300, 700), (700, 10**9)):
        e.where((F.col("event_id") >= lo) & (F.col("event_id") < hi)).coalesce(1).write.mode("append").parquet(out)
    return out


def test_assignment_equals_batch(spark, folder, tmp_path):
    got = S.run_once(S.assign_stream(S.source(spark, folder), FIXED).select("pid", "block"), "assigned", str(tmp_path))
    want = S.assign_stream(points.load(spark, SF, "events"), FIXED).select("pid", "block")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_rebalancer_ignores_repeats(spark):
    batch = points.load(spark, SF, "events")
    r = S.Rebalancer(FIXED, eps=0.03, windows=2)
    r(batch, 0)
    loads = list(r.loads)
    r(batch, 0)
    assert r.loads == loads and not r.alerts
    r(batch, 1)
    assert r.alerts and sum(r.loads) == 2 * batch.count()


def test_dedup_in_a_stream(spark, folder, tmp_path):
    s = S.source(spark, folder)
    twice = s.union(s)
    got = S.run_once(S.dedup(twice, "400 days").select("event_id"), "once", str(tmp_path))
    assert got.count() == got.distinct().count() == 1000


def test_rebalancer_goes_on_after_a_restart(spark, tmp_path):
    """The state of the last batch is read by a new object; a batch that was done before the restart changes nothing."""
    batch = points.load(spark, SF, "events")
    folder = f"file://{tmp_path}/state"
    one = S.Rebalancer(FIXED, eps=0.03, windows=3, folder=folder)
    for n in range(2):
        one(batch, n)
    two = S.Rebalancer(FIXED, eps=0.03, windows=3, folder=folder)
    two(batch, 1)
    assert (two.loads, two.over, two.last) == (one.loads, one.over, 1)
    two(batch, 2)
    assert two.alerts and sum(two.loads) == 3 * batch.count()


def test_rebalancer_starts_warm_and_reports_migration(spark, tmp_path):
    batch = points.load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    r = S.Rebalancer(FIXED, eps=0.05, windows=1, folder=f"file://{tmp_path}/moves", repartition=True)
    r(batch, 0)
    assert len(r.alerts) == 1 and r.moves and all(was != now and n > 0 for _, was, now, n, _ in r.moves)
    sizes = [x["count"] for x in S.assign_stream(batch, r.centres).groupBy("block").count().collect()]
    assert max(sizes) / (sum(sizes) / len(FIXED.rows)) - 1 < r.alerts[0][1]


def rows_of(spark, tmp_path, name, parts):
    """Events in files that arrive one after the other."""
    out = f"{tmp_path}/{name}"
    for rows in parts:
        df = spark.createDataFrame([(i, t, u, k, 1.0, "") for i, t, u, k in rows], "event_id long, ts string, user_id long, event_type string, value double, props string")
        df.withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(out)
    return out


def test_late_rows_are_dropped_and_windows_close(spark, tmp_path):
    """Two days later the first day is closed: a row for it is late. Its load is the first file's alone."""
    parts = [[(1, "2024-01-01 01:00:00", 1, "view"), (2, "2024-01-01 02:00:00", 1, "view")], [(3, "2024-01-04 01:00:00", 1, "view")], [(4, "2024-01-01 03:00:00", 1, "view")], [(5, "2024-01-08 00:00:00", 1, "view")]]
    out = rows_of(spark, tmp_path, "late", [])
    got = {}
    q = None
    for n, part in enumerate(parts):
        out = rows_of(spark, tmp_path, "late", [part])
        s = S.assign_stream(S.source(spark, out), FIXED)
        q = S.window_load(s).writeStream.format("parquet").option("path", f"{tmp_path}/loads").option("checkpointLocation", f"{tmp_path}/mark").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
    for r in spark.read.parquet(f"{tmp_path}/loads").collect():
        got[str(r["start"])[:10]] = got.get(str(r["start"])[:10], 0) + r["load"]
    assert got == {"2024-01-01": 2, "2024-01-04": 1}


def test_streams_join_on_an_interval_and_sessions_close(spark, tmp_path):
    rows = [(1, "2024-01-01 01:00:00", 7, "view"), (2, "2024-01-01 01:05:00", 7, "purchase"), (3, "2024-01-01 02:00:00", 7, "purchase"), (4, "2024-01-01 01:01:00", 8, "view"), (5, "2024-01-03 00:00:00", 9, "view")]
    out = rows_of(spark, tmp_path, "pairs", [rows])
    got = S.run_once(S.interval_events(S.source(spark, out)), "pairs", f"{tmp_path}/a").collect()
    assert [(r["user_id"], r["e1"], r["e2"]) for r in got] == [(7, 1, 2)]
    sessions = S.run_once(S.session_load(S.source(spark, out)), "sessions", f"{tmp_path}/b").collect()
    assert sorted((r["user_id"], r["n"]) for r in sessions if r["user_id"] != 9) == [(7, 1), (7, 2), (8, 1)]
    sliding = S.run_once(S.window_load(S.assign_stream(S.source(spark, out), FIXED), "1 hour", "30 minutes"), "sliding", f"{tmp_path}/c", "update")
    assert sliding.count() > 0
