"""Batch twins of the streaming operators, and one that runs the stream itself."""

from __future__ import annotations

from pyspark.sql import functions as F

from meshcut.operators.kmeans import Centre, Centres
from meshcut.plans import sqltext as T
from meshcut.plans.registry import ctes, query
from meshcut.sources import points
from meshcut.streaming import events as S

#: Eight fixed centres over days and values, with the closed influence formula.
FIXED = Centres([Centre(b, (15.0 + 25 * b, 2.0 + (b % 4)), 1 + (b % 3) * 0.125) for b in range(8)])
FIXED_SQL = "SELECT b::INTEGER AS block, (15+25*b)::DOUBLE AS x, (2+(b%4))::DOUBLE AS y FROM (SELECT unnest(range(8)) AS b)"
NEAR = T.nearest(T.P["events2d"], FIXED_SQL)


def assigned(spark, d):
    return S.assign_stream(points.load(spark, d, "events"), FIXED)


@query("stream_assign", f"SELECT pid, block FROM ({NEAR})")
def stream_assign(spark, d):
    return assigned(spark, d).select("pid", "block")


def start_us():
    return F.unix_micros(F.col("start").cast("timestamp")).alias("start_us")



@query("window_load", f"SELECT epoch_us(date_trunc('day', ts)) AS start_us, block, count(*) AS load FROM ({NEAR}) a JOIN events e ON e.event_id = a.pid GROUP BY ALL")
def window_load(spark, d):
    return S.window_load(assigned(spark, d)).select(start_us(), "block", "load")


@query("sliding_load", f"SELECT epoch_us(s) AS start_us, block, count(*) AS load FROM (SELECT block, unnest([time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR * i FOR i IN range(4)]) AS s FROM ({NEAR}) a JOIN events e ON e.event_id = a.pid) GROUP BY ALL")
def sliding_load(spark, d):
    return S.window_load(assigned(spark, d), "1 day", "6 hours").select(start_us(), "block", "load")


@query("session_load", ctes(("g", "SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)"), ("s", "SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g"), select="SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM s GROUP BY user_id, k"))
def session_load(spark, d):
    return S.session_load(points.load(spark, d, "events")).select("user_id", start_us(), "n")


@query("interval_events", "SELECT a.user_id, a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 10 MINUTE")
def interval_events(spark, d):
    return S.interval_events(points.load(spark, d, "events"))
