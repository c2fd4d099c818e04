"""Streaming queries: the events table replayed as a stream gives what the batch SQL gives."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..streaming.replay import collected, replayed, sketch_deltas
from . import oracle as O

W = 256
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}


def query(name: str, sql: str):
    def add(f):
        QUERIES[name], ORACLE[name] = f, sql
        return f

    return add


@query("stream_tumbling", "SELECT epoch(time_bucket(INTERVAL 7 DAY, ts, TIMESTAMP '1970-01-01'))::BIGINT AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, d):
    events = replayed(spark, d).withWatermark("ts", "1 day")
    agg = events.groupBy(F.window("ts", "7 days"), "event_type").agg(F.count("*").alias("n"))
    return collected(agg.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n"), "complete")


@query("stream_sliding", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([epoch(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'))::BIGINT, epoch(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '1970-01-01'))::BIGINT - 86400]) AS s FROM events) t GROUP BY 1")
def stream_sliding(spark, d):
    agg = replayed(spark, d).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n"))
    return collected(agg.select(F.unix_timestamp("window.start").alias("start"), "n"), "complete")


@query("stream_session", """WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR > ts THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2) t GROUP BY 1, 2""")
def stream_session(spark, d):
    agg = replayed(spark, d).groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count("*").alias("n"))
    return collected(agg.select("user_id", "n"), "complete").groupBy("user_id", "n").agg(F.count("*").alias("sessions"))


@query("stream_sketch_delta", f"SELECT rep, bin, val::BIGINT AS val FROM ({O.sketch('SELECT user_id FROM events', {'user_id': 'cust'}, W, 2, {'user_id': ['cust#0']})}) t")
def stream_sketch_delta(spark, d):
    return sketch_deltas(spark, d, W, 2)


