"""Streaming queries, each against its batch equivalent."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators.workspace import Workspace
from ..streaming import incremental as inc

QUERIES: dict = {}
ORACLES: dict = {}


def query(name: str, sql: str | None = None):
    def register(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return register


@query("stream_incremental_save", "select user_id, count(*)::bigint as n_nodes, md5(string_agg(h, ';' order by h)) as fp from (select user_id, md5(concat_ws('|', event_id, event_type, props)) as h from events) group by user_id")
def stream_incremental_save(spark, d):
    return inc.incremental_save(spark, inc.event_stream(spark, d), Workspace(spark, "stream"))


@query("stream_window_counts", "select date_trunc('day', ts)::timestamp as start, event_type, count(*)::bigint as n from events group by 1, 2")
def stream_window_counts(spark, d):
    """Daily counts in update mode: the last row of every window is its count."""
    work = Workspace(spark, "windows")
    out = inc.run_to_table(inc.window_counts(inc.event_stream(spark, d)), work, "windows", "update")
    return out.groupBy(F.col("start").cast("timestamp_ntz").alias("start"), "event_type").agg(F.max("n").alias("n"))


@query("stream_dedup", "select event_type, count(distinct event_id)::bigint as n from events group by 1")
def stream_dedup(spark, d):
    work = Workspace(spark, "dedup")
    s = inc.event_stream(spark, d)
    out = inc.run_to_table(inc.dedup(s.unionByName(s)).select("event_id", "event_type"), work, "dedup")
    return out.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


@query("stream_sessions", "select user_id, count(*)::bigint as n_sessions from (select user_id, case when lag(ts) over (partition by user_id order by ts) + interval 6 hour > ts then null else 1 end as new from events) where new = 1 group by 1")
def stream_sessions(spark, d):
    """Bursts of a user's events with gaps under six hours."""
    work = Workspace(spark, "sessions")
    s = inc.event_stream(spark, d).withWatermark("ts", "40 days").groupBy(F.session_window("ts", "6 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    out = inc.run_to_table(s.select("user_id", F.col("w.start").alias("start")), work, "sessions", "complete")
    return out.groupBy("user_id").agg(F.countDistinct("start").alias("n_sessions"))
