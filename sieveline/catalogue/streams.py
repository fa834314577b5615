"""Streaming plans over the events file; the SQL twins are their batch results."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..streaming import drain, event_stream, fold_counts
from ..workloads.inputs import table
from .registry import query


def _events(spark, sf):
    return event_stream(spark, f"{sf}/events.parquet")


@query("SELECT event_id, upper(event_type) AS kind FROM events WHERE value > 50")
def stream_filter_map(spark, sf):
    return drain(_events(spark, sf).filter("value > 50").select("event_id", F.upper("event_type").alias("kind")))


@query("SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, sf):
    g = _events(spark, sf).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day"), "event_type").count()
    return drain(g.select(F.date_format("window.start", "yyyy-MM-dd").alias("day"), "event_type", F.col("count").alias("n")), "complete")


@query("SELECT strftime(s, '%Y-%m-%d %H') AS start, count(*)::BIGINT AS n FROM (SELECT unnest([date_trunc('day', ts) + INTERVAL 12 HOUR * (hour(ts) // 12), date_trunc('day', ts) + INTERVAL 12 HOUR * (hour(ts) // 12) - INTERVAL 12 HOUR]) AS s FROM events) GROUP BY 1")
def stream_sliding(spark, sf):
    g = _events(spark, sf).groupBy(F.window("ts", "24 hours", "12 hours")).count()
    return drain(g.select(F.date_format("window.start", "yyyy-MM-dd HH").alias("start"), F.col("count").alias("n")), "complete")


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf):
    return drain(_events(spark, sf).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]))


@query("SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf):
    s = _events(spark, sf).join(table(spark, sf, "customer"), F.col("user_id") == F.col("c_custkey"))
    return drain(s.select("event_id", "c_mktsegment"))


@query("SELECT event_type, count(*)::BIGINT AS n, round(sum(value), 6) AS total FROM events GROUP BY event_type")
def stream_fold_state(spark, sf):
    return drain(fold_counts(_events(spark, sf).select("event_type", "value"), "event_type"), "update")
