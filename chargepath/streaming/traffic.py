"""Streams: traffic factors, station changes, request sessions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PROBE = "event_id long, ts timestamp, node long, slowdown double"


def probes(events: DataFrame, nodes: int) -> DataFrame:
    """events -> event_id, ts, node, slowdown."""
    return events.where("event_type = 'view'").select("event_id", F.col("ts").cast("timestamp").alias("ts"), (F.col("user_id") * 613 % nodes).alias("node"), (1 + F.col("value") / 100).alias("slowdown"))


def traffic_windows(rows: DataFrame, width: str = "1 hour", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """Count and mean slowdown of each window; works on tables and on streams."""
    spans = F.window("ts", width, slide) if slide else F.window("ts", width)
    source = rows.withWatermark("ts", late) if rows.isStreaming else rows
    out = source.groupBy(spans.alias("w")).agg(F.count("*").alias("probes"), F.sum(F.round(F.col("slowdown") * 1000).cast("long")).alias("slow_milli"))
    return out.select(F.col("w.start").alias("start"), "probes", "slow_milli")


def station_changes(events: DataFrame, stations: int) -> DataFrame:
    """events -> event_id, ts, station, op (open, close)."""
    rows = events.where("event_type IN ('error', 'signup')")
    return rows.select("event_id", F.col("ts").cast("timestamp").alias("ts"), (F.col("event_id") % stations).alias("station"), F.when(F.col("event_type") == "error", "close").otherwise("open").alias("op"))


def station_state(changes: DataFrame) -> DataFrame:
    """The last change of each station."""
    last = F.max(F.struct("ts", "event_id", "op")).alias("m")
    return changes.groupBy("station").agg(last).select("station", F.col("m.op").alias("op"), F.col("m.event_id").alias("event_id"))


def request_sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 day") -> DataFrame:
    """Sessions of each user's trip requests."""
    rows = events.where("event_type = 'click'").select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    rows = rows.withWatermark("ts", late) if rows.isStreaming else rows
    out = rows.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("requests"))
    return out.select("user_id", F.col("s.start").alias("start"), "requests")


def as_of(left: DataFrame, rows: DataFrame) -> DataFrame:
    """left(id, ts, node) + the slowdown of the last probe of its node at or before ts."""
    from pyspark.sql import Window

    a = left.select("id", "ts", "node", F.lit(None).cast("double").alias("slowdown"), F.lit(1).alias("kind"), F.lit(None).cast("long").alias("event_id"))
    b = rows.select(F.lit(None).cast("long").alias("id"), "ts", "node", "slowdown", F.lit(0).alias("kind"), "event_id")
    order = Window.partitionBy("node").orderBy("ts", "kind", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn("slowdown", F.last("slowdown", ignorenulls=True).over(order))
    return both.where("kind = 1").select("id", "node", "slowdown")
