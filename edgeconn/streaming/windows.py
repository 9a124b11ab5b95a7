"""Event-time windows over edge streams."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def windowed_edges(events: DataFrame, length: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, n_events, n_users): events by window; works on a stream, whose
    rows later than ``late`` are dropped, and on a table."""
    timed = events.select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    if timed.isStreaming:
        timed = timed.withWatermark("ts", late)
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return timed.groupBy(w).agg(F.count(F.lit(1)).alias("n_events"), F.sum("user_id").alias("user_sum")).select(F.col("window.start").alias("start"), "n_events", "user_sum")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, n_events): runs of a user's events without a gap."""
    timed = events.select(F.col("ts").cast("timestamp").alias("ts"), "user_id")
    if timed.isStreaming:
        timed = timed.withWatermark("ts", late)
    return timed.groupBy("user_id", F.session_window("ts", gap)).agg(F.count(F.lit(1)).alias("n_events")).select("user_id", F.col("session_window.start").alias("start"), "n_events")


def late_rows(query) -> int:
    """Rows that a finished streaming query dropped for being behind its
    watermark, from its own progress reports."""
    return sum(int(op.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for op in p["stateOperators"])


def unique_edges(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    """A stream of (ts, a, b) without repeats inside the watermark."""
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["a", "b"])
