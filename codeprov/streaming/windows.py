"""Windowed counts, sessions, duplicates and joins over arriving events."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def tumbling(stream: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Bursts of one user's events."""
    return stream.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("session_start"), "n")


def first_seen(stream: DataFrame, keys: list[str]) -> DataFrame:
    """Each key once within the watermark; state is dropped behind it."""
    return stream.dropDuplicatesWithinWatermark(keys).select(*keys)


def followed(stream: DataFrame, first: str, then: str, within: str) -> DataFrame:
    """Pairs of one user's events, the second after the first by at most ``within``: a stream-stream join bounded by both watermarks."""
    a = stream.where(F.col("event_type") == first).select(F.col("user_id").alias("u"), F.col("event_id").alias("first"), F.col("ts").alias("t0"))
    b = stream.where(F.col("event_type") == then).select(F.col("user_id").alias("v"), F.col("event_id").alias("then"), F.col("ts").alias("t1"))
    return a.join(b, F.expr(f"u = v AND t1 > t0 AND t1 <= t0 + INTERVAL {within}")).select("first", "then")
