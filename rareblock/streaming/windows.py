"""Windowed counts of events; each works on a stream and on a table alike."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(events: DataFrame, ts: str, late: str) -> DataFrame:
    """events with a watermark; streams take no time without a zone, so there it is read in the session's."""
    if events.isStreaming and dict(events.dtypes)[ts] == "timestamp_ntz":
        events = events.withColumn(ts, F.col(ts).cast("timestamp"))
    return events.withWatermark(ts, late)


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "10 minutes", key: str = "event_type", ts: str = "ts") -> DataFrame:
    """(start, key, n) per window; rows later than ``late`` behind the newest are dropped from a stream."""
    return timed(events, ts, late).groupBy(F.window(ts, width), F.col(key)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), key, "n")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "15 minutes", late: str = "10 minutes", key: str = "event_type", ts: str = "ts") -> DataFrame:
    return timed(events, ts, late).groupBy(F.window(ts, width, step), F.col(key)).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), key, "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes", key: str = "user_id", ts: str = "ts") -> DataFrame:
    """(start, end, key, n): runs of a key's events no further apart than gap."""
    return timed(events, ts, late).groupBy(F.session_window(ts, gap), F.col(key)).agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), key, "n")


def follow_ups(events: DataFrame, first: str = "view", then: str = "click", within: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """(first_id, then_id): events of one user, the second at most ``within`` after the first."""
    a = timed(events, "ts", late).filter(F.col("event_type") == first).select(F.col("event_id").alias("first_id"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    b = timed(events, "ts", late).filter(F.col("event_type") == then).select(F.col("event_id").alias("then_id"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + INTERVAL {within}")).select("first_id", "then_id")


def once(events: DataFrame, late: str = "10 minutes", key: str = "event_id", ts: str = "ts") -> DataFrame:
    """Each key once within the watermark."""
    return timed(events, ts, late).dropDuplicatesWithinWatermark([key])
