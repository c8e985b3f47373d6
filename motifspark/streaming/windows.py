"""Windowed counts: the same code on a stream and on a table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(events: DataFrame) -> DataFrame:
    """Event time as an instant, from microseconds, whatever the session's zone is."""
    from ..graph import micros

    return events.withColumn("at", F.timestamp_micros(micros("ts")))


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.groupBy(F.window("at", width).alias("w"), "event_type").agg(F.count("*").alias("n"))


def sliding(events: DataFrame, width: str = "1 day", slide: str = "6 hours") -> DataFrame:
    return events.groupBy(F.window("at", width, slide).alias("w"), "event_type").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    return events.groupBy(F.session_window("at", gap).alias("w"), "user_id").agg(F.count("*").alias("n"))


def flat(counts: DataFrame, key: str = "event_type") -> DataFrame:
    """The window's start in microseconds instead of the struct."""
    return counts.select(F.unix_micros("w.start").alias("w_start"), key, "n")


def counted_late(query) -> int:
    """Rows that a finished streaming query dropped because their window was closed, over all its batches.

    The state operator counts what reaches it after partial aggregation: rows of one window and key in one batch count once.
    """
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
