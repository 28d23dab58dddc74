"""Windowed aggregates of events; the same plans run on batches and streams."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _shown(ts: Column) -> Column:
    return F.date_format(ts, "yyyy-MM-dd HH:mm:ss")


def _by_window(events: DataFrame, window: Column) -> DataFrame:
    got = events.groupBy(window.alias("w"), "event_type").agg(F.count("*").alias("events"), F.round(F.sum("value"), 4).alias("total"))
    return got.select(_shown(F.col("w.start")).alias("window_start"), "event_type", "events", "total")


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    return _by_window(events, F.window("ts", size))


def sliding(events: DataFrame, size: str = "1 day", slide: str = "6 hours") -> DataFrame:
    return _by_window(events, F.window("ts", size, slide))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    got = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events"), F.round(F.sum("value"), 4).alias("total"))
    return got.select("user_id", _shown(F.col("w.start")).alias("session_start"), "events", "total")
