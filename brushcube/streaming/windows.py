"""Streaming views of ``events``. Times without zone can't carry a watermark, so they are cast (session zone UTC)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(events: DataFrame, delay: str | None = "1 hour") -> DataFrame:
    out = events.withColumn("at", F.col("ts").cast("timestamp"))
    return out.withWatermark("at", delay) if delay else out


def tumbling(events: DataFrame, width: str = "1 hour", delay: str | None = "1 hour") -> DataFrame:
    return _counts(timed(events, delay), F.window("at", width))


def sliding(events: DataFrame, width: str = "1 hour", slide: str = "30 minutes", delay: str | None = "1 hour") -> DataFrame:
    return _counts(timed(events, delay), F.window("at", width, slide))


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str | None = "1 hour") -> DataFrame:
    return _counts(timed(events, delay), F.session_window("at", gap), "user_id")


def deduplicated(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    return timed(events, delay).dropDuplicatesWithinWatermark(["event_id"])


def _counts(rows: DataFrame, window, *keys: str) -> DataFrame:
    out = rows.groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"), F.sum("value").alias("v"))
    return out.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "v")
