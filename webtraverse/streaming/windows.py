"""Windows over arrivals: each works on a batch or a stream of ``events`` alike; a watermark bounds the state of a stream."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WATERMARK = "10 minutes"


def _bounded(events: DataFrame, watermark: str | None) -> DataFrame:
    return events.withWatermark("ts", watermark) if watermark and events.isStreaming else events


def _counted(events: DataFrame, window, *keys: str) -> DataFrame:
    out = events.groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("total"))
    return out.select(F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), *keys, "n", "total")


def tumbling(events: DataFrame, size: str = "1 hour", watermark: str | None = WATERMARK) -> DataFrame:
    return _counted(_bounded(events, watermark), F.window("ts", size), "event_type")


def sliding(events: DataFrame, size: str = "1 hour", step: str = "15 minutes", watermark: str | None = WATERMARK) -> DataFrame:
    return _counted(_bounded(events, watermark), F.window("ts", size, step), "event_type")


def sessions(events: DataFrame, gap: str = "30 minutes", watermark: str | None = WATERMARK) -> DataFrame:
    return _counted(_bounded(events, watermark), F.session_window("ts", gap), "user_id")


def first_seen(events: DataFrame, watermark: str = WATERMARK) -> DataFrame:
    """A stream without the events whose id came before within the watermark."""
    return events.withWatermark("ts", watermark).dropDuplicatesWithinWatermark(["event_id"])
