"""Window aggregates that take batches and streams alike."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def marked(df: DataFrame, watermark: str) -> DataFrame:
    """Watermark on ``ts``, which must be a timestamp with zone for it."""
    return df.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def _late(df: DataFrame, watermark: str | None) -> DataFrame:
    return marked(df, watermark) if watermark else df


def tumbling(events: DataFrame, size: str, watermark: str | None = None) -> DataFrame:
    """``(start, event_type, n)``; ``start`` in epoch seconds."""
    g = _late(events, watermark).groupBy(F.window("ts", size), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str, slide: str, watermark: str | None = None) -> DataFrame:
    g = _late(events, watermark).groupBy(F.window("ts", size, slide), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return g.select(F.unix_timestamp("window.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str, watermark: str | None = None) -> DataFrame:
    g = _late(events, watermark).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.unix_timestamp("session_window.start").alias("start"), "n")
