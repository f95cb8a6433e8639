"""Live panels and alarms with Structured Streaming's own windows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from unscramble.sources.panels import CLICKS


def _timed(events: DataFrame) -> DataFrame:
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_ticks(events: DataFrame, tick: str = "6 hours", late: str = "1 day", slide: str | None = None) -> DataFrame:
    """Average of each channel on tumbling (or sliding) windows; rows later than the watermark are dropped."""
    window = F.window("ts", tick, slide) if slide else F.window("ts", tick)
    rows = _timed(events).withWatermark("ts", late).groupBy(window.alias("w"), "event_type").agg(F.avg("value").alias("v"), F.count("*").alias("c"))
    return rows.select(F.col("w.start").alias("ts"), "event_type", "v", "c")


def tick_panel(ticks: DataFrame, g: float = 40.0) -> DataFrame:
    """Tick rows of stream_ticks, written out, as tuples of five sensors."""
    x = F.array(*[F.max(F.when(F.col("event_type") == c, F.col("v") + g * m)) for m, c in enumerate(CLICKS)])
    return ticks.groupBy("ts").agg(x.alias("x"))


def alarm_sessions(alarms: DataFrame, gap: str = "2 hours", late: str = "1 day", by: str = "event_type") -> DataFrame:
    """Alarms of a channel that follow each other closely, as sessions."""
    rows = _timed(alarms).withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), by).agg(F.count("*").alias("n_alarms"))
    return rows.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), by, "n_alarms")
