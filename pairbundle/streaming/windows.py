"""Event-time windows that read a batch or a stream alike."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def timed(events: DataFrame) -> DataFrame:
    """Event time as a timestamp: watermarks need one, and files hold it without a zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def _start(name: str = "w.start"):
    return F.date_format(name, "yyyy-MM-dd HH:mm:ss").alias("start")


def _late(events: DataFrame, delay: str | None) -> DataFrame:
    return timed(events).withWatermark("ts", delay) if delay else timed(events)


def tumbling(events: DataFrame, width: str = "1 hour", delay: str | None = None) -> DataFrame:
    out = _late(events, delay).groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n"))
    return out.select(_start(), "event_type", "n")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "15 minutes", delay: str | None = None) -> DataFrame:
    return _late(events, delay).groupBy(F.window("ts", width, step).alias("w")).agg(F.count("*").alias("n")).select(_start(), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    out = _late(events, delay).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return out.select("user_id", _start(), "n")


def interval_join(clicks: DataFrame, purchases: DataFrame, within: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """Purchases within a time after a click of the same user; both sides keep state no longer than that."""
    a = clicks.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").cast("timestamp").alias("ta")).withWatermark("ta", delay)
    b = purchases.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").cast("timestamp").alias("tb")).withWatermark("tb", delay)
    return a.join(b, F.expr(f"u = user_id AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("click_id", "purchase_id")


def with_profile(events: DataFrame, profile: DataFrame) -> DataFrame:
    """Stream against a table: each event with its user's row."""
    return events.join(profile, "user_id", "left")
