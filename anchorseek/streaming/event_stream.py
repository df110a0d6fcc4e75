"""Event streams: windows, late rows, joins, and logs as sequences."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def tumbling(events: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return w.select(F.col("window.start").alias("start"), "event_type", "n", "total")


def sliding(events: DataFrame, width: str = "1 hour", step: str = "15 minutes", late: str = "1 hour") -> DataFrame:
    w = events.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.col("window.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """User sessions with their log string, the first letters of the events in order."""
    w = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("c")))).alias("run"))
    return w.select("user_id", F.col("session_window.start").alias("start"), F.array_join(F.transform("run", lambda x: x["c"]), "").alias("seq"))


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_to_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Purchases joined with the user's clicks in the interval before them."""
    c = events.where("event_type = 'click'").select(F.col("user_id").alias("cu"), F.col("ts").alias("cts"), F.col("event_id").alias("click_id")).withWatermark("cts", within)
    p = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("pts"), F.col("event_id").alias("purchase_id")).withWatermark("pts", within)
    near = (F.col("cu") == F.col("user_id")) & (F.col("cts") <= F.col("pts")) & (F.col("cts") >= F.col("pts") - F.expr(f"INTERVAL {within}"))
    return p.join(c, near).select("purchase_id", "click_id")
