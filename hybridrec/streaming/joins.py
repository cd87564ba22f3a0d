"""Stream-static and stream-stream joins."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def with_content(purchases: DataFrame, part: DataFrame) -> DataFrame:
    return purchases.join(part.select(F.col("p_partkey").alias("item_id"), "p_brand", "p_name"), "item_id")


def view_to_purchase(events: DataFrame, within: str = "1 hour", lateness: str = "2 hours") -> DataFrame:
    """Views followed by a purchase of the same user in time; both sides have a watermark, so state is bounded."""
    v = events.where("event_type = 'view'").select(F.col("user_id"), F.col("event_id").alias("viewed"), F.col("ts").alias("t0"))
    p = events.where("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("event_id").alias("bought"), F.col("ts").alias("t1"))
    if events.isStreaming:
        v, p = v.withWatermark("t0", lateness), p.withWatermark("t1", lateness)
    return v.join(p, (F.col("user_id") == F.col("buyer")) & (F.col("t1") > F.col("t0")) & (F.col("t1") <= F.col("t0") + F.expr(f"interval {within}"))).select("viewed", "bought")
