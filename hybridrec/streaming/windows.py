"""Windowed counts of events; the same code serves batch tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def _counted(grouped) -> DataFrame:
    return grouped.agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def tumbling(events: DataFrame, size: str = "1 day") -> DataFrame:
    return _counted(events.groupBy(F.window("ts", size), "event_type"))


def sliding(events: DataFrame, size: str = "1 day", step: str = "6 hours") -> DataFrame:
    return _counted(events.groupBy(F.window("ts", size, step), "event_type"))


def session(events: DataFrame, gap: str = "2 hours") -> DataFrame:
    return events.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count("*").alias("n")).select(F.col("s.start").alias("start"), F.col("s.end").alias("end"), "user_id", "n")


def with_lateness(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", lateness)
