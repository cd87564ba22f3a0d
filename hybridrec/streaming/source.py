"""The events as a stream of files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

SCHEMA = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def events(spark: SparkSession, directory: str, files_per_trigger: int = 1) -> DataFrame:
    raw = spark.readStream.schema(SCHEMA.replace("timestamp", "timestamp_ntz")).option("maxFilesPerTrigger", files_per_trigger).parquet(directory)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def dedup(stream: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """One row per event id, as long as copies come within the lateness."""
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def purchases(stream: DataFrame) -> DataFrame:
    return stream.where(F.col("event_type") == "purchase").select("event_id", "ts", "user_id", F.get_json_object("props", "$.k").cast("long").alias("item_id"))


def split_into_files(spark: SparkSession, events_table: DataFrame, directory: str, files: int = 4) -> str:
    """Writes the events, in time order, as several files of a stream directory, one after the other: sources read older files first."""
    bounds = events_table.agg(F.min("event_id").alias("low"), (F.max("event_id") + 1).alias("high")).collect()[0]
    low, high = bounds["low"] or 0, bounds["high"] or 1
    for i in range(files):
        a, b = (low + (high - low) * k // files for k in (i, i + 1))
        events_table.where((F.col("event_id") >= a) & (F.col("event_id") < b)).coalesce(1).write.mode("append").parquet(directory)
    return directory
