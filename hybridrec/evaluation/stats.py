"""Dataset figures."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F


def dataset_stats(rated: DataFrame, threshold: int = 5, approximate: bool = False) -> DataFrame:
    """users, videos, ratings, density, positives, positive_density in one pass."""
    distinct = F.approx_count_distinct if approximate else F.count_distinct
    one = rated.agg(distinct("user_id").alias("users"), distinct("item_id").alias("videos"), F.count("*").alias("ratings"), F.count_if(F.col("stars") >= threshold).alias("positives"))
    cells = F.col("users").cast("double") * F.col("videos")
    return one.select("users", "videos", "ratings", (F.col("ratings") / cells).alias("density"), "positives", (F.col("positives") / cells).alias("positive_density"))


def length_stats(df: DataFrame, column: str) -> DataFrame:
    return df.agg(F.min(column).alias("min"), F.max(column).alias("max"), F.avg(column).alias("mean"))
