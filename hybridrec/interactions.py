"""Ratings and positives from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from hybridrec.features.descriptors import blend_vectors
from hybridrec.functions import portable_hash
from hybridrec.sources import table


def _stars() -> Column:
    return F.ceil(F.col("l_quantity") / 10).cast("int")


def ratings_view(lineitem: DataFrame, orders: DataFrame) -> DataFrame:
    """One rating per (customer, part): the largest fifth of the quantities any of their lines reached."""
    lines = lineitem.select("l_orderkey", F.col("l_partkey").alias("item_id"), _stars().alias("stars"))
    owners = orders.select("o_orderkey", F.col("o_custkey").alias("user_id"))
    return lines.join(owners, lines["l_orderkey"] == owners["o_orderkey"]).groupBy("user_id", "item_id").agg(F.max("stars").alias("stars"))


def ratings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ratings_view(table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders"))


def to_implicit(rated: DataFrame, threshold: int = 5) -> DataFrame:
    """Pairs at the top of the scale; all other pairs are zeros and never stored."""
    return rated.where(F.col("stars") >= threshold).select("user_id", "item_id")


def top_positives(lineitem: DataFrame, orders: DataFrame, threshold: int = 5) -> DataFrame:
    """``to_implicit`` of ``ratings_view``: the largest of a pair's lines is at the top if any of them is, so only those are joined."""
    return to_implicit(ratings_view(lineitem.where(_stars() >= threshold), orders), threshold)


def restrict(rated: DataFrame, items: DataFrame) -> DataFrame:
    """Ratings of items with content; users without a rating left vanish with their rows."""
    return rated.join(items.select("item_id").distinct(), "item_id", "left_semi")


def taste_view(spark: SparkSession, sf_dir: str, kind: str = "mixed") -> DataFrame:
    """Positives planted on the pairs really rated, so that content says something about taste.

    ``vector``: a component of the item's blend vector, chosen by the user, is high. ``mixed``: that, or brand or title class
    agree with the user at given rates. Both with 3 % noise.
    """
    if kind not in ("vector", "mixed"):
        raise ValueError(f"no view {kind!r}")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("user_id"))
    bought = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), F.col("l_partkey").alias("item_id")).join(orders, "o_orderkey").select("user_id", "item_id")
    least = 0.1 if kind == "vector" else 0.15
    high = F.transform(F.slice("f", 1, 8), lambda y: y > least).alias("high")  # all that users choose from
    pairs = bought.join(blend_vectors(spark, sf_dir).select("item_id", high), "item_id")
    liked = F.element_at("high", (F.col("user_id") % 8).cast("int") + 1) | (portable_hash(F.col("user_id"), F.col("item_id"), 3) % 100 < 3)
    if kind == "mixed":
        part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"), F.regexp_extract("p_brand", "([0-9]+)", 1).cast("int").alias("brand"), F.ascii("p_name").alias("letter"))
        pairs = pairs.join(part, "item_id")
        by_brand = (F.col("brand") % 5 == F.col("user_id") % 5) & (portable_hash(F.col("user_id"), F.col("item_id"), 21) % 100 < 70)
        by_title = (F.col("letter") % 8 == F.col("user_id") % 8) & (portable_hash(F.col("user_id"), F.col("item_id"), 22) % 100 < 30)
        liked = liked | by_brand | by_title
    # lines are partitioned by item by now, so that telling equal pairs apart takes no exchange of its own
    return pairs.where(liked).select("user_id", "item_id").distinct()


def events_positives(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct purchases: the second, denser interaction set."""
    events = table(spark, sf_dir, "events").where(F.col("event_type") == "purchase")
    return events.select("user_id", F.get_json_object("props", "$.k").cast("long").alias("item_id")).distinct()


def positives(spark: SparkSession, sf_dir: str, dataset: str = "mixed") -> DataFrame:
    if dataset == "quantity":
        return top_positives(table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders"))
    if dataset == "events":
        return events_positives(spark, sf_dir)
    return taste_view(spark, sf_dir, dataset)
