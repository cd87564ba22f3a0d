"""Pooled Accuracy@k and what is derived from it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window, functions as F

KS = (5, 10, 15, 20, 25, 30)


def accuracy_at(recs: DataFrame, test: DataFrame, ks: tuple[int, ...] = KS) -> DataFrame:
    """k, hits, tests, accuracy: hits in the lists over all test pairs, pooled and not averaged per user; all k in one pass."""
    hit = test.select("user_id", "item_id").join(recs.where(F.col("rank") <= max(ks)).select("user_id", "item_id", "rank"), ["user_id", "item_id"], "left")
    one = hit.agg(F.count("*").alias("tests"), *[F.count_if(F.col("rank") <= k).alias(f"h{k}") for k in ks])
    rows = F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(f"h{k}").alias("hits")) for k in ks]))
    return one.select("tests", rows.alias("r")).select("r.k", "r.hits", "tests", F.when(F.col("tests") > 0, F.col("r.hits") / F.col("tests")).alias("accuracy"))


def mae(scores: DataFrame, truth: DataFrame) -> DataFrame:
    """Mean absolute error of the scores; a pair missing in ``truth`` (user_id, item_id) is a zero."""
    both = scores.join(truth.select("user_id", "item_id", F.lit(1.0).alias("r")), ["user_id", "item_id"], "left")
    return both.agg(F.avg(F.abs(F.col("score") - F.coalesce("r", F.lit(0.0)))).alias("mae"))


def scenario_pair(rows: DataFrame, k: int = 30) -> DataFrame:
    """model, feature, in_k, out_k from rows (model, feature, scenario, k, accuracy)."""
    return rows.where(F.col("k") == k).groupBy("model", "feature").pivot("scenario", ["in", "out"]).agg(F.first("accuracy"))


def feature_chain(rows: DataFrame, k: int = 30) -> DataFrame:
    """feature, accuracy, position: features by accuracy, ties by name."""
    return rows.where(F.col("k") == k).select("feature", "accuracy", F.row_number().over(Window.orderBy(F.desc("accuracy"), "feature")).alias("position"))  # one row a feature


def lift(rows: DataFrame, reference: str) -> DataFrame:
    """method, k, accuracy, gain, relative gain and win over the reference method."""
    ref = rows.where(F.col("method") == reference).select("k", F.col("accuracy").alias("ref"))
    both = rows.join(ref, "k")
    return both.select("method", "k", "accuracy", (F.col("accuracy") - F.col("ref")).alias("gain"), (F.col("accuracy") / F.col("ref") - 1).alias("relative"), (F.col("accuracy") > F.col("ref")).alias("wins"))


def divergence(rows: DataFrame, k: int = 30) -> DataFrame:
    """Best over worst accuracy among the features."""
    return rows.where(F.col("k") == k).agg((F.max("accuracy") / F.min("accuracy")).alias("divergence"))


def chance(pool: int, k: int) -> float:
    """Accuracy@k of a random list over a pool of candidates."""
    return min(1.0, k / pool) if pool else 0.0
