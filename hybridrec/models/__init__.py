"""Recommenders with one contract: fit on (user_id, item_id), predict scores for pairs."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, functions as F

from hybridrec.functions import dot


@dataclass
class Model:
    """Factor tables of a fit. ``content_latents`` score items that have no ``item_factors``."""

    user_factors: DataFrame
    item_factors: DataFrame
    content_latents: DataFrame | None = None
    history: list[dict] = field(default_factory=list)
    extra: dict = field(default_factory=dict)

    def predict_in(self, pairs: DataFrame) -> DataFrame:
        """Scores of pairs whose item was seen in training."""
        return _scored(pairs, self.user_factors, self.item_factors)

    def predict_out(self, pairs: DataFrame) -> DataFrame:
        """Scores from content alone."""
        if self.content_latents is None:
            raise ValueError("this model knows no content")
        return _scored(pairs, self.user_factors, self.content_latents)

    def candidates(self) -> DataFrame:
        """id, v, branch for every item that can be scored: its factors if seen, else its content."""
        seen = self.item_factors.select("id", "v", F.lit("in").alias("branch"))
        if self.content_latents is None:
            return seen
        cold = self.content_latents.join(self.item_factors.select("id"), "id", "left_anti").select("id", "v", F.lit("out").alias("branch"))
        return seen.unionByName(cold)

    def predict(self, pairs: DataFrame) -> DataFrame:
        """user_id, item_id, score, branch by whether the item was seen in training."""
        both = pairs.join(self.user_factors.select(F.col("id").alias("user_id"), F.col("v").alias("w")), "user_id").join(self.candidates().select(F.col("id").alias("item_id"), F.col("v").alias("h"), "branch"), "item_id")
        return both.select("user_id", "item_id", dot(F.col("w"), F.col("h")).alias("score"), "branch")


def _scored(pairs: DataFrame, users: DataFrame, items: DataFrame) -> DataFrame:
    both = pairs.join(users.select(F.col("id").alias("user_id"), F.col("v").alias("w")), "user_id").join(items.select(F.col("id").alias("item_id"), F.col("v").alias("h")), "item_id")
    return both.select("user_id", "item_id", dot(F.col("w"), F.col("h")).alias("score"))
