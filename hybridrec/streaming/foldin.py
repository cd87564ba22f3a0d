"""New interactions and new items without fitting again."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, functions as F

from hybridrec.linalg import gram, half_step, layout
from hybridrec.models.emf import EmfParams, embed


def fold_in(history: DataFrame, item_factors: DataFrame, p: EmfParams) -> DataFrame:
    """id, v: one user step against fixed item factors for the users in ``history`` (all their positives)."""
    return half_step(layout(history, "user_id", "item_id"), item_factors, p.k, p.lam_u, p.c_pos, p.c_zero, None, p.strategy, gram(item_factors, p.k))


def fold_in_sink(item_factors: DataFrame, p: EmfParams, read_history: Callable[[], DataFrame | None], write: Callable[[DataFrame, DataFrame, int], None]) -> Callable:
    """For foreachBatch: adds the batch to the history of the users it touches and hands their new factors on.

    ``write`` gets (history rows of the batch, factors, batch id); writing by batch id makes a repeated batch harmless.
    """

    def each(batch: DataFrame, batch_id: int) -> None:
        new = batch.select("user_id", "item_id").distinct()
        old = read_history()
        touched = new.select("user_id").distinct()
        full = new if old is None else new.unionByName(old.join(touched, "user_id", "left_semi").select("user_id", "item_id")).distinct()
        if not full.isEmpty():
            write(new, fold_in(full, item_factors, p), batch_id)

    return each


def new_items(features: DataFrame, e: np.ndarray) -> DataFrame:
    """id, v: content latents of a stream (or table) of new items; they can be recommended at once."""
    return embed(features, e)


def running_accuracy(purchases: DataFrame, lists: DataFrame, k: int = 10) -> DataFrame:
    """hits and tests of later purchases against standing lists (user_id, item_id, rank)."""
    known = lists.where(F.col("rank") <= k).select("user_id", "item_id", F.lit(1).alias("hit"))
    return purchases.join(known, ["user_id", "item_id"], "left").agg(F.count("hit").alias("hits"), F.count("*").alias("tests"))
