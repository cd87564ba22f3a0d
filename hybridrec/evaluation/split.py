"""Folds over items, then over the pairs of the other items: training, in-matrix and out-of-matrix tests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from hybridrec.functions import portable_hash

ITEM_SEED, PAIR_SEED = 7, 11


def item_fold(item: Column, n: int = 5, seed: int = ITEM_SEED) -> Column:
    return (portable_hash(F.lit(0), item, seed) % n).cast("int")


def item_folds(items: DataFrame, n: int = 5, seed: int = ITEM_SEED, exact: bool = False) -> DataFrame:
    """item_id, fold. By hash; ``exact`` makes equal folds by a global order, for small data only."""
    ids = items.select("item_id").distinct()
    if exact:
        return ids.select("item_id", (F.ntile(n).over(Window.orderBy(portable_hash(F.lit(0), F.col("item_id"), seed), "item_id")) - 1).alias("fold"))
    return ids.select("item_id", item_fold(F.col("item_id"), n, seed).alias("fold"))


def make_split(positives: DataFrame, fold: int = 0, item_seed: int = ITEM_SEED, pair_seed: int = PAIR_SEED, strict: bool = True) -> DataFrame:
    """user_id, item_id, split: ``out_test`` for the held-out item fold, a quarter of the rest ``in_test``, ``train`` otherwise.

    ``strict`` drops in-matrix test pairs whose item has no training pair. Nothing but that check shuffles.
    """
    user, item = F.col("user_id"), F.col("item_id")
    pair = portable_hash(user, item, pair_seed) % 4
    out = positives.select("user_id", "item_id", F.when(item_fold(item, seed=item_seed) == fold, "out_test").when(pair == 0, "in_test").otherwise("train").alias("split"))
    if not strict:
        return out
    known = out.where("split = 'train'").select("item_id").distinct()
    tested = out.where("split = 'in_test'").join(known, "item_id", "left_semi").select("user_id", "item_id", "split")
    return out.where("split != 'in_test'").unionByName(tested)


def part(split: DataFrame, name: str) -> DataFrame:
    return split.where(F.col("split") == name).select("user_id", "item_id")


def validation_cut(train: DataFrame, frac: float = 0.1, mode: str = "pair", seed: int = 13) -> DataFrame:
    """user_id, item_id, inner: ``valid`` for a share of the pairs, or of the items with all their pairs."""
    key = portable_hash(F.col("user_id"), F.col("item_id"), seed) if mode == "pair" else portable_hash(F.lit(0), F.col("item_id"), seed)
    return train.select("user_id", "item_id", F.when(key % 1000 < round(frac * 1000), "valid").otherwise("train").alias("inner"))


def check_split(split: DataFrame) -> DataFrame:
    """One row of violations: out-of-matrix items seen in training, in-matrix items unseen, pairs in two parts."""
    train = part(split, "train").select("item_id").distinct()
    out = part(split, "out_test").select("item_id").distinct()
    leaked = out.join(train, "item_id", "left_semi").agg(F.count("*").alias("out_items_in_train"))
    unseen = part(split, "in_test").join(train, "item_id", "left_anti").agg(F.count("*").alias("in_pairs_unseen"))
    twice = split.groupBy("user_id", "item_id").agg(F.count("*").alias("n")).where("n > 1").agg(F.count("*").alias("pairs_twice"))
    return leaked.crossJoin(unseen).crossJoin(twice)
