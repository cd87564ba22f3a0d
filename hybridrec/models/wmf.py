"""Confidence-weighted factorization without content, and the library's own solver as a speed yardstick."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from hybridrec.models import Model
from hybridrec.models.emf import EmfParams, fit_confidence
from hybridrec.runtime import shared_dir

DEFAULTS = EmfParams(lam_u=0.01, lam_v=0.01)


def fit_wmf(train: DataFrame, p: EmfParams = DEFAULTS) -> Model:
    """Prior mean zero; scores items seen in training only."""
    return fit_confidence(train, None, p)


def fit_mllib(train: DataFrame, k: int = 50, reg: float = 0.01, iters: int = 10, alpha: float = 99.0, seed: int = 1) -> Model:
    """Spark's implicit ALS. It scales the penalty by row counts and weighs by 1 + alpha, so it is not the same model.

    Factors are written once an iteration into the shared folder, upon which Spark deletes the shuffle files of the one before.
    """
    from pyspark.ml.recommendation import ALS

    shared_dir(train.sparkSession)  # without one nothing is written
    m = ALS(rank=k, maxIter=iters, checkpointInterval=1, regParam=reg, alpha=alpha, implicitPrefs=True, userCol="user_id", itemCol="item_id", ratingCol="r", seed=seed).fit(train.withColumn("r", F.lit(1.0)))
    wide = lambda t: t.select(F.col("id").cast("long"), F.col("features").cast("array<double>").alias("v"))
    return Model(wide(m.userFactors), wide(m.itemFactors))
