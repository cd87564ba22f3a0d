"""Five divisions and their mean."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, functions as F

from hybridrec.evaluation.split import make_split
from hybridrec.runtime import materialize, scratch


def cross_validate(positives: DataFrame, fn: Callable[[DataFrame], DataFrame], folds: int = 5) -> DataFrame:
    """Mean and deviation of accuracy per (scenario, k); ``fn`` takes a split and returns rows with scenario, k, accuracy. Of a fold only these rows stay."""
    runs = []
    for fold in range(folds):
        with scratch(positives.sparkSession) as used:
            runs.append(materialize(fn(make_split(positives, fold)).withColumn("fold", F.lit(fold)), "fold-accuracy"))
            used.pop()
    return reduce(DataFrame.unionByName, runs).groupBy("scenario", "k").agg(F.avg("accuracy").alias("accuracy"), F.stddev("accuracy").alias("deviation"), F.count("*").alias("folds"))
