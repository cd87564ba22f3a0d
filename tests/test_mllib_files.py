"""Spark's own solver keeps no shuffle files of past iterations."""

import os
import re

from hybridrec.models.wmf import fit_mllib


def _shuffles(spark):
    dirs = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    return {m[1] for top in dirs for _, _, names in os.walk(top) for f in names if (m := re.match(r"shuffle_(\d+)_.*\.data$", f))}


def test_iterations_do_not_leave_their_shuffle_files(spark):
    train = spark.createDataFrame([(u, i) for u in range(40) for i in range(25) if (u * 7 + i * 5) % 4 == 0], "user_id long, item_id long")
    before = _shuffles(spark)
    model = fit_mllib(train, 3, iters=8)
    assert len(_shuffles(spark) - before) < 8  # two an iteration otherwise
    assert model.user_factors.count() == 40 and model.item_factors.count() == 25
