"""What positives and folds move and leave on disk."""

import os

from pyspark.sql import functions as F

from hybridrec import interactions
from hybridrec.evaluation.cv import cross_validate
from hybridrec.runtime import materialize, shared_dir
from hybridrec.sources import table


def test_only_lines_at_the_top_are_joined(spark, sf):
    want = interactions.to_implicit(interactions.ratings(spark, sf))
    got = interactions.positives(spark, sf, "quantity")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    for df, early in ((want, False), (got, True)):
        plan = df._jdf.queryExecution().optimizedPlan().toString()
        assert (">= 5" in plan[plan.index("Join") :]) is early


def test_top_positives_of_odd_lines(spark):
    lines = spark.createDataFrame([(1, 7, 3.0), (1, 7, 50.0), (2, 7, 41.0), (2, 8, 40.0), (3, 9, None), (4, 9, 99.0), (9, 9, 50.0)], "l_orderkey long, l_partkey long, l_quantity double")
    orders = spark.createDataFrame([(1, 5), (2, 5), (3, 5), (4, 6)], "o_orderkey long, o_custkey long")
    assert sorted(map(tuple, interactions.top_positives(lines, orders).collect())) == [(5, 7), (6, 9)]


def test_folds_leave_only_their_accuracies(spark, sf):
    stages = lambda: {x for x in os.listdir(shared_dir(spark).removeprefix("file://")) if x.startswith("stage-")}
    positives = materialize(interactions.positives(spark, sf, "quantity").where("user_id % 3 = 0"), "positives")
    before = stages()

    def one(split):
        split = materialize(split, "fold")
        return split.groupBy(F.col("split").alias("scenario")).agg((F.count("*") / 100).alias("accuracy")).withColumn("k", F.lit(1))

    rows = cross_validate(positives, one).collect()
    assert {r["folds"] for r in rows} == {5} and {r["scenario"] for r in rows} == {"train", "in_test", "out_test"}
    left = stages() - before
    assert len(left) == 5 and all(x.startswith("stage-fold-accuracy") for x in left)
