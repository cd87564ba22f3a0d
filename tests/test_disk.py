"""What queries leave on disk and move through exchanges."""

import os
import re

from pyspark.sql import functions as F

from hybridrec.features.descriptors import blend_vectors, blended, descriptor_sets
from hybridrec.models.simple import content_profile
from hybridrec.runtime import materialize


def _shuffle_files(spark):
    dirs = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()
    return {f for top in dirs for d, _, names in os.walk(top) for f in names if f.startswith("shuffle_")}


def test_materialize_leaves_no_shuffle_files(spark):
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    was = spark.conf.get(key, None)
    out = materialize(spark.range(5000).groupBy((F.col("id") % 700).alias("k")).count(), "counted")
    assert out.count() == 700
    assert spark.conf.get(key, None) == was
    before = _shuffle_files(spark)
    kept = materialize(out.repartition(7, "k").withColumn("v", F.lit(1)), "dealt")
    assert not [f for f in _shuffle_files(spark) - before if f.endswith(".data")]
    assert kept.count() == 700


def _exchanges(df):
    return [x for x in df._jdf.queryExecution().executedPlan().toString().splitlines() if "Exchange hashpartitioning" in x]


def test_item_vectors_of_a_small_table_take_no_exchange(spark, sf):
    assert not _exchanges(blend_vectors(spark, sf))
    assert not _exchanges(descriptor_sets(spark, sf))


def test_profiles_move_pairs_and_no_vectors(spark, sf):
    train = spark.createDataFrame([(u, i) for u in range(6) for i in (u, u + 1, u * 7 % 150, 10**9)], "user_id long, item_id long").distinct()
    features = materialize(blend_vectors(spark, sf), "blend")
    plain, _ = content_profile(train, features)
    users, _ = content_profile(train, features, lambda rows: blended(rows, spark, sf))
    want, got = ({r["id"]: r["v"] for r in df.collect()} for df in (plain, users))
    assert want.keys() == got.keys() and len(want) == 6
    assert all(abs(a - b) < 1e-12 for u in want for a, b in zip(want[u], got[u], strict=True))
    again = re.compile(r"hashpartitioning\(user_id#\d+L, \d+\), ENSURE")  # sums that meet by an exchange of their own
    assert any(again.search(x) for x in _exchanges(plain)) and not any(again.search(x) for x in _exchanges(users))


def test_folds_share_positives_that_are_computed_once(spark, sf, monkeypatch):
    from hybridrec import catalogue
    from hybridrec.evaluation import cv

    monkeypatch.setattr(cv, "cross_validate", lambda positives, one: positives)
    positives = catalogue.cross_validated_popularity(spark, sf)
    assert not _exchanges(positives) and positives.columns == ["user_id", "item_id"]
