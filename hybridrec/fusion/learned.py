"""Late fusion with weights learned to rank."""

from __future__ import annotations

from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from hybridrec.evaluation.topk import SENT_BYTES
from hybridrec.functions import M, dot, portable_hash, portable_hash_line
from hybridrec.models import Model
from hybridrec.runtime import materialize

SCALE = 1_000_000


def points(scores: DataFrame, positives: DataFrame, features: list[str], neg_ratio: int = 4, seed: int = 31) -> DataFrame:
    """user_id, item_id, x (scores by feature), label: all positives, and per user about ``neg_ratio`` hashed negatives for each."""
    wide = scores.groupBy("user_id", "item_id").pivot("feature", features).agg(F.first("score")).select("user_id", "item_id", F.array(*features).alias("x"))
    wide = wide.where(~F.exists("x", lambda v: v.isNull()))
    liked = positives.select("user_id", "item_id", F.lit(1.0).alias("label"))
    marked = wide.join(liked, ["user_id", "item_id"], "left").withColumn("label", F.coalesce("label", F.lit(0.0)))
    w = Window.partitionBy("user_id")
    counted = marked.withColumn("np", F.sum("label").over(w)).withColumn("nn", F.sum(1 - F.col("label")).over(w)).where("np > 0")
    share = neg_ratio * F.col("np") / F.col("nn")
    chosen = portable_hash(F.col("user_id"), F.col("item_id"), seed) % SCALE < share * SCALE
    return counted.where((F.col("label") == 1) | chosen).select("user_id", "item_id", "x", "label")


class _Draws:
    """Items by the last six digits of their part of the hash, so that the ones a user's hash puts below a bound lie in two runs."""

    def __init__(self, ids: np.ndarray, seed: int):
        self.p, self.k, self.c = portable_hash_line(seed)
        own = ids % M * self.k % M
        order = np.argsort(own % SCALE, kind="stable")
        self.ids, self.own = ids[order], own[order]
        digits = self.own % SCALE
        self.twice = np.concatenate([digits, digits + SCALE])  # a run may pass the end

    def below(self, users: np.ndarray, bound: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places in ``users``, and items, of the pairs whose hash modulo ``SCALE`` is less than the user's bound."""
        base = (users % M * self.p % M * self.k + self.c) % M
        whole = np.minimum(np.ceil(bound), SCALE).astype(np.int64)
        rows, items = [], []
        for over in (False, True):  # whether the sum of both parts reaches M
            first = -(base - M * over) % SCALE
            a, b = np.searchsorted(self.twice, first), np.searchsorted(self.twice, first + whole)
            n = b - a
            r = np.repeat(np.arange(len(users)), n)
            at = (np.arange(len(r)) - np.repeat(np.cumsum(n) - n, n) + np.repeat(a, n)) % max(len(self.ids), 1)
            ok = (self.own[at] + base[r] >= M) == over
            rows.append(r[ok])
            items.append(self.ids[at[ok]])
        return np.concatenate(rows), np.concatenate(items)


def sampled_points(models: dict[str, Model], positives: DataFrame, neg_ratio: int = 4, seed: int = 31) -> DataFrame:
    """The rows of ``points`` for the scores of ``models`` on all users and items of ``positives``, without those scores.

    Which negatives a user gets follows from hashes alone, so they are looked up among the items' hashes, and only chosen pairs are scored:
    the work follows the positives and not the product of users and items.
    """
    known = lambda get, column: materialize(reduce(lambda a, b: a.join(b, "id"), [get(m).select("id") for m in models.values()]).join(positives.select(F.col(column).alias("id")), "id", "left_semi"), "known-ids")
    users, pool = known(lambda m: m.user_factors, "user_id"), known(lambda m: m.content_latents, "item_id")
    liked = positives.select("user_id", "item_id").distinct().join(users.withColumnRenamed("id", "user_id"), "user_id", "left_semi").join(pool.withColumnRenamed("id", "item_id"), "item_id", "left_semi")
    liked = materialize(liked.select("user_id", "item_id"), "liked")
    n, spark = pool.count(), pool.sparkSession
    need = liked.groupBy("user_id").agg(F.count("*").alias("np")).where(F.col("np") < n)
    need = materialize(need.select("user_id", (neg_ratio * F.col("np").cast("double") / (F.lit(n) - F.col("np")) * SCALE).alias("bound")), "bounds")
    parts = max(1, -(-n * 32 // SENT_BYTES))

    def drawn(at):
        own = pool if parts == 1 else pool.where(F.pmod(F.xxhash64("id", F.lit(5)), F.lit(parts)) == at)
        shared = spark.sparkContext.broadcast(own.toArrow().column("id").to_numpy())  # bounded by SENT_BYTES

        def run(batches):
            draws = _Draws(shared.value, seed)
            for batch in batches:
                u, bound = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
                each = np.cumsum(np.minimum(bound / SCALE, 1.0) * len(draws.ids) + 1) // 500_000  # users whose draws are about as many rows
                for cut in np.split(np.arange(len(u)), np.flatnonzero(np.diff(each)) + 1):
                    r, items = draws.below(u[cut], bound[cut])
                    yield pa.RecordBatch.from_arrays([pa.array(u[cut][r]), pa.array(items)], names=["user_id", "item_id"])

        return need.mapInArrow(run, "user_id long, item_id long")

    others = reduce(DataFrame.unionByName, [drawn(at) for at in range(parts)]).join(liked, ["user_id", "item_id"], "left_anti")
    rows = materialize(liked.withColumn("label", F.lit(1.0)).unionByName(others.withColumn("label", F.lit(0.0))), "pairs")
    for i, m in enumerate(models.values()):
        both = rows.join(m.user_factors.select(F.col("id").alias("user_id"), F.col("v").alias("w")), "user_id").join(m.content_latents.select(F.col("id").alias("item_id"), F.col("v").alias("h")), "item_id")
        rows = materialize(both.select(*rows.columns, dot(F.col("w"), F.col("h")).alias(f"x{i}")), "scored")
    return rows.select("user_id", "item_id", F.array(*[f"x{i}" for i in range(len(models))]).alias("x"), "label")


def _weights(spark, features, values) -> DataFrame:
    rows = [(f, i + 1, float(v)) for i, (f, v) in enumerate(sorted(zip(features, values, strict=True), key=lambda t: (-t[1], t[0])))]
    return spark.createDataFrame(rows, "feature string, position int, weight double")


def pointwise_weights(pts: DataFrame, features: list[str], reg: float = 0.01, iters: int = 50) -> DataFrame:
    """Coefficients of a linear hinge classifier of positives against negatives."""
    from pyspark.ml.classification import LinearSVC
    from pyspark.ml.functions import array_to_vector

    m = LinearSVC(regParam=reg, maxIter=iters, featuresCol="v", labelCol="label").fit(pts.select(array_to_vector("x").alias("v"), "label"))
    return _weights(pts.sparkSession, features, m.coefficients.toArray())


def pairwise_weights(pts: DataFrame, features: list[str], reg: float = 0.01, iters: int = 50) -> DataFrame:
    """Coefficients of a logistic model on score differences of each user's positives and negatives, both signs, no intercept."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    pos, neg = pts.where("label = 1").select("user_id", F.col("x").alias("p")), pts.where("label = 0").select("user_id", F.col("x").alias("n"))
    diff = pos.join(neg, "user_id").select(F.zip_with("p", "n", lambda a, b: a - b).alias("d"))
    both = diff.select("d", F.lit(1.0).alias("label")).unionByName(diff.select(F.transform("d", lambda a: -a).alias("d"), F.lit(0.0).alias("label")))
    m = LogisticRegression(regParam=reg, maxIter=iters, fitIntercept=False, standardization=False, featuresCol="v", labelCol="label").fit(both.select(array_to_vector("d").alias("v"), "label"))
    return _weights(pts.sparkSession, features, m.coefficients.toArray())
