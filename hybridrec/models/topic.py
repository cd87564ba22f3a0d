"""Factorization with topic proportions as content side; needs nonnegative counts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from hybridrec.models import Model
from hybridrec.models.emf import ContentSide, EmfParams, fit_confidence
from hybridrec.runtime import materialize


def simplex(v: np.ndarray) -> np.ndarray:
    """Rows projected to the probability simplex."""
    s = -np.sort(-v, axis=1)
    c = (np.cumsum(s, 1) - 1) / np.arange(1, v.shape[1] + 1)
    rho = (s > c).sum(1) - 1
    return np.maximum(v - np.take_along_axis(c, rho[:, None], 1), 0)


class TopicSide(ContentSide):
    """Topics are learned once on the training items' counts; held-out items get theirs by inference.

    ``refine`` moves the proportions after every item step: up the count likelihood, towards the item's factor, on the simplex.
    """

    def __init__(self, counts: DataFrame, train_items: DataFrame, k: int, lam_v: float, iters: int, refine: bool, seed: int):
        from pyspark.ml.clustering import LDA
        from pyspark.ml.functions import array_to_vector

        if counts.where(F.exists("f", lambda x: x < 0)).limit(1).count():
            raise ValueError("topics need nonnegative counts")
        rows = counts.select("item_id", array_to_vector(F.col("f")).alias("features"))
        known = rows.join(train_items, "item_id", "left_semi")
        self.model = LDA(k=k, maxIter=iters, seed=seed, featuresCol="features", optimizer="online", subsamplingRate=1.0).fit(known)
        self.theta = materialize(self._proportions(rows), "topics")
        self.counts, self.lam_v, self.refine = counts, lam_v, refine
        self.topics = np.array(self.model.topicsMatrix().toArray())
        self.topics /= np.maximum(self.topics.sum(0), 1e-12)

    def _proportions(self, rows):
        from pyspark.ml.functions import vector_to_array

        return self.model.transform(rows).select(F.col("item_id").alias("id"), vector_to_array("topicDistribution").alias("v"))

    def fit(self, factors):
        if not self.refine:
            return
        shared = self.counts.sparkSession.sparkContext.broadcast((self.topics, self.lam_v))
        rows = self.theta.join(self.counts.withColumnRenamed("item_id", "id"), "id").join(factors.select("id", F.col("v").alias("h")), "id", "left")

        def run(batches):
            topics, lam = shared.value
            for pdf in batches:
                theta, f = np.array(pdf["v"].tolist(), float), np.array(pdf["f"].tolist(), float)
                has = pdf["h"].notna().to_numpy()
                h = np.array([x if ok else t for x, ok, t in zip(pdf["h"], has, theta, strict=True)], float)
                for _ in range(10):
                    up = (f / np.maximum(theta @ topics.T, 1e-12)) @ topics
                    theta = np.where(has[:, None], simplex(theta + 0.02 / (1 + lam) * (up - lam * (theta - h))), theta)
                yield pd.DataFrame({"id": pdf["id"], "v": list(theta)})

        self.theta = materialize(rows.mapInPandas(run, "id long, v array<double>"), "topics")

    def transform(self):
        return self.theta


def fit_topic_hybrid(train: DataFrame, counts: DataFrame, p: EmfParams = EmfParams(), lda_iters: int = 20, refine: bool = False) -> Model:
    """``counts``: (item_id, f) with nonnegative entries."""
    counts = materialize(counts, "counts")
    return fit_confidence(train, TopicSide(counts, train.select("item_id").distinct(), p.k, p.lam_v, lda_iters, refine, p.seed), p)
