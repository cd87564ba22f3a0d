"""Triples with content move as ids and slopes, and give the gradients of the joined vectors."""

import re

import numpy as np
from pyspark.sql import functions as F

from hybridrec.models import bpr


def _tables(spark, p, users=9, items=7):
    rng = np.random.default_rng(3)
    w = spark.createDataFrame([(u, rng.normal(size=2 * p.k).tolist()) for u in range(users)], "id long, v array<double>")
    own = spark.createDataFrame([(i, rng.normal(size=p.k).tolist(), float(rng.normal()), rng.normal(size=p.k + 1).tolist()) for i in range(items)], "id long, v array<double>, b double, c array<double>")
    triples = [(u, i, (i * 3 + u) % (items + 1)) for u in range(users + 1) for i in range(items) if (u + i) % 2 and (i * 3 + u) % (items + 1) != i]  # a user and an item are unknown
    return w, own, spark.createDataFrame(triples, "user_id long, i long, j long"), len(triples)


def test_slopes_give_the_gradients_of_joined_vectors(spark, monkeypatch):
    monkeypatch.setattr(bpr, "TRIPLES_A_TASK", 5)
    monkeypatch.setattr(bpr, "ROLES_A_TASK", 11)
    p = bpr.BprParams(k=3, lam_b=0.1)
    w, own, triples, n = _tables(spark, p)
    want, got = bpr._content_joined(w, own, triples, p), bpr._content_sent(w, own, triples, p, w.count(), own.count(), n)
    assert np.isclose(got[2], want[2])
    for a, b in zip(want[:2], got[:2], strict=True):
        a, b = ({r["id"]: r["g"] for r in df.collect()} for df in (a, b))
        assert a.keys() == b.keys() and all(np.allclose(a[x], b[x]) for x in a)


def test_no_item_vector_moves_with_triples(spark, sf, monkeypatch):
    plans, real = {}, bpr.materialize
    monkeypatch.setattr(bpr, "materialize", lambda df, name: plans.setdefault(name, df._jdf.queryExecution().executedPlan().toString()) and real(df, name))
    train = spark.createDataFrame([(u, i) for u in range(6) for i in (u, u + 1, u * 7 % 20)], "user_id long, item_id long").distinct()
    features = spark.range(20).select(F.col("id").alias("item_id"), F.array(F.col("id") * 0.1, F.lit(1.0)).alias("f"))
    bpr.fit_content_bpr(train, features, bpr.BprParams(k=2, epochs=1, batches=1))
    joins = {n: len(re.findall(r"SortMergeJoin|HashJoin", plans[n].split("Initial Plan")[0])) for n in ("gradients", "item-sums")}
    assert joins == {"gradients": 1, "item-sums": 0}
