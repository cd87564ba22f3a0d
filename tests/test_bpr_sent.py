"""Pairwise ranking without vectors in exchanges."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridrec.models import bpr
from hybridrec.models.bpr import BprParams, fit_bpr, sample_triples, step, step_sent


@pytest.fixture(scope="module")
def train(spark):
    return spark.createDataFrame([(u, i) for u in range(40) for i in range(25) if (u * 7 + i * 5) % 4 == 0], "user_id long, item_id long")


def vectors(df, *more):
    return {r["id"]: [*r["v"], *[r[m] for m in more]] for r in df.collect()}


def near(a, b):
    assert a.keys() == b.keys() and all(np.allclose(a[x], b[x], atol=1e-12) for x in a)


def test_sent_step_equals_the_joined_one(spark, train, monkeypatch):
    monkeypatch.setattr(bpr, "ROLES_A_TASK", 100)
    p = BprParams(k=3, lam_b=0.01)
    rng = np.random.default_rng(3)
    rows = lambda n: [(i, [float(x) for x in rng.normal(size=3)], float(rng.normal())) for i in range(n)]
    w, h = spark.createDataFrame(rows(41), "id long, v array<double>, b double").select("id", "v"), spark.createDataFrame(rows(24), "id long, v array<double>, b double")
    triples = sample_triples(train, 0, 5).where("user_id != 7").cache()  # an item and users without triples, and triples of an item without a vector
    want, got = step(w, h, triples, p), step_sent(w, h, triples, p, 41, 24, triples.count())
    near(vectors(got[0]), vectors(want[0]))
    near(vectors(got[1], "b"), vectors(want[1], "b"))


def test_fits_are_equal_and_move_no_vectors_with_triples(spark, train, monkeypatch):
    seen = []
    real = bpr.step
    monkeypatch.setattr(bpr, "step", lambda *a: seen.append(1) or real(*a))
    p = BprParams(k=3, epochs=2)
    sent = fit_bpr(train, p)
    assert not seen
    monkeypatch.setattr(bpr, "BROADCAST_BYTES", 0)
    joined = fit_bpr(train, p)
    assert len(seen) == 4
    near(vectors(sent.user_factors), vectors(joined.user_factors))
    near(vectors(sent.item_factors), vectors(joined.item_factors))


def test_tries_do_not_multiply_pairs(spark, train, monkeypatch):
    rows, real = [], bpr.materialize
    monkeypatch.setattr(bpr, "materialize", lambda df, name: (lambda out: rows.append((name, out.count())) or out)(real(df, name)))
    got = sample_triples(train.unionByName(train), 0, 5, retries=4)
    n = train.count()
    assert got.count() == n == got.select("user_id", "i").distinct().count()
    drawn = [x for name, x in rows if name == "drawn"]
    assert drawn[0] == n and all(a > b for a, b in zip(drawn, drawn[1:], strict=False)) and len(drawn) > 1
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert not re.search("Generate explode", plan) and got.where(F.col("batch") != 0).count() == 0
