"""Hits need only the wanted entries of the lists, and a prior meets its item's block."""

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridrec.evaluation import topk
from hybridrec.linalg import half_step, layout
from hybridrec.models.emf import EmfParams, fit_confidence
from hybridrec.runtime import discard, materialize


def _factors(spark, v):
    return spark.createDataFrame([(i, [float(y) for y in x]) for i, x in enumerate(v)], "id long, v array<double>")


@pytest.mark.parametrize("sent", [128 << 20, 500])
def test_wanted_entries_keep_their_ranks(spark, monkeypatch, sent):
    monkeypatch.setattr(topk, "SENT_BYTES", sent)
    monkeypatch.setattr(topk, "USER_BLOCK", 4)
    rng = np.random.default_rng(5)
    users, items = _factors(spark, rng.normal(size=(15, 3))), _factors(spark, rng.normal(size=(40, 3)))
    pairs = users.select(F.col("id").alias("user_id")).crossJoin(items.select(F.col("id").alias("item_id")))
    wanted, seen = pairs.where("(user_id + item_id) % 3 = 0 and user_id > 1"), pairs.where("(user_id + item_id) % 7 = 0")
    rows = lambda df: sorted(map(tuple, df.collect()))
    whole = topk.recommend(users, items, seen, 9).join(wanted, ["user_id", "item_id"]).select("user_id", "item_id", "score", "rank")
    got = rows(topk.recommend(users, items, seen, 9, wanted))
    assert got == rows(whole) and 0 < len(got) < 135


def test_no_sum_of_products_is_moved_to_a_prior(spark):
    rng = np.random.default_rng(2)
    pairs = spark.createDataFrame([(u, i) for u in range(12) for i in range(8) if (u * i) % 3 == 1], "user_id long, item_id long")
    by_item, w, prior = layout(pairs, "item_id", "user_id", 3), _factors(spark, rng.normal(size=(12, 2))), _factors(spark, rng.normal(size=(10, 2)))
    out = half_step(by_item, w, 2, 2.0, prior=prior)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and not re.search(r"Exchange.*\ba#", plan)
    got = {r["id"]: r["v"] for r in out.collect()}
    by_item.hot = True  # the way of ids whose sums are added up elsewhere
    want = {r["id"]: r["v"] for r in half_step(by_item, w, 2, 2.0, prior=prior).collect()}
    assert got.keys() == want.keys() == set(range(10)) and all(np.allclose(got[i], want[i], atol=1e-12) for i in got)


def test_past_iterations_leave_no_factors(spark, monkeypatch):
    import glob
    import os

    from hybridrec.runtime import shared_dir

    pairs = materialize(spark.createDataFrame([(u, i) for u in range(6) for i in (u, u + 1)], "user_id long, item_id long"), "pairs")
    before = set(glob.glob(f"{shared_dir(spark)}/stage-*"))
    m = fit_confidence(pairs, None, EmfParams(k=2, iters=3))
    assert m.user_factors.count() == 6 and m.item_factors.count() == 7
    left = [os.path.basename(x).split("-")[1] for x in set(glob.glob(f"{shared_dir(spark)}/stage-*")) - before]
    assert sorted(left) == ["h", "hot", "hot", "w"]
    discard(pairs)
    assert not os.path.exists(pairs.stage)


def test_taste_tells_pairs_apart_without_an_exchange_of_their_own(spark, sf):
    from hybridrec.interactions import taste_view

    plan = taste_view(spark, sf)._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[0]
    assert not re.search(r"Exchange hashpartitioning\((user_id#\d+L, item_id|item_id#\d+L, user_id)", plan)
