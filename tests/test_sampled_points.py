"""Learning-to-rank rows without the scores of all pairs."""

import numpy as np
from pyspark.sql import functions as F

from hybridrec import catalogue
from hybridrec.evaluation.topk import all_scores
from hybridrec.functions import portable_hash
from hybridrec.fusion import learned
from hybridrec.models import Model


def test_draws_are_those_of_the_hash(spark):
    users, items = np.array([0, 3, 7, 2**31 + 5, 10**9]), np.arange(0, 40_000, 7) * 977
    bound = np.array([1000.0, 20.5, 0.0, 3_000_000.0, 999_999.5])
    pairs = spark.createDataFrame([(int(u),) for u in users], "u long").crossJoin(spark.createDataFrame([(int(i),) for i in items], "i long"))
    h = {(r["u"], r["i"]): r["h"] for r in pairs.withColumn("h", portable_hash(F.col("u"), F.col("i"), 31) % 1_000_000).collect()}
    want = {(u, i) for u, b in zip(users, bound, strict=True) for i in items if h[u, i] < b}
    r, got = learned._Draws(items, 31).below(users, bound)
    assert len(got) == len(want) and set(zip(users[r], got, strict=True)) == want


def test_sampled_points_equal_those_of_all_scores(spark):
    rng = np.random.default_rng(0)
    table = lambda ids: spark.createDataFrame([(int(i), rng.normal(0, 1, 3).tolist()) for i in ids], "id long, v array<double>")
    a, b = (Model(table(range(n)), table(range(40)), table(range(lo, 300))) for n, lo in ((25, 0), (30, 4)))  # some lack a side in one model
    valid = spark.createDataFrame(sorted({(int(u), int(i)) for u, i in zip(rng.integers(0, 32, 200), rng.integers(0, 310, 200), strict=True)}), "user_id long, item_id long")
    users, pool = valid.select(F.col("user_id").alias("id")).distinct(), valid.select(F.col("item_id").alias("id")).distinct()
    scores = [all_scores(m.user_factors.join(users, "id", "left_semi"), m.content_latents.join(pool, "id", "left_semi")).withColumn("feature", F.lit(f)) for f, m in (("a", a), ("b", b))]
    want, got = ({(r["user_id"], r["item_id"], r["label"]): r["x"] for r in df.collect()} for df in (learned.points(scores[0].unionByName(scores[1]), valid, ["a", "b"], 2), learned.sampled_points({"a": a, "b": b}, valid, 2)))
    assert want.keys() == got.keys() and len({k[2] for k in want}) == 2
    assert max(abs(x - y) for k in want for x, y in zip(want[k], got[k], strict=True)) < 1e-12


def test_learned_weights_score_no_table_of_all_pairs(spark, sf, monkeypatch):
    def never(*_):
        raise AssertionError("all pairs")

    monkeypatch.setattr(catalogue, "all_scores", never)
    pts, _ = catalogue._validation_points(spark, sf, ("audio", "scene"))
    assert {r["label"] for r in pts.select("label").distinct().collect()} == {0.0, 1.0}
