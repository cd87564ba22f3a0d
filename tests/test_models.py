"""Models, fusion and protocol against dense algebra and worked examples."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridrec.evaluation import split as sp
from hybridrec.evaluation.accuracy import accuracy_at, chance
from hybridrec.evaluation.topk import recommend, recommend_sql
from hybridrec.features import audio, encode, reduce, text
from hybridrec.functions import portable_hash, signed_sqrt
from hybridrec.fusion import early, late
from hybridrec.linalg import gram, half_step, layout
from hybridrec.models import io
from hybridrec.models.bpr import BprParams, pairwise_batch, sample_triples
from hybridrec.models.dae import DaeParams, coupled_loss
from hybridrec.models.emf import EmfParams, fit_emf, objective, solve_embedding
from hybridrec.models.mlp import regression_loss
from hybridrec.models.nets import flat, init_layers, unflat
from hybridrec.models.topic import simplex
from hybridrec.models.wmf import fit_wmf


def factors(spark, rows):
    return spark.createDataFrame([(i, [float(x) for x in v]) for i, v in rows], "id long, v array<double>")


def test_half_step_by_hand(spark):
    pos = layout(spark.createDataFrame([(1, 2)], "user_id long, item_id long"), "user_id", "item_id")
    w = half_step(pos, factors(spark, [(1, [1]), (2, [2])]), 1, 0.1).collect()
    assert [round(r["v"][0], 6) for r in w] == [0.486618]
    by_item = layout(spark.createDataFrame([(1, 7)], "user_id long, item_id long"), "item_id", "user_id")
    h = half_step(by_item, factors(spark, [(1, [1]), (2, [-1])]), 1, 10.0, prior=factors(spark, [(7, [0.2]), (8, [0.2])])).collect()
    assert {r["id"]: round(r["v"][0], 6) for r in h} == {7: 0.27248, 8: 0.199601}


@pytest.mark.parametrize("strategy", ["broadcast", "routed", "sql"])
def test_half_step_equals_dense_confidence(spark, strategy, monkeypatch):
    import hybridrec.linalg as linalg

    monkeypatch.setattr(linalg, "HOT", 6)
    rng = np.random.default_rng(0)
    k, users, items = 3, 12, 15
    h, r = rng.normal(size=(items, k)), rng.random((users, items)) < 0.3
    r[0] = True  # beyond HOT: the row is salted
    r[5] = False
    p = rng.normal(size=(users, k))
    pairs = spark.createDataFrame([(int(u), int(i)) for u, i in zip(*np.nonzero(r), strict=True)], "user_id long, item_id long")
    prior = factors(spark, enumerate(p))
    got = {x["id"]: np.array(x["v"]) for x in half_step(layout(pairs, "user_id", "item_id", 4), factors(spark, enumerate(h)), k, 2.0, prior=prior, strategy=strategy).collect()}
    plain = {x["id"]: np.array(x["v"]) for x in half_step(layout(pairs, "user_id", "item_id", 4), factors(spark, enumerate(h)), k, 2.0, strategy=strategy).collect()}
    assert set(plain) == set(range(users)) - {5}
    for u in range(users):
        c = np.where(r[u], 1.0, 0.01)
        left = (h.T * c) @ h + 2.0 * np.eye(k)
        assert np.allclose(got[u], np.linalg.solve(left, h.T @ (c * r[u]) + 2.0 * p[u]), atol=1e-9)
        if u != 5:
            assert np.allclose(plain[u], np.linalg.solve(left, h.T @ (c * r[u])), atol=1e-9)


def test_embedding_solvers_agree(spark):
    rng = np.random.default_rng(1)
    f, h = rng.normal(size=(30, 6)), rng.normal(size=(30, 2))
    feats = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(f)], "item_id long, f array<double>")
    dense = np.linalg.solve(10 * f.T @ f + 7 * np.eye(6), 10 * f.T @ h)
    for solver in ("direct", "dual", "cg"):
        assert np.allclose(solve_embedding(feats, factors(spark, enumerate(h)), 10, 7, 2, solver), dense, atol=1e-7), solver
    one = spark.createDataFrame([(0, [1.0]), (1, [2.0])], "item_id long, f array<double>")
    assert abs(solve_embedding(one, factors(spark, [(0, [0.5]), (1, [1.0])]), 10, 1000, 1)[0, 0] - 0.0238095) < 1e-6


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(2)
    f = rng.normal(size=(25, 4))
    pairs = [(u, i) for u in range(20) for i in range(25) if f[i, u % 4] > 0.7 or rng.random() < 0.05]
    train = spark.createDataFrame(pairs, "user_id long, item_id long").cache()
    feats = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(f)], "item_id long, f array<double>").cache()
    return train, feats, pairs, f


def test_objective_falls_and_equals_the_double_sum(spark, small):
    train, feats, pairs, f = small
    p = EmfParams(k=3, iters=4, lam_e=10.0, tol=1e-12)
    m = fit_emf(train, feats, p)
    values = [x["objective"] for x in m.history]
    assert all(b <= a + 1e-9 for a, b in zip(values, values[1:], strict=False))
    w = {r["id"]: np.array(r["v"]) for r in m.user_factors.collect()}
    h = {r["id"]: np.array(r["v"]) for r in m.item_factors.collect()}
    e, liked = m.extra["side"].e, set(pairs)
    total = sum((1.0 if (u, i) in liked else 0.01) / 2 * (w[u] @ h[i] - ((u, i) in liked)) ** 2 for u in w for i in h)
    total += 0.05 * sum(v @ v for v in w.values()) + 5 * sum(((v - f[i] @ e) ** 2).sum() for i, v in h.items()) + 5 * (e**2).sum()
    assert abs(total - values[-1]) < 1e-6


def test_zero_content_is_the_plain_model(spark, small):
    train, feats, *_ = small
    zero = feats.withColumn("f", F.transform("f", lambda x: x * 0.0))
    p = EmfParams(k=2, iters=2)
    a, b = fit_emf(train, zero, p), fit_wmf(train, p)
    va, vb = ({r["id"]: r["v"] for r in m.item_factors.collect()} for m in (a, b))
    assert all(np.allclose(va[i], vb[i]) for i in va)


def test_stacking_reaches_concatenation(spark, small):
    train, feats, *_ = small
    parts = {"a": feats.select("item_id", F.slice("f", 1, 2).alias("f")), "b": feats.select("item_id", F.slice("f", 3, 2).alias("f"))}
    p = EmfParams(k=2, iters=2, lam_e=10.0)
    one, two = early.fit_concat(train, parts, p), early.fit_stack(train, parts, p, sweeps=12)
    a, b = ({r["id"]: r["v"] for r in m.content_latents.collect()} for m in (one, two))
    assert all(np.allclose(a[i], b[i], atol=1e-5) for i in a)


def test_predictor_routes_by_branch_and_survives_saving(spark, small, tmp_path):
    train, feats, *_ = small
    m = fit_emf(train.where("item_id < 20"), feats, EmfParams(k=2, iters=2, lam_e=10.0))
    pairs = spark.createDataFrame([(1, 3), (1, 22)], "user_id long, item_id long")
    rows = {r["item_id"]: r for r in m.predict(pairs).collect()}
    assert (rows[3]["branch"], rows[22]["branch"]) == ("in", "out")
    assert abs(rows[22]["score"] - m.predict_out(pairs.where("item_id = 22")).collect()[0]["score"]) < 1e-12
    again = io.load(spark, io.save(m, str(tmp_path)))
    assert sorted(r["score"] for r in again.predict(pairs).collect()) == sorted(r["score"] for r in rows.values())


def test_weights_example_and_dominance(spark):
    acc = spark.createDataFrame([("a", 0.4), ("b", 0.3), ("c", 0.2), ("d", 0.1)], "feature string, accuracy double")
    assert [round(r["weight"], 6) for r in late.priority_weights(acc).orderBy("position").collect()] == [0.5, 0.25, 0.125, 0.0625]
    assert [round(r["weight"], 6) for r in late.priority_weights(acc, 0.8).orderBy("position").collect()] == [0.8, 0.16, 0.032, 0.0064]
    with pytest.raises(ValueError):
        late.priority_weights(acc, 0.3)
    assert not late.dominates(late.priority_weights(acc, 0.3, strict=False)).where("position = 1").collect()[0]["holds"]
    assert late.dominates(late.priority_weights(acc, 0.5)).where("not holds").count() == 0


def test_missing_features_and_vector_form(spark):
    scores = spark.createDataFrame([("a", 1, 1, 2.0)], "feature string, user_id long, item_id long, score double")
    w = spark.createDataFrame([("a", 1, 0.5), ("b", 2, 0.25)], "feature string, position int, weight double")
    assert late.fuse(scores, w).count() == 0
    assert late.fuse(scores, w, "zero").collect()[0]["score"] == 1.0
    assert late.fuse(scores, w, "renormalize").collect()[0]["score"] == 1.5


def test_accuracy_is_pooled(spark):
    recs = spark.createDataFrame([(1, 10, 1), (1, 11, 2), (2, 12, 1), (2, 10, 2)], "user_id long, item_id long, rank int")
    test = spark.createDataFrame([(1, 11), (2, 10), (2, 13)], "user_id long, item_id long")
    assert {r["k"]: (r["hits"], r["tests"]) for r in accuracy_at(recs, test, (1, 2)).collect()} == {1: (0, 3), 2: (2, 3)}
    assert chance(40, 10) == 0.25


def test_blocked_lists_equal_all_pairs(spark, monkeypatch):
    import hybridrec.evaluation.topk as topk

    monkeypatch.setattr(topk, "ITEM_BLOCK", 7)
    monkeypatch.setattr(topk, "USER_BLOCK", 3)
    rng = np.random.default_rng(3)
    u, i = factors(spark, enumerate(rng.integers(-2, 3, (8, 2)))), factors(spark, enumerate(rng.integers(-2, 3, (30, 2))))
    seen = spark.createDataFrame([(0, 1), (0, 2), (3, 29)], "user_id long, item_id long")
    a, b = ({(r["user_id"], r["rank"]): (r["item_id"], r["score"]) for r in f(u, i, seen, 5).collect()} for f in (recommend, recommend_sql))
    assert a == b


@pytest.mark.parametrize(("sf_", "sizes"), [("sf0.001", (697, 255, 218)), ("sf0.01", (7232, 2356, 2311))])
def test_split_sizes(spark, sf_, sizes):
    from hybridrec.interactions import positives

    split = sp.make_split(positives(spark, f"/root/testdata/{sf_}", "quantity"), strict=False)
    n = {r["split"]: r["n"] for r in split.groupBy("split").agg(F.count("*").alias("n")).collect()}
    assert (n["train"], n["in_test"], n["out_test"]) == sizes


def test_encodings(spark):
    assert spark.range(1).select(signed_sqrt(F.array(F.lit(4.0), F.lit(-9.0), F.lit(0.0))).alias("v")).collect()[0]["v"] == [2.0, -3.0, 0.0]
    desc = spark.createDataFrame([(1, 0, [1.0, 0.0]), (1, 1, [0.0, 2.0]), (1, 2, [9.0, 10.0])], "item_id long, frame int, vec array<double>")
    assert encode.vlad_vectors(desc, np.array([[0.0, 0.0], [10.0, 10.0]]), normalize=False).collect()[0]["f"] == [1.0, 2.0, -1.0, 0.0]
    g = encode.fit_diag_gmm(desc, 2, 3)
    assert len(encode.fisher_vectors(desc, g).collect()[0]["f"]) == 8


def test_principal_components(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(40, 5)) * [5, 3, 1, 0.5, 0.1]
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "item_id long, f array<double>")
    fits = [reduce.fit_pca(df, 2, m, passes=8) for m in ("exact", "dual", "randomized")]
    for p in fits:
        assert np.allclose(p.axes, fits[0].axes, atol=1e-6) and np.allclose(p.axes.T @ p.axes, np.eye(2), atol=1e-9)


def test_audio():
    t = np.arange(16_000) / 16_000
    m = audio.cepstral_matrix(np.sin(2 * np.pi * 440 * t))
    assert m.shape == (98, 40) and np.isfinite(m).all()
    assert audio.cepstral_matrix(np.zeros(10)).shape == (0, 40)


def test_tfidf_order(spark):
    tokens = spark.createDataFrame([(1, ["a", "a", "b"]), (2, ["a", "c"]), (3, ["c", "c", "c"])], "item_id long, tokens array<string>")
    assert [r["term"] for r in text.tfidf_vocabulary(tokens, 2).orderBy("term_id").collect()] == ["c", "a"]


@pytest.mark.parametrize("which", ["mlp", "gaussian", "binary"])
def test_net_gradients(which):
    import pandas as pd

    rng = np.random.default_rng(5)
    x = rng.random((6, 4))
    pdf = pd.DataFrame({"item_id": range(6), "f": list(x), "v": list(rng.normal(size=(6, 2)))})
    layers = init_layers([4, 5, 2], 0) if which == "mlp" else init_layers([4, 5, 2, 5, 4], 0)
    loss = regression_loss if which == "mlp" else coupled_loss(DaeParams(lam_n=3.0, visible=which, corruption=0.0), 2.0, 1)
    v, g = flat(layers), flat(loss(layers, pdf)[1])
    for i in range(0, len(v), 3):
        up, down = v.copy(), v.copy()
        up[i] += 1e-6
        down[i] -= 1e-6
        assert abs((loss(unflat(up, layers), pdf)[0] - loss(unflat(down, layers), pdf)[0]) / 2e-6 - g[i]) < 1e-4


def test_pairwise_gradients():
    import pandas as pd

    rng = np.random.default_rng(6)
    k, d = 2, 3
    row = {c: [rng.normal(size=k)] for c in ("w", "u", "hi", "hj")} | {c: [rng.normal(size=d)] for c in ("fi", "fj")} | {"bi": [0.1], "bj": [-0.2]}
    e, beta = rng.normal(size=(d, k)), rng.normal(size=d)
    p = BprParams(k=k, lam_u=0, lam_i=0, lam_j=0, lam_p=0)
    g = pairwise_batch(pd.DataFrame(row), e, beta, p)
    for name, i in (("w", 0), ("u", 1), ("hi", 0), ("hj", 1)):
        up = {c: [np.array(v[0], copy=True)] if c not in ("bi", "bj") else v for c, v in row.items()}
        up[name][0][i] += 1e-6
        assert abs((pairwise_batch(pd.DataFrame(up), e, beta, p)["loss"] - g["loss"]) / 1e-6 - g[name][0][i]) < 1e-4
    e2 = e.copy()
    e2[1, 1] += 1e-6
    assert abs((pairwise_batch(pd.DataFrame(row), e2, beta, p)["loss"] - g["loss"]) / 1e-6 - g["e"][1, 1]) < 1e-4


def test_sampled_negatives_are_no_positives(spark, small):
    train, _, pairs, _ = small
    liked = set(pairs)
    rows = sample_triples(train, 1, 3).collect()
    assert rows and all((r["user_id"], r["i"]) in liked and (r["user_id"], r["j"]) not in liked for r in rows)


def test_simplex():
    v = simplex(np.array([[0.2, 0.9, -1.0], [5.0, 0.0, 0.0]]))
    assert np.allclose(v.sum(1), 1) and (v >= 0).all()


def test_gram_and_hash(spark):
    rng = np.random.default_rng(7)
    x = rng.normal(size=(50, 3))
    assert np.allclose(gram(factors(spark, enumerate(x)), 3), x.T @ x)
    h = spark.range(5).select(portable_hash(F.lit(0), F.col("id"), 7).alias("h")).collect()
    assert len({r["h"] for r in h}) == 5


def test_objective_of_nothing(spark, small):
    train, *_ = small
    m = fit_wmf(train, EmfParams(k=1, iters=1))
    assert objective(train, m.user_factors, m.item_factors, None, EmfParams(k=1)) > 0
