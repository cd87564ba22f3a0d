"""Text rules, recovery of a simulated draw, five divisions, network gradients summed over tasks, late rows and restarts of streams."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridrec.evaluation.cv import cross_validate
from hybridrec.features import registry, text
from hybridrec.fusion import learned
from hybridrec.linalg import summed, vector_sums
from hybridrec.models.dae import corrupted
from hybridrec.models.emf import EmfParams, embed, embed_sparse, fit_emf, simulate
from hybridrec.models.nets import flat, init_layers, train_net
from hybridrec.models.mlp import regression_loss
from hybridrec.streaming import foldin, windows


def test_stems_and_stop_words(spark):
    words = [("running", "en", "runn"), ("houses", "en", "hous"), ("is", "en", "is"), ("quickly", "en", "quick"), ("Zeitungen".lower(), "de", "zeit"), ("rapidement", "fr", "rapid"), ("naciones", "es", "na"), ("running", "xx", "running")]
    df = spark.createDataFrame([(a, b) for a, b, _ in words], "w string, lang string")
    got = [r[0] for r in df.select(text.stem(F.col("w"), F.col("lang"))).collect()]
    want = ["runn", "hous", "is", "quick", "zeit", "rapid"]
    assert got[:6] == want and got[7] == "running" and len(got[6]) >= 3
    stop = text.stop_words(("en", "de"))
    assert {"the", "und"} <= set(stop)
    row = spark.createDataFrame([(["the", "cat", "und", "hund"],)], "t array<string>").select(text.drop_stop_words(F.col("t"), stop)).first()[0]
    assert row == ["cat", "hund"]


def test_vector_sums_of_many_dimensions(spark):
    """Ten thousand dimensions are one expression and not ten thousand."""
    d = 10_000
    df = spark.range(40).select((F.col("id") % 2).alias("k"), F.transform(F.sequence(F.lit(1), F.lit(d)), lambda x: x * F.col("id").cast("double")).alias("v"), F.lit(1).alias("n"))
    got = {k: (n, v) for k, n, v in vector_sums(df, "k", "v", "n")}
    assert {k: n for k, (n, _) in got.items()} == {0: 20, 1: 20}
    assert np.allclose(got[0][1], np.arange(1, d + 1) * sum(range(0, 40, 2)))
    assert df.select("k", "v").groupBy("k").agg(summed("v").alias("v")).where(F.size("v") == d).count() == 2


def test_simulated_scores_are_recovered(spark):
    """A model fitted on what a draw likes ranks the draw's own scores of held-out items better than chance."""
    p = EmfParams(k=3, lam_u=1.0, lam_v=25.0, lam_e=1.0, iters=6)
    z = simulate(60, 50, 6, p, 3)
    liked = z["scores"] > np.quantile(z["scores"], 0.8)
    train = spark.createDataFrame([(int(u), int(i)) for u, i in zip(*np.nonzero(liked[:, :40]), strict=True)], "user_id long, item_id long")
    feats = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(z["f"])], "item_id long, f array<double>")
    m = fit_emf(train, feats, EmfParams(k=3, lam_e=1.0, iters=6))
    w = {r["id"]: np.array(r["v"]) for r in m.user_factors.collect()}
    h = {r["id"]: np.array(r["v"]) for r in m.content_latents.collect()}
    users = sorted(w)
    got = np.array([[w[u] @ h[i] for i in range(40, 50)] for u in users])
    want = z["scores"][users][:, 40:]
    better = np.mean([(got[a, i] > got[a, j]) == (want[a, i] > want[a, j]) for a in range(len(users)) for i in range(10) for j in range(i)])
    assert better > 0.7
    assert [set(x) for x in ({"iteration", "seconds"}, m.history[0])][0] <= set(m.history[0])


def test_sparse_content_equals_dense(spark):
    e = np.arange(12.0).reshape(4, 3)
    sparse = spark.createDataFrame([(1, (4, [0, 2], [2.0, 1.0])), (2, (4, [3], [1.5]))], "item_id long, f struct<size:int,idx:array<int>,val:array<double>>")
    rows = spark.createDataFrame([(i, x.tolist()) for i, x in enumerate(e)], "dim_id int, e array<double>")
    a = {r["id"]: r["v"] for r in embed_sparse(sparse, rows, 3).collect()}
    b = {r["id"]: r["v"] for r in embed(registry.dense(sparse, counts=True), e).collect()}
    assert all(np.allclose(a[i], b[i]) for i in (1, 2))


def test_five_divisions_are_averaged(spark):
    pos = spark.createDataFrame([(u, i) for u in range(10) for i in range(20)], "user_id long, item_id long")

    def share(split):
        return split.agg(F.avg((F.col("split") == "out_test").cast("double")).alias("accuracy")).select(F.lit("out").alias("scenario"), F.lit(5).alias("k"), "accuracy")

    r = cross_validate(pos, share).collect()
    assert len(r) == 1 and r[0]["folds"] == 5 and abs(r[0]["accuracy"] - 0.2) < 1e-9


@pytest.mark.parametrize("parts", [1, 5])
def test_gradients_do_not_depend_on_tasks(spark, parts):
    rng = np.random.default_rng(1)
    f, v = rng.normal(size=(40, 3)), rng.normal(size=(40, 2))
    rows = spark.createDataFrame([(i, a.tolist(), b.tolist()) for i, (a, b) in enumerate(zip(f, v, strict=True))], "item_id long, f array<double>, v array<double>").repartition(parts)
    layers, seen = train_net(rows, init_layers([3, 4, 2], 0), regression_loss, 3, 0.05, chunk=8)
    one, first = train_net(rows.coalesce(1), init_layers([3, 4, 2], 0), regression_loss, 3, 0.05)
    assert np.allclose(flat(layers), flat(one)) and np.allclose(seen, first) and seen[-1] < seen[0]


def test_masks_change_with_the_epoch():
    x, ids = np.ones((50, 20)), np.arange(50)
    a, b = corrupted(x, ids, 0.3, 1), corrupted(x, ids, 0.3, 2)
    assert (a != b).any() and abs((a == 0).mean() - 0.3) < 0.05 and (a == corrupted(x, ids, 0.3, 1)).all()


def test_learned_weights_follow_the_telling_feature(spark):
    rng = np.random.default_rng(2)
    rows = [(u, i, [float(good) + 0.3 * rng.normal(), float(rng.normal())], float(good)) for u in range(20) for i in range(10) for good in [i < 3]]
    pts = spark.createDataFrame(rows, "user_id long, item_id long, x array<double>, label double")
    for fit in (learned.pointwise_weights, learned.pairwise_weights):
        w = {r["feature"]: (r["position"], r["weight"]) for r in fit(pts, ["a", "b"]).collect()}
        assert w["a"][0] == 1 and w["a"][1] > 5 * abs(w["b"][1])


def _files(spark, root, batches):
    schema = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
    for n, rows in enumerate(batches):
        spark.createDataFrame([(i, dt.datetime.fromisoformat(t), 1, "view", 0.0, "{}") for i, t in rows], schema).coalesce(1).write.mode("append").parquet(f"{root}/{n}")
    return schema


def test_rows_behind_the_watermark_are_dropped_and_a_restart_goes_on(spark, tmp_path):
    root = tmp_path / "in"
    schema = _files(spark, str(root), [[(1, "2024-01-01 10:30:00"), (2, "2024-01-01 12:00:00")], [(3, "2024-01-01 10:10:00"), (4, "2024-01-01 11:10:00")], [(5, "2024-01-01 15:00:00")]])
    out, cp = str(tmp_path / "out"), str(tmp_path / "cp")
    files = tmp_path / "seen"
    files.mkdir()
    for n in range(3):  # each file is a run of its own: the query stops and starts again from its checkpoint
        for f in (root / str(n)).glob("*.parquet"):
            f.rename(files / f"{n}.parquet")
        s = spark.readStream.schema(schema).parquet(str(files))
        windows.tumbling(windows.with_lateness(s, "1 hour"), "1 hour").writeStream.option("checkpointLocation", cp).option("path", out).format("parquet").trigger(availableNow=True).start().awaitTermination()
    got = {r["start"].hour: r["n"] for r in spark.read.parquet(out).collect()}
    assert got[10] == 1 and got[11] == 1 and got[12] == 1 and 15 not in got


def test_running_accuracy_and_new_items(spark):
    lists = spark.createDataFrame([(1, 10, 1), (1, 11, 2), (2, 10, 1)], "user_id long, item_id long, rank int")
    bought = spark.createDataFrame([(1, 11), (2, 12)], "user_id long, item_id long")
    assert tuple(foldin.running_accuracy(bought, lists, 2).first()) == (1, 2) and tuple(foldin.running_accuracy(bought, lists, 1).first()) == (0, 2)
    feats = spark.createDataFrame([(7, [1.0, 2.0])], "item_id long, f array<double>")
    assert foldin.new_items(feats, np.eye(2)).first()["v"] == [1.0, 2.0]
