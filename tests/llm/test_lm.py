"""Language-model scores: counts and base scores against a plain loop, the model against the base on held-out texts."""

import math
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from hybridrec.llm import lm


def brute(rows):
    words = lambda t: re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
    held = lambda d: d is not None and zlib.crc32(str(d).encode()) % 7 == 2
    c, ends = Counter(), 0
    for d, t in rows:
        if not held(d):
            c.update(words(t))
            ends += 1
    n, v = sum(c.values()) + ends, len(c) + (1 if ends else 0)
    out = []
    for d, t in rows:
        counts = [c[w] for w in words(t)] + [ends]
        out.append((d, held(d), len(counts), sum(x > 0 for x in counts), n, sum(math.log10((x + 1) / (n + v + 1)) for x in counts)))
    return out


@pytest.mark.parametrize("known", [1100, 200_000])
def test_base_scores(spark, monkeypatch, known):
    monkeypatch.setattr(lm, "KNOWN", known)
    given = [(r[0], r[1]) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").collect()]
    rows = [*given, (1001, None), (1002, ""), (1003, "A\x1fb \tA"), (1004, "ümlaut ÜMLAUT the THE"), (1005, "the " * 20_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("word", F.lit("clash")).withColumn("c", F.lit(1)).repartition(3)
    got = {r["doc_id"]: r for r in lm.fit_and_score(docs).collect()}
    assert len(got) == len(rows)
    for d, held, n, known_, total, base in brute(rows):
        r = got[d]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held, n, known_, total), d
        assert abs(r["base_score"] - base) < 1e-6 * max(1, abs(base))
        assert np.isfinite(r["score"]) and r["score"] < 0


def test_model_beats_base_on_held_out_texts(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    r = lm.fit_and_score(docs).where("held_out").agg(F.sum("score").alias("m"), F.sum("base_score").alias("b")).collect()[0]
    assert r["m"] > 0.97 * r["b"]


def test_probabilities_sum_to_one():
    top = [(b"w%d" % i, 500 - i // 4) for i in range(1500)]
    tails = {}
    for w, c in top[lm.HEAD - 1 :]:
        n, v = tails.get(lm._tail(w), (0, 0))
        tails[lm._tail(w)] = (n + c, v + 1)
    v = lm.Vocabulary(top, 40, tails, sum(c for _, c in top) + 40, 1501)
    w = lm.Weights.zero()
    rng = np.random.default_rng(0)
    context = rng.integers(0, lm.HEAD + lm.TAILS, 5000)
    history = lm._history([context], [context])
    before = lm.log_probability(w, v, context, history).sum()
    for _ in range(5):
        lm.train_step(w, v, context, history, 0.5)
    assert lm.log_probability(w, v, context, history).sum() > before
    every = np.arange(lm.HEAD + lm.TAILS)
    p = np.exp(lm.log_probability(w, v, every, np.repeat([[7], [9], [7], [9]], len(every), axis=1)))
    assert abs(p.sum() - 1) < 1e-3


def test_gradients_of_equal_rows_add_up():
    rng = np.random.default_rng(1)
    rows, grads = rng.integers(0, 50, 4096), rng.standard_normal((4096, 8)).astype(np.float32)
    table, want = np.zeros((64, 8), np.float32), np.zeros((64, 8))
    lm._push(table, rows, grads, 0.5)
    for r in range(50):
        want[r] = grads[rows == r].sum(0) * 0.25 / np.sqrt((rows == r).sum())
    assert np.allclose(table, want, atol=1e-4)


def test_model_grows_with_the_tokens():
    small, large = lm.Weights.zero(20_000_000), lm.Weights.zero(80_000_000)
    assert len(large.by_class) == len(large.by_word) == 2 * len(small.by_class)


def test_scores_do_not_depend_on_partitions(spark, monkeypatch):
    monkeypatch.setattr(lm, "SHARD_TOKENS", 20_000)
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    two, seven = ({r["doc_id"]: r["score"] for r in lm.fit_and_score(docs.repartition(n)).collect()} for n in (2, 7))
    assert two.keys() == seven.keys()
    assert all(abs(two[d] - seven[d]) < 1e-6 * abs(two[d]) for d in two)


def test_scores_do_not_depend_on_where_shards_lie(spark, monkeypatch):
    monkeypatch.setattr(lm, "SHARD_TOKENS", 20_000)
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    apart = {r["doc_id"]: r["score"] for r in lm.fit_and_score(docs).collect()}
    monkeypatch.setattr(lm, "_places", lambda _, n: [0] * n)
    together = {r["doc_id"]: r["score"] for r in lm.fit_and_score(docs).collect()}
    assert apart.keys() == together.keys()
    assert all(abs(apart[d] - together[d]) < 1e-6 * abs(apart[d]) for d in apart)


def test_places_differ(spark):
    for n in (1, 3, 50):
        places = lm._places(spark, n)
        assert len(set(places)) == n
        got = spark.createDataFrame([(p,) for p in places], "p long").repartition(n, "p").select(F.spark_partition_id()).distinct()
        assert got.count() == n


def test_odd_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert lm.fit_and_score(empty).count() == 0
    held = next(i for i in range(100) if zlib.crc32(str(i).encode()) % 7 == 2)
    only = lm.fit_and_score(spark.createDataFrame([(held, "a b")], "doc_id long, text string")).collect()
    assert [(r["held_out"], r["n_known"], r["base_score"], r["score"]) for r in only] == [(True, 0, 0.0, 0.0)]
    odd = lm.fit_and_score(spark.createDataFrame([(None, "a"), (1, "a b"), (1, "a b")], "doc_id long, text string"))
    assert sorted(str(r["doc_id"]) for r in odd.collect()) == ["1", "1", "None"]
