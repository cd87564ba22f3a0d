"""Near duplicates against all pairs, and components against a plain search."""

import random
import re

import pytest
from pyspark.sql import functions as F

from hybridrec.llm import near_dedup
from hybridrec.llm.components import components


def brute(rows, words, percent):
    sets = {}
    for doc, text in rows:
        w = re.findall("[^\x20\x09-\x0d]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
        k = min(words, len(w))
        sets[doc] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if w else set()
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets, key=lambda d: len(sets[d]))
    for i, a in enumerate(ids):
        for b in ids[i + 1 :]:
            if len(sets[b]) * percent > len(sets[a]) * 100:
                break
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), root(d)) for d in sets}


def near_copies(seed, n=60):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    out, i = [], 10_000
    for length in (3, 8, 40, 150, 600):
        base = [word() for _ in range(length)]
        for _ in range(n):
            own = list(base)
            for _ in range(rng.randint(0, max(1, length // 15))):
                own[rng.randrange(length)] = word()
            out.append((i, rng.choice(["\n", " ", "  "]).join(own)))
            i += 1
    return out


EDGES = [(1, None), (2, ""), (3, " \n"), (4, "one"), (5, "ONE"), (6, "one two"), (7, "one two"), (8, "two one"), (9, "One  two\nthree"), (11, "x " * 3000), (12, "x " * 10)]


@pytest.mark.parametrize(("words", "percent"), [(3, 85), (5, 80)])
def test_groups_equal_all_pairs(spark, words, percent):
    given = [(r[0], r[1]) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select(F.col("doc_id") + 100, "text").collect()]
    rows = given + near_copies(words) + EDGES
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n", F.lit("clash")).withColumn("label", F.lit(0)).repartition(5)
    got = {r["doc_id"]: r for r in near_dedup.groups(docs, near_dedup.Near(words=words, percent=percent)).collect()}
    want = brute(rows, words, percent)
    assert len(got) == len(rows)
    for d, (n, c) in want.items():
        assert (got[d]["n_shingles"], got[d]["component_id"], got[d]["kept"]) == (n, c, d == c), (d, got[d], n, c)


def test_small_blocks_lose_nothing(spark):
    rows = near_copies(9, 40)
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in near_dedup.groups(docs, near_dedup.Near(words=3, percent=85, block=7)).collect()}
    assert got == {d: c for d, (_, c) in brute(rows, 3, 85).items()}


def test_odd_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert near_dedup.groups(empty).count() == 0
    odd = spark.createDataFrame([(None, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e f")], "doc_id long, text string")
    rows = sorted((str(r["doc_id"]), r["component_id"], r["kept"]) for r in near_dedup.groups(odd).collect())
    assert rows == [("1", 1, True), ("1", 1, True), ("2", 1, False), ("None", None, True)]
    assert near_dedup.keep_one(odd).count() == 3


def test_rows_that_share_an_id_keep_the_links_of_all_their_texts(spark):
    rng = random.Random(2)
    text = lambda: [f"w{rng.randrange(10**6)}" for _ in range(60)]
    a, b, c = text(), text(), text()
    near = lambda x: " ".join([*x[:-1], "other"])
    rows = [(7, " ".join(a)), (7, " ".join(b)), (3, near(a)), (4, near(b)), (9, " ".join(c)), (8, None), (8, " ".join(c)), (7, ""), (10, " ".join(text()))]
    got = {(r["doc_id"], r["component_id"]) for r in near_dedup.groups(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    assert got == {(7, 3), (3, 3), (4, 3), (9, 8), (8, 8), (10, 10)}


def test_components(spark):
    rng = random.Random(1)
    links = [(rng.randrange(300), rng.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1060)] + [(2000, j) for j in range(2001, 2100)] + [(5, 5), (None, 3)]
    parent = {}

    def root(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        if a is not None and a != b:
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    got = {r["id"]: r["label"] for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {x: root(x) for x in list(parent)}


def test_bands_reach_the_miss_probability():
    for percent in (70, 80, 85, 95):
        near = near_dedup.Near(percent=percent)
        n, r = near.bands()
        assert n * r <= near.hashes and (1 - (percent / 100) ** r) ** n <= near.miss
