"""Line deduplication: bit-parallel distance against the plain one, decisions against all pairs."""

import random

import pytest
from pyspark.sql import functions as F

from hybridrec.llm import line_dedup
from hybridrec.llm.line_dedup import Lines


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def edited(rng, s, n):
    s = list(s)
    for _ in range(n):
        at, kind = rng.randint(0, len(s)), rng.randint(0, 2)
        if kind == 0:
            s.insert(at, rng.choice("abcé\U0001f600"))
        elif s and at < len(s):
            s[at : at + 1] = [] if kind == 1 else [rng.choice("abxyz")]
    return "".join(s)


@pytest.mark.parametrize("edits", [0, 1, 2, 3])
def test_banded_distance(spark, edits):
    rng, rows = random.Random(edits), []
    for _ in range(500):
        a = "".join(rng.choice("abcd é") for _ in range(rng.choice([0, 1, 2, 3, 5, 17, 40, 90])))
        rows.append((a, edited(rng, a, rng.randint(0, edits + 2))))
    rows += [("", ""), ("", "ab"), ("abcdef" * 20, "bcdef" + "abcdef" * 19 + "a")]
    got = {(r["x"], r["y"]) for r in line_dedup.within(spark.createDataFrame(rows, "x string, y string"), edits).collect()}
    assert got == {(a, b) for a, b in rows if distance(a, b) <= edits}


def brute(rows, rules):
    """(doc, pos, near) of the lines that go."""
    occ = sorted((d, i, line) for d, t in rows if d is not None and t is not None for i, line in enumerate(t.split("\n")) if len(line) >= rules.exact_chars)
    first = {}
    for d, i, line in occ:
        first.setdefault(line, (d, i))
    longs = [x for x in first if len(x) >= rules.near_chars]
    near = set()
    for n, x in enumerate(longs):
        for y in longs[n + 1 :]:
            if abs(len(x) - len(y)) <= rules.edits and distance(x, y) <= rules.edits:
                near.add(max(x, y, key=first.get))
    return {(d, i, (d, i) == first[line]) for d, i, line in occ if line in near or (d, i) != first[line]}


def corpus(seed):
    rng = random.Random(seed)
    word = lambda: "".join(rng.choice("abcdefg") for _ in range(rng.randint(2, 7)))
    pool = [" ".join(word() for _ in range(rng.randint(3, 14))) for _ in range(25)]
    out = []
    for d in range(60):
        lines = [edited(rng, rng.choice(pool), rng.choice([0, 0, 0, 1, 2, 3])) if rng.random() < 0.6 else " ".join(word() for _ in range(rng.randint(1, 12))) for _ in range(rng.randint(0, 9))]
        out.append((d, "\n".join(lines)))
    return out


@pytest.mark.parametrize("rules", [Lines(), Lines(edits=1, exact_chars=1, near_chars=10), Lines(edits=3, exact_chars=8, near_chars=30)])
def test_decisions_equal_all_pairs(spark, rules):
    rows = [*corpus(3), (900, None), (901, ""), (902, "\n\n"), (903, "x" * 3000 + "\n" + "x" * 3001), (None, "a line that stands nowhere else in here " * 2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("pos", F.lit("clash")).withColumn("line", F.lit("clash")).repartition(4)
    got = {(r["doc_id"], r["pos"], r["near"]) for r in line_dedup.decisions(docs, rules).collect()}
    assert got == brute(rows, rules)


@pytest.mark.parametrize("crowd", [0, 4])
def test_crowded_segments_equal_all_pairs(spark, crowd):
    """Every segment crowded, and forms in which one word changes."""
    rng = random.Random(9)
    form = "one very common line of a form that is filled in again and again by many people".split()
    rows = corpus(4)
    for d in range(200, 320):
        words = list(form)
        words[rng.choice([3, 3, rng.randrange(len(words))])] = "".join(rng.choice("abc") for _ in range(rng.randint(3, 6)))
        rows.append((d, " ".join(words)))
    rules = Lines(crowd=crowd, block=8)
    got = {(r["doc_id"], r["pos"], r["near"]) for r in line_dedup.decisions(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), rules).collect()}
    assert got == brute(rows, rules)


def test_rows_that_share_an_id(spark):
    x, own = "a line that stands in several of these rows", "a line that stands nowhere else in this table"
    docs = spark.createDataFrame([(1, x), (5, x), (5, own)], "doc_id long, text string")
    assert sorted(map(tuple, line_dedup.keep(docs).collect())) == [(1, x), (5, own)]
    twice = spark.createDataFrame([(1, x), (5, x + "!"), (5, x + "!")], "doc_id long, text string")
    assert [(r["n_lines"], r["n_near"], r["n_kept"]) for r in line_dedup.digest(twice).orderBy("doc_id").collect()] == [(1, 0, 1), (1, 1, 0), (1, 1, 0)]


def test_many_lines_of_one_document(spark):
    lines = [f"line number {i} of a document of very many lines {i * 7919}" for i in range(30_000)]
    docs = spark.createDataFrame([(1, "\n".join(lines)), (2, "\n".join(lines[::2] + ["own"]))], "doc_id long, text string")
    assert {r["doc_id"]: r["text"] for r in line_dedup.keep(docs, Lines(near_chars=1 << 20)).collect()} == {1: "\n".join(lines), 2: "own"}


def test_documents_without_their_repeats(spark):
    long_ = "this very line is repeated in many places"
    rows = [(1, f"{long_}\nown words of one"), (2, f"{long_}\nown words of two"), (3, long_), (4, long_ + "!\nz"), (5, None), (6, ""), (None, long_)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_chars", F.length("text").cast("long")).withColumn("_id", F.lit(0))
    kept = line_dedup.keep(docs)
    assert kept.columns == docs.columns
    assert {(r["doc_id"], r["text"], r["n_chars"]) for r in kept.collect()} == {(1, rows[0][1], len(rows[0][1])), (2, "own words of two", 16), (4, "z", 1), (5, None, None), (6, "", 0), (None, long_, len(long_))}


def test_odd_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    assert line_dedup.decisions(empty).count() == line_dedup.digest(empty).count() == line_dedup.keep(empty).count() == 0
    same = spark.createDataFrame([(1, "a line of more than twenty characters")] * 3, "doc_id long, text string")
    assert [r["n_kept"] for r in line_dedup.digest(same).collect()] == [1, 1, 1]


def test_a_shared_segment_makes_few_pairs(spark, monkeypatch):
    from hybridrec.llm import line_dedup

    counts = {}
    real = line_dedup.materialize

    def kept(df, name):
        out = real(df, name)
        counts[name] = out.count() if name == "line-pairs" else None
        return out

    monkeypatch.setattr(line_dedup, "materialize", kept)
    tail = lambda i: "".join(chr(97 + (i * 7 + j * (i + 3)) % 26) for j in range(40))
    docs = spark.createDataFrame([(i, "a form that begins so " + tail(i)) for i in range(30)], "doc_id long, text string")
    line_dedup.decisions(docs).collect()
    assert counts["line-pairs"] <= 8 * 30
