"""Near-duplicate documents: banded MinHash, Bayesian pruning, exact verification.

1. A document is the set of its distinct word shingles (64-bit hashes). Equal sets are one class, kept by its smallest id.
2. Representatives are hashed into bands. In a bucket every member is first paired with the bucket's smallest
   id only; whatever stays in another component than its bucket's commonest one then meets that whole component and the bucket's other
   strays, in bounded blocks. So a group of near copies costs a star, and no link between components is lost.
3. A pair's signatures are compared batch by batch; it goes as soon as the posterior probability of reaching
   the threshold is under ``miss``. What survives is verified on the full sets.
4. Components of the links are the groups.

Defined results: null text, or one without words, has no set, no links and is kept. Rows that share a doc_id are one
vertex with the links of all their texts: each distinct set is a class of its own, searched and verified with its own signature, and classes
that share an id are tied at the end. A null doc_id has no component and is kept. Extra columns are ignored; an empty table gives an empty result.
Texts are read whole, whatever their length.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.llm.components import components
from hybridrec.llm.texts import byte_texts
from hybridrec.runtime import materialize


@dataclass(frozen=True)
class Near:
    words: int = 5
    #: Percent of the union that the intersection must reach.
    percent: int = 80
    #: Chance that bands miss a pair at the threshold, and that the posterior prunes one that reaches it.
    miss: float = 1e-6
    hashes: int = 192
    #: Hashes compared between two looks at the posterior.
    batch: int = 32
    #: Most members of a bucket in one comparison block.
    block: int = 256

    def bands(self) -> tuple[int, int]:
        """Bands and rows: the most rows whose bands, enough for ``miss``, fit into the signature."""
        t, best = self.percent / 100, None
        for rows in range(1, 17):
            n = math.ceil(math.log(self.miss) / math.log1p(-(t**rows))) if t < 1 else 1
            if n * rows <= self.hashes:
                best = (n, rows)
        if best is None:
            raise ValueError("the signature is too short for this threshold and miss probability")
        return best

    def least_matches(self) -> list[tuple[int, int]]:
        """(hashes compared, least matches that keep a pair): under a uniform prior the posterior chance of the threshold after x of m is P(Bin(m+1, t) <= x)."""
        t, out = self.percent / 100, []
        for m in range(self.batch, self.hashes + 1, self.batch):
            total = 0.0
            for x in range(m + 1):
                total += math.comb(m + 1, x) * t**x * (1 - t) ** (m + 1 - x)
                if total >= self.miss:
                    out.append((m, x))
                    break
        return out


_ODD = np.uint64(0x9E3779B97F4A7C15)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x81DADEF4BC2DD44D)
    return h ^ (h >> np.uint64(33))


def shingles(text: bytes, words: int) -> np.ndarray:
    """Sorted distinct hashes of a text's word shingles; of the whole sequence if it has fewer words."""
    import xxhash

    own = text.lower().split()
    if not own:
        return np.zeros(0, np.uint64)
    digest = xxhash.xxh3_64_intdigest
    h = np.array([digest(w) for w in own], np.uint64)
    k = min(words, len(h))
    with np.errstate(over="ignore"):
        s = np.full(len(h) - k + 1, k, np.uint64)
        for j in range(k):
            s = _mix(s * _ODD + h[j : len(h) - k + 1 + j])
    return np.unique(s)


def _fingerprint(s: np.ndarray) -> tuple[int, int]:
    """Two signed 64-bit halves of a hash of a whole set."""
    import xxhash

    f = xxhash.xxh3_128_intdigest(s.tobytes())
    return (f >> 64) - (1 << 63), (f & ((1 << 64) - 1)) - (1 << 63)


def signature(s: np.ndarray, a: np.ndarray, b: np.ndarray, block: int = 2048) -> np.ndarray:
    """Top 32 bits of the least value of each hash function over a set."""
    best = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
    with np.errstate(over="ignore"):
        for lo in range(0, len(s), block):
            np.minimum(best, (s[lo : lo + block, None] * a + b).min(0), out=best)
    return (best >> np.uint64(32)).astype(np.uint32)


def sketch(docs: DataFrame, near: Near) -> DataFrame:
    """doc_id, n, two halves of the set's fingerprint, short signature, band keys."""
    bands, rows = near.bands()

    def run(batches):
        random = np.random.default_rng(20_240_229)
        a = random.integers(0, 1 << 63, near.hashes, np.uint64) * np.uint64(2) + np.uint64(1)
        b = random.integers(0, 1 << 63, near.hashes, np.uint64)
        weights = random.integers(0, 1 << 63, (1, rows), np.uint64) * np.uint64(2) + np.uint64(1)
        salt = _mix(np.arange(1, bands + 1, dtype=np.uint64) * _ODD)
        for batch in batches:
            n, f1, f2, sig, keys = [], [], [], [], []
            for text in byte_texts(batch.column(1)):
                s = shingles(text, near.words)
                n.append(len(s))
                high, low = _fingerprint(s)
                f1.append(high)
                f2.append(low)
                if not len(s):
                    sig.append(None)
                    keys.append(None)
                    continue
                m = signature(s, a, b)
                with np.errstate(over="ignore"):
                    k = _mix((_mix(m[: bands * rows].reshape(bands, rows).astype(np.uint64) + _ODD) * weights).sum(1, dtype=np.uint64) + salt)
                sig.append((m & np.uint32(0xFFFF)).astype("<u2").tobytes())
                keys.append(k.view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(f1, pa.int64()), pa.array(f2, pa.int64()), pa.array(sig, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], names=["doc_id", "n", "f1", "f2", "sig", "bands"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n long, f1 long, f2 long, sig binary, bands array<long>")


def _plausible(x: np.ndarray, y: np.ndarray, near: Near) -> np.ndarray:
    """Which pairs of signatures (rows of x and y) survive every look at the posterior."""
    alive, matches, lo = np.arange(len(x)), np.zeros(len(x), np.int64), 0
    for m, least in near.least_matches():
        matches = matches + (x[alive, lo:m] == y[alive, lo:m]).sum(1)
        ok = matches >= least
        alive, matches, lo = alive[ok], matches[ok], m
    out = np.zeros(len(x), bool)
    out[alive] = True
    return out


def _signatures(column: pa.Array, near: Near) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), "<u2").reshape(-1, near.hashes)


def _prune(pairs: DataFrame, reps: DataFrame, near: Near) -> DataFrame:
    """Pairs a < b whose sizes and signatures allow the threshold."""
    left = reps.select(F.col("doc_id").alias("a"), F.col("n").alias("na"), F.col("sig").alias("sa"))
    right = reps.select(F.col("doc_id").alias("b"), F.col("n").alias("nb"), F.col("sig").alias("sb"))
    both = pairs.join(left, "a").join(right, "b").where(F.least("na", "nb") * 100 >= F.greatest("na", "nb") * near.percent)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                ok = _plausible(_signatures(batch.column(2), near), _signatures(batch.column(3), near), near)
                yield pa.RecordBatch.from_arrays([batch.column(0).filter(pa.array(ok)), batch.column(1).filter(pa.array(ok))], names=["a", "b"])

    return both.select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def _sets(docs: DataFrame, wanted: DataFrame, near: Near, extra: DataFrame | None) -> DataFrame:
    """id, items of the wanted classes (column id), made again from their documents' texts alone; ``extra`` (id, items) has those of shared ids."""
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text").join(wanted, "id", "left_semi")
    if extra is not None:
        texts = texts.join(extra.select("id"), "id", "left_anti")

    def sets(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([shingles(t, near.words).tobytes() for t in byte_texts(batch.column(1))], pa.binary())], names=["id", "items"])

    found = texts.mapInArrow(sets, "id long, items binary").dropDuplicates(["id"])
    return materialize(found if extra is None else found.unionByName(extra.join(wanted, "id", "left_semi")), "sets")


def _linked(x: np.ndarray, y: np.ndarray, near: Near) -> bool:
    """Exact test of two sorted sets."""
    if not len(x) or not len(y):
        return False
    common = int((x[np.minimum(np.searchsorted(x, y), len(x) - 1)] == y).sum())
    return common > 0 and 100 * common >= near.percent * (len(x) + len(y) - common)


def _verify(pairs: DataFrame, docs: DataFrame, near: Near, extra: DataFrame | None) -> DataFrame:
    """Links: pairs whose full sets reach the threshold."""
    full = _sets(docs, pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), near, extra)
    both = pairs.join(full.select(F.col("id").alias("a"), F.col("items").alias("x")), "a").join(full.select(F.col("id").alias("b"), F.col("items").alias("y")), "b")

    def run(batches):
        for batch in batches:
            keep = pa.array([_linked(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64), near) for x, y in zip(batch.column(2), batch.column(3), strict=True)], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], names=["a", "b"])

    return both.select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def _block_links(left, right, near: Near, same: bool) -> list[tuple[int, int]]:
    """Links of the rows of ``left`` with those of ``right`` (pandas frames of doc_id, label, n, sig, items) between different labels.

    Plausible partners are verified on the full sets, most similar first; a row stops at its first link with each label, since everything of one
    label is one component already.
    """
    sig = np.frombuffer(b"".join(right["sig"]), "<u2").reshape(len(right), -1)
    ids, labels, sizes = (right[c].to_numpy() for c in ("doc_id", "label", "n"))
    items, out = right["items"].to_numpy(), []
    for doc, label, n, raw, mine in zip(left["doc_id"], left["label"], left["n"], left["sig"], left["items"], strict=True):
        ok = (labels != label) & (100 * np.minimum(sizes, n) >= near.percent * np.maximum(sizes, n))
        if same:
            ok &= ids > doc
        at = np.flatnonzero(ok)
        if not len(at):
            continue
        y = np.frombuffer(raw, "<u2")
        at = at[_plausible(sig[at], np.broadcast_to(y, (len(at), len(y))), near)]
        own, done = np.frombuffer(mine, np.uint64), set()
        for i in at[np.argsort(-(sig[at] == y).sum(1), kind="stable")]:
            if labels[i] not in done and _linked(own, np.frombuffer(items[i], np.uint64), near):
                done.add(labels[i])
                out.append((min(doc, ids[i]), max(doc, ids[i])))
    return out


def _rest(members: DataFrame, reps: DataFrame, docs: DataFrame, labels: DataFrame, near: Near, extra: DataFrame | None) -> DataFrame:
    """Links between different components that share a bucket, beyond those with a bucket's centre.

    A member outside its bucket's commonest component (a stray) meets all of that component, each in blocks of ``near.block``, once and not once
    a bucket; and the other strays of the bucket. Every plausible pair is verified inside the block, and what leaves it are links.
    """
    import pandas as pd

    known = members.join(labels, members["doc_id"] == labels["id"], "left").select("bucket", "doc_id", F.coalesce("label", "doc_id").alias("label"))
    parts = known.groupBy("bucket", "label").agg(F.count("*").alias("c"))
    main = parts.groupBy("bucket").agg(F.max(F.struct("c", "label")).alias("top"), F.count("*").alias("labels"), F.sum("c").alias("size")).where("labels > 1 and size > 2")
    strays = materialize(known.join(main.select("bucket", F.col("top.label").alias("main"), (F.col("size") - F.col("top.c")).alias("strays"), "labels"), "bucket").where("label != main"), "strays")
    asked = strays.select("doc_id", "label", "main").distinct()
    every = reps.select("doc_id").join(labels, reps["doc_id"] == labels["id"], "left").select("doc_id", F.coalesce("label", "doc_id").alias("main"))
    met = every.join(asked.select("main").distinct(), "main", "left_semi")
    wanted = materialize(met.select(F.col("doc_id").alias("id")).unionByName(asked.select(F.col("doc_id").alias("id"))).distinct(), "wanted")
    full = _sets(docs, wanted, near, extra)
    facts = reps.select("doc_id", "n", "sig").join(full.withColumnRenamed("id", "doc_id"), "doc_id")

    # strays against components
    counts = asked.groupBy("main").agg(F.ceil(F.count("*") / near.block).cast("int").alias("sbs")).join(met.groupBy("main").agg(F.ceil(F.count("*") / near.block).cast("int").alias("mbs")), "main")
    at = lambda n: F.pmod(F.xxhash64("doc_id", F.lit(3)), F.col(n)).cast("int")
    upto = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    as_member = met.join(counts, "main").select("main", "doc_id", F.col("main").alias("label"), F.lit(False).alias("stray"), at("mbs").alias("mb"), upto("sbs").alias("sb"))
    as_stray = asked.join(counts, "main").select("main", "doc_id", "label", F.lit(True).alias("stray"), upto("mbs").alias("mb"), at("sbs").alias("sb"))

    def against(pdf):
        s, m = pdf[pdf["stray"]], pdf[~pdf["stray"]]
        return pd.DataFrame(_block_links(s, m, near, False) if len(s) and len(m) else [], columns=["a", "b"]).astype("int64")

    one = as_member.unionByName(as_stray).join(facts, "doc_id").groupBy("main", "mb", "sb").applyInPandas(against, "a long, b long")

    # strays of one bucket among themselves: each pair of blocks is a group
    among = strays.where("labels > 2").withColumn("bs", F.ceil(F.col("strays") / near.block).cast("int")).withColumn("own", at("bs"))
    dealt = among.select("bucket", "doc_id", "label", "own", upto("bs").alias("other")).select("bucket", "doc_id", "label", "own", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"))

    def between(pdf):
        lo, hi = pdf["lo"].iloc[0], pdf["hi"].iloc[0]
        a, b = pdf[pdf["own"] == lo], pdf[pdf["own"] == hi]
        return pd.DataFrame(_block_links(a, b, near, lo == hi) if len(a) and len(b) else [], columns=["a", "b"]).astype("int64")

    two = dealt.join(facts, "doc_id").groupBy("bucket", "lo", "hi").applyInPandas(between, "a long, b long")
    return one.unionByName(two).distinct()


def _classes(some: DataFrame, docs: DataFrame, near: Near) -> tuple[DataFrame, DataFrame, DataFrame | None, DataFrame | None]:
    """doc_id, n, rep of every document with a set; rep, n, sig, bands of every class; and what ids of several texts need.

    A class is a set; its vertex is its smallest doc_id, or a number below all ids if that id has other texts too. Then the third frame has the sets
    of such classes (id, items) and the fourth ties classes that share an id (a, b).
    """
    several = some.groupBy("doc_id").agg(F.min("f1").alias("low"), F.max("f1").alias("high")).where("low != high").select("doc_id")
    several = materialize(several, "shared-ids")
    classes = some.groupBy("f1", "f2").agg(F.min("doc_id").alias("rep"))
    if not several.limit(1).count():
        member = materialize(some.select("doc_id", "n", "f1", "f2").join(classes, ["f1", "f2"]).select("doc_id", "n", "rep"), "classes")
        first = some.join(member.where("doc_id = rep").select("doc_id").distinct(), "doc_id", "left_semi").dropDuplicates(["doc_id"])
        return member, materialize(first.select(F.col("doc_id").alias("rep"), "n", "sig", "bands"), "representatives"), None, None
    below = some.agg(F.min("doc_id").alias("m")).collect()[0]["m"]
    odd = materialize(classes.join(several.select(F.col("doc_id").alias("rep")), "rep", "left_semi").select("f1", "f2", (F.lit(below - 1) - F.monotonically_increasing_id()).alias("own")), "odd-classes")
    named = materialize(classes.join(odd, ["f1", "f2"], "left").select("f1", "f2", F.col("rep").alias("least"), F.coalesce("own", "rep").alias("rep")), "named-classes")
    member = materialize(some.select("doc_id", "n", "f1", "f2").join(named, ["f1", "f2"]).select("doc_id", "n", "rep"), "classes")
    whole = some.join(named, ["f1", "f2"]).where("doc_id = least").dropDuplicates(["rep"])
    reps = materialize(whole.select("rep", "n", "sig", "bands"), "representatives")

    def sets(batches):
        for batch in batches:
            own = [shingles(t, near.words) for t in byte_texts(batch.column(0))]
            prints = [_fingerprint(x) for x in own]
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in prints], pa.int64()), pa.array([x[1] for x in prints], pa.int64()), pa.array([x.tobytes() for x in own], pa.binary())], names=["f1", "f2", "items"])

    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(several, "doc_id", "left_semi").select("text")
    extra = materialize(texts.mapInArrow(sets, "f1 long, f2 long, items binary").join(odd, ["f1", "f2"]).select(F.col("own").alias("id"), "items").dropDuplicates(["id"]), "odd-sets")
    tied = member.join(several, "doc_id", "left_semi")
    tied = tied.join(tied.groupBy("doc_id").agg(F.min("rep").alias("a")), "doc_id").select("a", F.col("rep").alias("b")).where("a != b").distinct()
    return member, reps, extra, materialize(tied, "ties")


def groups(docs: DataFrame, near: Near = Near()) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row."""
    table = materialize(sketch(docs, near), "sketches")
    some = table.where("n > 0 and doc_id is not null")
    member, reps, extra, ties = _classes(some, docs, near)
    reps = reps.withColumnRenamed("rep", "doc_id")
    keys = reps.select("doc_id", F.explode("bands").alias("bucket"))
    shared = keys.groupBy("bucket").agg(F.min("doc_id").alias("centre"), F.count("*").alias("size")).where("size > 1")
    members = materialize(keys.join(shared.select("bucket", "centre"), "bucket"), "buckets")
    star = members.where("doc_id != centre").select(F.col("centre").alias("a"), F.col("doc_id").alias("b")).distinct()
    links = materialize(_verify(materialize(_prune(star, reps, near), "pairs"), docs, near, extra), "star-links")
    labels = materialize(components(links), "star-labels")
    links = links.unionByName(materialize(_rest(members.select("bucket", "doc_id"), reps, docs, labels, near, extra), "rest-links"))
    final = components(links if ties is None else links.unionByName(ties))
    labelled = member.join(final, member["rep"] == final["id"], "left").select("doc_id", "n", F.coalesce("label", "rep").alias("component_id"))
    if ties is not None:  # a label may be a number below all ids
        labelled = materialize(labelled, "labelled")
        least = labelled.groupBy("component_id").agg(F.min("doc_id").alias("least"))
        labelled = labelled.join(least, "component_id").select("doc_id", "n", F.col("least").alias("component_id"))
    rest = table.where("n = 0 or doc_id is null").select("doc_id", "n", F.col("doc_id").alias("component_id"))
    if ties is not None:  # a row without words belongs where its id's other texts do
        known = labelled.groupBy("doc_id").agg(F.min("component_id").alias("known"))
        rest = rest.join(known, "doc_id", "left").select("doc_id", "n", F.coalesce("known", "component_id").alias("component_id"))
    return labelled.unionByName(rest).select("doc_id", F.col("n").alias("n_shingles"), "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame, near: Near = Near()) -> DataFrame:
    """The documents of smallest id of each group, with all their columns; of rows that share an id all stay."""
    gone = groups(docs, near).where("not kept").select(F.col("doc_id").alias("_gone")).distinct()
    return docs.join(gone, docs["doc_id"] == gone["_gone"], "left_anti")
