"""Language-model scores from a hashed maximum-entropy model.

Words split into ``HEAD`` frequent ones, in ``CLASSES`` classes of equal size, and all others, in ``TAILS`` classes by a hash
of their last two bytes. A token's probability is the softmax of its class given the words before it, times a
softmax inside a head class or the smoothed frequency inside a tail class. Both softmaxes start at the
corpus frequencies and add hashed weights of features of the history: last word, the word before it skipped over, and the
pair, in which rare words stand for their class. Single words are hashed whole, so every word of the corpus has weights of its own but
for collisions, and the hashed rows grow with the training tokens up to ``MOST_ROWS``. Counts cover every training document. Weights are trained by
gradient updates in each of several data shards, over every training token, and averaged. A document's shard and its place there follow from
its text and id alone, so scores do not depend on how the input is partitioned; shards grow in number and in
size as the root of the tokens. Scoring runs in numpy batches.

An unknown word has its tail class's mass of one unseen word, so log-probabilities are finite and unknown texts score low.

Defined results: null text is empty and scores its end token. A null doc_id is held in training (its checksum is no remainder).
Rows that share a doc_id are scored each. Extra columns are ignored. An empty table gives an empty result; without
training documents every token has probability 1.
"""

from __future__ import annotations

import zlib
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.llm.texts import byte_texts, held_out
from hybridrec.runtime import materialize

CLASSES, CLASS_WORDS, TAILS = 16, 64, 16
HEAD = CLASSES * CLASS_WORDS
#: Words whose counts are sent to the workers; all others are joined. A bound on what is broadcast, not on what is counted.
KNOWN = 120_000
#: Hashed rows of each weight table: a power of two near 16 times the root of the training tokens, within these. The upper one bounds what is broadcast.
LEAST_ROWS, MOST_ROWS, BLOCK = 1 << 16, 1 << 18, 256
BATCH, RATE = 4096, 0.5
#: There are as many shards as the root of the training tokens over this many: 8 for 80 million tokens, 4,000 for 20 trillion.
SHARD_TOKENS = 1_200_000
SCHEMA = "uid long, doc_id long, held_out boolean, n_tokens long, head_known long, head_base double, model double, word binary, times long"


def count_words(docs: DataFrame) -> DataFrame:
    """word (binary), c over all given documents; the end of each document is not in it. Workers pre-aggregate in bounded memory."""

    def run(batches):
        from collections import Counter

        held: Counter = Counter()
        for batch in batches:
            for text in byte_texts(batch.column(0)):
                held.update(text.lower().split())
                if len(held) > 400_000:
                    yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], names=["word", "c"])
                    held = Counter()
        yield pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], names=["word", "c"])

    return docs.select("text").mapInArrow(run, "word binary, c long").groupBy("word").agg(F.sum("c").alias("c"))


class Vocabulary:
    """What workers need of the counts: ids and counts of the most frequent words, class sizes of the rest."""

    def __init__(self, top: list[tuple[bytes, int]], ends: int, tails: dict[int, tuple[int, int]], total: int, distinct: int):
        self.total, self.distinct, self.ends = total, distinct, ends
        #: the document's end is the first head word, None
        head = sorted([(None, ends), *top[: HEAD - 1]], key=lambda x: -x[1]) if total else []
        self.ids = {w: i for i, (w, _) in enumerate(head) if w is not None}
        self.end = next((i for i, (w, _) in enumerate(head) if w is None), 0)
        self.head_counts = np.zeros(HEAD)
        self.head_counts[: len(head)] = [c for _, c in head]
        n_head = len(head)
        for j, (w, _) in enumerate(top[HEAD - 1 :]):
            self.ids[w] = n_head + j
        self.n_head = n_head
        self.counts = np.array([*[c for _, c in head], *[c for _, c in top[HEAD - 1 :]]], np.int64)
        tail_of = np.array([_tail(w) for w, _ in top[HEAD - 1 :]], np.int64)
        #: id of a word as context: itself in the head, else its tail class
        self.context = np.concatenate([np.arange(max(n_head, 1)), HEAD + tail_of]).astype(np.int32)
        self.tail_n = np.array([tails.get(k, (0, 0))[0] for k in range(TAILS)], float)
        self.tail_v = np.array([tails.get(k, (0, 0))[1] for k in range(TAILS)], float)
        by_class = np.concatenate([self.head_counts.reshape(CLASSES, CLASS_WORDS).sum(1), self.tail_n + self.tail_v + 1])
        self.class_log = np.log((by_class + 0.5) / (by_class + 0.5).sum()).astype(np.float32)
        inside = np.where(np.arange(HEAD) < max(n_head, 1), self.head_counts + 0.5, 0).reshape(CLASSES, CLASS_WORDS)
        with np.errstate(divide="ignore", invalid="ignore"):
            self.word_log = np.where(inside > 0, np.log(inside / inside.sum(1, keepdims=True)), -1e9).astype(np.float32)


def _tail(word: bytes) -> int:
    return zlib.crc32(word[-2:]) % TAILS


def _most_frequent(counts: DataFrame) -> list[tuple[bytes, int]]:
    """Words by count, then bytes: all above the lowest count that keeps them within ``KNOWN``.

    The cut comes from a histogram of counts in sixteenths of powers of two, so that tasks send nothing but words that stay. A global sort with
    a limit would have every task send its own top to the driver.
    """
    step = F.floor(F.log2("c") * 16)
    histogram = sorted(((r["s"], r["n"]) for r in counts.groupBy(step.alias("s")).agg(F.count("*").alias("n")).collect()), reverse=True)  # at most 16 x 64 rows
    total, cut = 0, None
    for s, n in histogram:
        if total + n > KNOWN:
            break
        total, cut = total + n, s
    if cut is None:
        return []
    return sorted(((bytes(r["word"]), r["c"]) for r in counts.where(step >= cut).collect()), key=lambda x: (-x[1], x[0]))


def gather(docs: DataFrame, counts: DataFrame) -> Vocabulary:
    """Sizes, the top words (bounded by ``KNOWN``) and one row per tail class."""
    ends = docs.count()
    sums = counts.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n"), F.count("*").alias("v")).collect()[0]
    top = _most_frequent(counts)
    tails = {r["k"]: [r["n"], r["v"]] for r in counts.groupBy((F.crc32(F.expr("substring(word, greatest(octet_length(word) - 1, 1), 2)")) % TAILS).alias("k")).agg(F.sum("c").alias("n"), F.count("*").alias("v")).collect()}
    for w, c in top[: HEAD - 1]:
        tails[_tail(w)][0] -= c
        tails[_tail(w)][1] -= 1
    return Vocabulary(top, ends, {k: tuple(x) for k, x in tails.items()}, sums["n"] + ends, sums["v"] + (1 if ends else 0))


class Weights:
    def __init__(self, by_class: np.ndarray, by_word: np.ndarray):
        self.by_class, self.by_word = by_class, by_word

    @classmethod
    def zero(cls, tokens: int = 0):
        rows = min(max(1 << round(np.log2(16 * max(tokens, 1) ** 0.5)), LEAST_ROWS), MOST_ROWS)
        return cls(np.zeros((rows, CLASSES + TAILS), np.float32), np.zeros((rows, CLASS_WORDS), np.float32))


_P = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F), np.uint64(0x165667B19E3779F9))


def _hash(kind: int, a: np.ndarray, b, rows: int) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (a.astype(np.uint64, copy=False) + np.uint64(kind) * _P[2]) * _P[0] + np.asarray(b).astype(np.uint64, copy=False) * _P[1]
        h = (h ^ (h >> np.uint64(29))) * _P[2]
    return (h >> np.uint64(40)).astype(np.int64) & (rows - 1)


def _class_rows(history: np.ndarray, rows: int) -> list[np.ndarray]:
    """Rows of the class table for the last word, the one before, and the pair of both, rare ones by their class."""
    one, two, near, far = history
    return [_hash(1, one, 0, rows), _hash(2, two, 0, rows), _hash(3, near, far, rows)]


def _word_rows(history: np.ndarray, own_class: np.ndarray, rows: int) -> list[np.ndarray]:
    """Rows of the word table, given the class, for the last word and the one before."""
    return [_hash(4, history[0], own_class, rows), _hash(5, history[1], own_class, rows)]


def _gathered(base: np.ndarray, at: np.ndarray | None, table: np.ndarray, rows: list[np.ndarray]) -> np.ndarray:
    """base (its rows at ``at``, if given) plus the table's rows, without a copy for each sum."""
    out = np.take(table, rows[0], axis=0)
    out += base if at is None else np.take(base, at, axis=0)
    for r in rows[1:]:
        out += np.take(table, r, axis=0)
    return out


def _lower(logits: np.ndarray) -> None:
    """Subtract each row's largest value. Halves are compared as a whole: reducing short rows one by one is slower."""
    most = logits
    while most.shape[1] > 1 and most.shape[1] % 2 == 0:
        half = most.shape[1] // 2
        most = np.maximum(most[:, :half], most[:, half:])
    logits -= most.max(1, keepdims=True)


def _sums(x: np.ndarray) -> np.ndarray:
    return x @ np.ones(x.shape[1], x.dtype)


def _softmax(logits: np.ndarray) -> np.ndarray:
    _lower(logits)
    np.exp(logits, out=logits)
    logits *= (1 / _sums(logits))[:, None]
    return logits


def _tokens(text: bytes, ids: dict, known_context: np.ndarray, end: int) -> tuple[list, np.ndarray, np.ndarray, np.ndarray]:
    """Words, their ids (-1: not among the most frequent) with the end last, their context ids, and a number for each whole word."""
    words = text.lower().split()
    get = ids.get
    own = np.array([get(w, -1) for w in words] + [end], np.int64)
    context = known_context[own]
    whole = own
    if len(strange := np.flatnonzero(own < 0)):
        rare = [words[i] for i in strange.tolist()]
        whole = own.copy()
        context[strange] = [HEAD + _tail(w) for w in rare]
        whole[strange] = [zlib.crc32(w) + (1 << 32) for w in rare]
    return words, own, context, whole


def _history(contexts: list[np.ndarray], wholes: list[np.ndarray]) -> np.ndarray:
    """Last and last but one word of each token, then their context ids; before a document stand two starts."""

    def before(parts, start, k):
        return np.concatenate([np.concatenate([[start] * k, c[:-k]])[: len(c)] for c in parts])

    return np.stack([before(wholes, 1 << 33, 1), before(wholes, 1 << 33, 2), before(contexts, HEAD + TAILS, 1), before(contexts, HEAD + TAILS, 2)]).astype(np.int64)


def _class_of(context: np.ndarray) -> np.ndarray:
    return np.where(context < HEAD, context // CLASS_WORDS, CLASSES + context - HEAD)


def _push(table: np.ndarray, rows: np.ndarray, grads: np.ndarray, rate: float) -> None:
    """table[row] += rate * mean-bounded sum of the gradients of each row, for a table of an even number of columns."""
    n, wide = len(rows), table.shape[1]
    bits = n.bit_length()
    keys = np.sort(rows << bits | np.arange(n))  # rows in order, with the places they come from
    ranked, order = keys >> bits, keys & ((1 << bits) - 1)
    first = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
    times = np.diff(np.append(first, n))
    scale = np.empty(n, np.float32)
    scale[order] = np.repeat(rate * 0.5 / np.sqrt(times), times)
    # what came through a broadcast carries a dtype object of its own, and add.at is ten times slower unless both sides share one
    parts = np.empty((n, wide), table.dtype)
    np.multiply(grads, scale[:, None], out=parts)
    # two columns at a time, as the parts of a complex number: half as many places to add at
    pairs = wide // 2
    np.add.at(table.reshape(-1).view(np.complex64), (rows[:, None] * pairs + np.arange(pairs)).reshape(-1), parts.reshape(-1).view(np.complex64))


def train_step(w: Weights, v: Vocabulary, context: np.ndarray, history: np.ndarray, rate: float) -> None:
    """One gradient update from a batch of tokens."""
    own_class = _class_of(context)
    class_rows = _class_rows(history, len(w.by_class))
    p = _softmax(_gathered(v.class_log, None, w.by_class, class_rows))
    np.negative(p, out=p)
    p[np.arange(len(p)), own_class] += 1
    for r in class_rows:
        _push(w.by_class, r, p, rate)
    head = np.flatnonzero(context < HEAD)
    if len(head):
        c = own_class[head]
        rows = _word_rows(history[:, head], c, len(w.by_word))
        q = _softmax(_gathered(v.word_log, c, w.by_word, rows))
        np.negative(q, out=q)
        q[np.arange(len(q)), context[head] % CLASS_WORDS] += 1
        for r in rows:
            _push(w.by_word, r, q, rate)


def log_probability(w: Weights, v: Vocabulary, context: np.ndarray, history: np.ndarray) -> np.ndarray:
    """Natural log of each token's class, and of the word inside it for head words."""
    out = np.empty(len(context))
    for lo in range(0, len(context), BATCH):
        c, h = context[lo : lo + BATCH], history[:, lo : lo + BATCH]
        own = _class_of(c)
        logits = _gathered(v.class_log, None, w.by_class, _class_rows(h, len(w.by_class)))
        _lower(logits)
        part = logits[np.arange(len(c)), own]
        part -= np.log(_sums(np.exp(logits, out=logits)))
        head = np.flatnonzero(c < HEAD)
        if len(head):
            k = own[head]
            inner = _gathered(v.word_log, k, w.by_word, _word_rows(h[:, head], k, len(w.by_word)))
            _lower(inner)
            part[head] += inner[np.arange(len(head)), c[head] % CLASS_WORDS]
            part[head] -= np.log(_sums(np.exp(inner, out=inner)))
        out[lo : lo + BATCH] = part
    return out


def _groups(texts, v: Vocabulary, most: int = 1 << 17):
    """Numbered documents in groups of so many tokens."""
    held, size = [], 0
    for i, text in enumerate(texts):
        held.append((i, *_tokens(text, v.ids, v.context, v.end)))
        size += len(held[-1][3])
        if size >= most:
            yield held
            held, size = [], 0
    if held:
        yield held


def local_model(texts, v: Vocabulary) -> tuple[Weights, int]:
    """Weights after one pass of gradient updates over all tokens of the texts, and how many tokens these were."""
    w, seen = Weights.zero(v.total), 0
    for group in _groups(texts, v):
        context = np.concatenate([g[3] for g in group])
        history = _history([g[3] for g in group], [g[4] for g in group])
        # tokens of all the group's documents are mixed, else one document would fill a batch
        order = np.argsort(_hash(9, np.arange(len(context)), len(context), 1 << 24), kind="stable")
        for lo in range(0, len(order), BATCH):
            at = order[lo : lo + BATCH]
            train_step(w, v, context[at], history[:, at], RATE / (1 + seen / 4_000_000))
            seen += len(at)
    return w, seen


def _by_shard(batches):
    """(shard, texts) of each run of rows of one shard in Arrow batches."""
    for batch in batches:
        shard = batch.column(0).to_numpy()
        edges = [0, *(np.flatnonzero(np.diff(shard)) + 1).tolist(), len(shard)]
        for lo, hi in zip(edges, edges[1:]):
            if hi > lo:
                yield int(shard[lo]), byte_texts(batch.column(1).slice(lo, hi - lo))


def _places(spark, n: int) -> list[int]:
    """A number for each of n shards, such that hash partitioning sends them to n different partitions. Where it does not, shards share a task and nothing else."""
    at = F.pmod(F.hash("id"), F.lit(n))
    found = {r["at"]: r["id"] for r in spark.range(32 * n).groupBy(at.alias("at")).agg(F.min("id").alias("id")).collect()}  # n rows at most
    return [found.get(k, k) for k in range(n)]


def train(docs: DataFrame, v: Vocabulary) -> Weights:
    """Average of local models, each trained by gradient updates over its shard's every token.

    There is one model a shard, however many partitions the shards lie in, so what is exchanged does not grow with the partitions.
    """
    shared = docs.sparkSession.sparkContext.broadcast(v)
    shards = max(1, round((v.total / SHARD_TOKENS) ** 0.5))

    def run(batches):
        for _, own in groupby(_by_shard(batches), key=lambda x: x[0]):
            w, seen = local_model((text for _, texts in own for text in texts), shared.value)
            for part, table in enumerate((w.by_class, w.by_word) if seen else ()):
                blocks = table.astype(np.float16).reshape(len(table) // BLOCK, -1)
                for lo in range(0, len(blocks), 64):
                    n = len(some := blocks[lo : lo + 64])
                    yield pa.RecordBatch.from_arrays([pa.array([part] * n, pa.int32()), pa.array(range(lo, lo + n), pa.int32()), pa.array([seen] * n, pa.int64()), pa.array([x.tobytes() for x in some], pa.binary())], names=["part", "block", "seen", "w"])

    own = F.xxhash64("text", F.col("doc_id").cast("string"))
    shard = F.pmod(own, F.lit(shards)).cast("int")
    place = F.element_at(F.array(*map(F.lit, _places(docs.sparkSession, shards))), shard + 1)
    dealt = docs.select("text", own.alias("own"), shard.alias("shard"), place.alias("place")).repartition(shards, "place").sortWithinPartitions("shard", "own", "text").select("shard", "text")
    local = dealt.mapInArrow(run, "part int, block int, seen long, w binary")
    total = v.total

    def average(batches):
        # the rows of a block follow each other, so one sum is held at a time
        at, held = None, None
        for batch in batches:
            for part, block, seen, raw in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                x = np.frombuffer(raw, np.float16).astype(np.float64) * (seen / total)
                if (part, block) == at:
                    held += x
                    continue
                if at:
                    yield _block(at, held)
                at, held = (part, block), x
        if at:
            yield _block(at, held)

    mean = local.repartition("part", "block").sortWithinPartitions("part", "block", "seen", "w").mapInArrow(average, "part int, block int, w binary")
    w = Weights.zero(v.total)
    tables = [x.reshape(len(x) // BLOCK, -1) for x in (w.by_class, w.by_word)]
    for r in mean.collect():  # 2 MOST_ROWS / BLOCK rows at most
        tables[r["part"]][r["block"]] = np.frombuffer(r["w"], np.float16)
    return w


def _block(at: tuple[int, int], held: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([at[0]], pa.int32()), pa.array([at[1]], pa.int32()), pa.array([held.astype(np.float16).tobytes()], pa.binary())], names=["part", "block", "w"])


def score(docs: DataFrame, v: Vocabulary, w: Weights, counts: DataFrame) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    # weights are averaged in half precision, so this rounds nothing that training made
    shared = docs.sparkSession.sparkContext.broadcast((v, w.by_class.astype(np.float16), w.by_word.astype(np.float16)))

    def run(batches):
        v, *tables = shared.value
        w = Weights(*(x.astype(np.float32) for x in tables))
        unseen = v.total + v.distinct + 1
        for batch in batches:
            uid, doc, held = (batch.column(i).to_pylist() for i in (0, 1, 2))
            for group in _groups(byte_texts(batch.column(3)), v):
                all_ = np.concatenate([g[3] for g in group])
                logs = log_probability(w, v, all_, _history([g[3] for g in group], [g[4] for g in group])) / np.log(10) if v.total else np.zeros(len(all_))
                rows, owner, word, count, at = [], [], [], [], 0
                for i, words, own, context, _ in group:
                    n = len(own)
                    known = own >= 0
                    c = v.counts[own[known]].astype(float) if v.total else np.zeros(0)
                    base = float(np.log10((c + 1) / unseen).sum()) if v.total else 0.0
                    model = float(logs[at : at + n].sum())
                    at += n
                    tail = context >= HEAD
                    seen = tail & known
                    if v.total:
                        # inside a tail class: smoothed frequency; for words not among the most frequent the count comes by the join
                        k = context[tail] - HEAD
                        model -= float(np.log10(v.tail_n[k] + v.tail_v[k] + 1).sum())
                        model += float(np.log10(v.counts[own[seen]] + 1.0).sum())
                    rows.append((uid[i], doc[i], held[i], n, int(known.sum()) if v.total else 0, base, model, b" %d" % uid[i], None))  # a key of its own: no word holds a space
                    times: dict = {}
                    for j in np.flatnonzero(~known).tolist():
                        times[words[j]] = times.get(words[j], 0) + 1
                    owner += [uid[i]] * len(times)
                    word += times
                    count += times.values()
                yield _record(rows)
                if word:
                    given = {"uid": owner, "word": word, "times": count}
                    yield pa.RecordBatch.from_arrays([pa.array(given[f.name], f.type) if f.name in given else pa.nulls(len(word), f.type) for f in _FIELDS], schema=_FIELDS)

    named = docs.select(F.monotonically_increasing_id().alias("uid"), F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id"), 7, 2).alias("held_out"), "text")
    parts = named.mapInArrow(run, SCHEMA)
    rare = counts.select("word", "c")
    # every row of a rare word adds log10((c + 1) / all) to the base score and log10(c + 1) to the model's
    joined = parts.join(rare, "word", "left")
    unseen = float(np.log10(v.total + v.distinct + 1))
    log = F.log10(F.coalesce("c", F.lit(0)) + F.lit(1.0))
    isword = F.col("times").isNotNull()
    return (
        joined.groupBy("uid")
        .agg(
            F.max("doc_id").alias("doc_id"),
            F.max("held_out").alias("held_out"),
            F.max("n_tokens").alias("n_tokens"),
            (F.sum(F.coalesce("head_known", F.lit(0))) + F.sum(F.when(F.col("c") > 0, F.col("times")).otherwise(0))).alias("n_known"),
            (F.sum(F.coalesce("head_base", F.lit(0.0))) + F.sum(F.when(isword, F.col("times") * (log - unseen)).otherwise(0.0))).alias("base_score"),
            (F.sum(F.coalesce("model", F.lit(0.0))) + F.sum(F.when(isword, F.col("times") * log).otherwise(0.0))).alias("score"),
        )
        .select("doc_id", "held_out", "n_tokens", "n_known", F.lit(v.total).cast("long").alias("train_tokens"), "base_score", "score")
    )


_FIELDS = pa.schema([("uid", pa.int64()), ("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("head_known", pa.int64()), ("head_base", pa.float64()), ("model", pa.float64()), ("word", pa.binary()), ("times", pa.int64())])


def _record(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _FIELDS, strict=True)], schema=_FIELDS)


def fit_and_score(docs: DataFrame) -> DataFrame:
    """Learn from the documents that are not held out and score all."""
    training = docs.where(~held_out(docs["doc_id"], 7, 2))
    counts = materialize(count_words(training), "word-counts")
    v = gather(training, counts)
    w = train(training, v) if v.total else Weights.zero()
    return score(docs, v, w, counts)
