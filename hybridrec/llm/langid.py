"""Language identification by prediction by partial matching over bytes.

Every language has a byte context tree of orders 0 to ``ORDER``: how often each byte followed each
context in its training texts. A byte's code length comes from the longest context seen, escaping to
shorter ones with probability distinct/(total+distinct), down to a uniform byte. The commonest bytes are kinds of their own and the
rest share one, inside which they are uniform, so that in every context the probabilities of all 256 bytes add up to one. Training freezes the
trees, so the code length of a byte depends on it and the few bytes before it alone, and whole Arrow
batches are scored with array lookups.

Training texts are read whole. The sample's bound is on rows: at most ``TEXTS_A_LANGUAGE`` texts a language, chosen among those of at most ``LONGEST``
characters, so that a few giant texts cannot fill the driver. Prediction reads every text whole, whatever its length. Contexts beyond ``max_nodes``
an order, rarest first, and contexts seen once are coded by the next shorter one.

Defined results: a null text or one without a letter is ``und`` with score 0. Null ``lang`` rows teach
nothing. With no labelled row at all everything is ``und``. Ties go to the language that sorts first.
Rows that share a doc_id are scored each. Extra columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from hybridrec.llm.texts import held_out

ORDER = 3
#: Documented bound of the labelled sample: so many whole texts a language, those with the smallest hash among texts of so many characters at most.
TEXTS_A_LANGUAGE, LONGEST = 400, 1 << 16
#: Bytes are told apart up to so many kinds, the rest share one.
KINDS = 128
SCHEMA = "doc_id long, held_out boolean, lang_pred string, score double"


def training_rows(docs: DataFrame, texts: int = TEXTS_A_LANGUAGE) -> DataFrame:
    """The labelled sample: per language the ``texts`` rows with the smallest hash of doc_id among those not held out.

    Sampling is by a hash threshold per language before the exact cut, so no group meets in one task.
    """
    known = docs.select(F.col("doc_id"), F.col("lang"), F.col("text")).where((F.length("text") <= LONGEST) & F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"), 3, 1))
    hashed = known.select("lang", "doc_id", "text", F.xxhash64("doc_id").alias("h"))
    cuts = hashed.groupBy("lang").agg(F.count("*").alias("n"))
    share = 4.0 * texts / F.col("n")
    thin = hashed.join(F.broadcast(cuts), "lang").where((F.pmod("h", F.lit(1 << 20)) < F.ceil(share * (1 << 20))) | (F.col("n") <= 8 * texts))
    w = Window.partitionBy("lang").orderBy("h", "doc_id")
    return thin.select("lang", "doc_id", "h", F.col("text").cast("binary").alias("raw")).withColumn("r", F.row_number().over(w)).where(F.col("r") <= texts).select("lang", "raw")


class Trees:
    """Frozen statistics: ``kinds`` maps a byte to its kind, ``node`` a context of ORDER kinds to a tree node, ``cost[node, kind, language]`` is a code length in bits."""

    def __init__(self, languages, kinds, node, cost):
        self.languages, self.kinds, self.node, self.cost = languages, kinds, node, cost

    def byte_costs(self) -> np.ndarray:
        """Code lengths [node, byte, language] of all 256 bytes, laid out; the powers of two of each row add up to one."""
        return self.cost[:, self.kinds, :]


def grow(samples: list[tuple[str, bytes]], order: int = ORDER, max_nodes: int = 1 << 14) -> Trees | None:
    """Context trees from (language, bytes) samples; contexts beyond ``max_nodes`` fall back to the next shorter one, rarest first."""
    if not samples:
        return None
    languages = sorted({lang for lang, _ in samples})
    joined = {lang: np.frombuffer(b"".join(b"\n" * order + raw for x, raw in samples if x == lang), np.uint8) for lang in languages}
    seen = np.bincount(np.concatenate(list(joined.values())), minlength=256)
    ranked = [b for b in np.argsort(-seen, kind="stable") if seen[b]][: KINDS - 1]
    shared = 256 - len(ranked)  # bytes of the last kind
    kinds = np.full(256, KINDS - 1, np.int64)
    kinds[ranked] = np.arange(len(ranked))
    size = KINDS**order
    streams = {lang: kinds[x] for lang, x in joined.items()}
    # probability of each next kind, per language, for contexts of growing order
    tables: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    base = np.zeros((1, KINDS, len(languages)))
    base[:, : len(ranked)], base[:, KINDS - 1] = 1.0 / 256, shared / 256
    contexts = np.zeros(1, np.int64)
    for o in range(order + 1):
        counts: dict[str, tuple] = {}
        keys = []
        for lang, s in streams.items():
            n = len(s)
            c = np.zeros(max(n - order, 0), np.int64)
            for k in range(o):  # nearest byte is the lowest digit
                c += s[order - 1 - k : n - 1 - k] * KINDS**k
            u, m = np.unique(c * KINDS + s[order:], return_counts=True)
            counts[lang] = (u, m)
            keys.append(u // KINDS)
        if o:
            keys = np.concatenate(keys)
            total = np.concatenate([m for _, m in counts.values()])
            uniq, inv = np.unique(keys, return_inverse=True)
            weight = np.bincount(inv, total)
            fit = np.sort(np.argsort(-weight, kind="stable")[: max_nodes // 2])
            new = uniq[fit[weight[fit] > 1]]
            parent = np.searchsorted(contexts, new % KINDS ** (o - 1)) if o > 1 else np.zeros(len(new), np.int64)
            known = np.ones(len(new), bool) if o == 1 else (contexts[np.minimum(parent, len(contexts) - 1)] == new % KINDS ** (o - 1))
            new, parent = new[known], parent[known]
            lower = base[parent]
        else:
            new, lower = contexts, base
        table = np.empty((len(new), KINDS, len(languages)))
        for j, lang in enumerate(languages):
            u, m = counts[lang]
            at = np.searchsorted(new, u // KINDS)
            ok = (at < len(new)) & (new[np.minimum(at, len(new) - 1)] == u // KINDS) if len(new) else np.zeros(len(u), bool)
            hit = np.zeros((len(new), KINDS))
            hit[at[ok], (u % KINDS)[ok]] = m[ok]
            distinct, all_ = (hit > 0).sum(1, keepdims=True), hit.sum(1, keepdims=True)
            escape = np.where(all_ > 0, distinct / np.maximum(all_ + distinct, 1), 1.0)
            table[:, :, j] = np.where(all_ > 0, hit / np.maximum(all_ + distinct, 1), 0.0) + escape * lower[:, :, j]
        tables[o] = (new, table)
        contexts, base = new, table
    offset, node, costs = 0, np.zeros(size, np.int32), []
    for o in range(order + 1):
        found, table = tables[o]
        costs.append(-np.log2(np.maximum(table, 1e-30)).astype(np.float32))
        if o == order:
            node[found] = offset + np.arange(len(found))
        elif o:
            view = node.reshape(-1, KINDS**o)
            view[:, found] = offset + np.arange(len(found), dtype=np.int32)
        offset += len(found)
    cost = np.concatenate(costs)
    cost[:, KINDS - 1] += np.float32(np.log2(shared))
    return Trees(languages, kinds.astype(np.int32), node, cost)


def code_lengths(trees: Trees, data: np.ndarray, starts: np.ndarray, order: int = ORDER, block: int = 1 << 20) -> np.ndarray:
    """Bits of each text under each language; texts lie one after another in ``data`` from ``starts`` (with the end last)."""
    n, out = len(starts) - 1, np.zeros((len(starts) - 1, len(trees.languages)))
    pad = int(trees.kinds[ord("\n")])
    for lo in range(0, len(data), block):
        hi = min(lo + block, len(data))
        s = trees.kinds[data[max(lo - order, 0) : hi]]
        s = np.concatenate([np.full(order - (lo - max(lo - order, 0)), pad, np.int32), s])
        first, last = np.searchsorted(starts, lo, "right") - 1, np.searchsorted(starts, hi, "left")
        c = np.zeros(hi - lo, np.int32)
        for k in range(order):
            c += s[order - 1 - k : len(s) - 1 - k] * np.int32(KINDS**k)
        cuts = starts[first:last].clip(lo) - lo
        begun = starts[first:last]
        for k in range(order):  # the first bytes of a text see no bytes of the text before it
            at = begun[(begun + k >= lo) & (begun + k < hi) & (begun + k < starts[first + 1 : last + 1])] + k - lo
            for j in range(k, order):
                c[at] += (pad - s[order + at - 1 - j]) * np.int32(KINDS**j)
        bits = trees.cost[trees.node[c], s[order:]]
        sums = np.add.reduceat(bits, np.minimum(cuts, hi - lo - 1), axis=0, dtype=np.float64)
        sums[np.diff(np.append(cuts, hi - lo)) == 0] = 0
        out[first : first + len(cuts)] += sums
    return out


def _bytes_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All UTF-8 bytes of an Arrow string column and each text's start, with the end last."""
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    large = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    ends = np.frombuffer(column.buffers()[1], np.int64 if large else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = column.buffers()[2]
    return (np.frombuffer(raw, np.uint8)[ends[0] : ends[-1]] if raw is not None and len(raw) else np.zeros(0, np.uint8)), ends - ends[0]


def predict(docs: DataFrame, trees: Trees | None) -> DataFrame:
    """doc_id, held_out, lang_pred and the posterior of the prediction under equal priors."""
    spark = docs.sparkSession
    frozen = spark.sparkContext.broadcast(trees)  # bounded by KINDS, ORDER and max_nodes

    def run(batches):
        t = frozen.value
        for batch in batches:
            data, starts = _bytes_of(batch.column(2))
            spoken = np.array(batch.column(3).to_pylist(), bool)
            n = batch.num_rows
            if t is None or not n:
                names, score = ["und"] * n, np.zeros(n)
            else:
                bits = code_lengths(t, data, starts)
                best = bits.argmin(1)
                weight = np.exp2(np.maximum(bits[np.arange(n), best][:, None] - bits, -1000))
                score = np.where(spoken, 1 / weight.sum(1), 0.0)
                names = [t.languages[b] if s else "und" for b, s in zip(best, spoken, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(names, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id").cast("long"), held_out(F.col("doc_id"), 3, 1).alias("held_out"), text.alias("text"), text.rlike("\\p{L}").alias("spoken")).mapInArrow(run, SCHEMA)


def identify(docs: DataFrame) -> DataFrame:
    """Train on the labelled sample and predict every document."""
    samples = [(r["lang"], bytes(r["raw"])) for r in training_rows(docs).collect()]  # bounded by languages x TEXTS_A_LANGUAGE x LONGEST
    return predict(docs, grow(samples))
