"""Sequence packing, shortest pack first over the length histogram.

A document is its vocabulary ids and one end id. What exceeds the sequence length is cut into full pieces,
each a sequence of its own; one shorter piece remains. Remainders are packed by their histogram alone:
lengths are placed longest first, always into the open pattern with the least room used that still fits
(the shortest pack), and a count says how many sequences follow each pattern. Patterns are then joined
back to documents by rank within their length. The histogram has at most one row per length, so what
the driver holds is bounded by the sequence length and not by the input.

Defined results: null text is empty and yields its end id alone. Rows that share a doc_id are packed
each on its own; equal rows get neighbouring ranks. Extra columns are ignored; an empty table gives an
empty result. Texts may be of any length.
"""

from __future__ import annotations

import zlib
from bisect import bisect_left, insort
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from hybridrec.llm.texts import byte_texts
from hybridrec.llm.tokens import vocabulary_path, word_ids
from hybridrec.runtime import materialize

END_ID, LENGTH, VOCABULARY = 2, 4096, "word_bpe_49k.json"
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"


def cut(docs: DataFrame, length: int = LENGTH, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    """Pieces of every document: full ones, then one remainder (none if the document ends on a cut)."""
    end = np.array([end_id], "<u4").tobytes()

    def run(batches):
        coder = word_ids(path or vocabulary_path(VOCABULARY))
        step = 4 * length
        for batch in batches:
            out = []
            for doc, text in zip(batch.column(0).to_pylist(), byte_texts(batch.column(1)), strict=True):
                ids = coder.ids(text) + end
                out += [(doc, lo // 4, (min(lo + step, len(ids)) - lo) // 4, zlib.crc32(ids[lo : lo + step]), len(ids) // 4) for lo in range(0, len(ids), step)]
            columns = list(zip(*out, strict=True)) if out else [[]] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, PIECES)


def shortest_pack_first(histogram: dict[int, int], length: int = LENGTH) -> list[tuple[int, tuple[int, ...]]]:
    """(count, lengths) of every packing pattern.

    Open patterns are kept by room left. A length goes to the pattern with most room, that is the shortest
    pack; of a pattern that stands for more sequences than there are pieces, the rest stays open as it was.
    """
    open_: dict[int, list] = defaultdict(list)
    rooms: list[int] = []
    done: list[tuple[int, tuple[int, ...]]] = []

    def put(room, count, parts):
        if room == 0:
            done.append((count, parts))
            return
        if room not in open_:
            insort(rooms, room)
        open_[room].append((count, parts))

    for size in sorted(histogram, reverse=True):
        left = histogram[size]
        fresh: list[tuple[int, int, tuple[int, ...]]] = []
        while left:
            if not rooms or rooms[-1] < size:
                fit = min(length // size, left)  # as many as fit into one new sequence
                per = left // fit
                fresh.append((length - fit * size, per, (size,) * fit))
                left -= per * fit
                continue
            room = rooms[-1]
            count, parts = open_[room].pop()
            if not open_[room]:
                del open_[room]
                rooms.pop(bisect_left(rooms, room))
            used = min(count, left)
            if count > used:
                put(room, count - used, parts)
            fresh.append((room - size, used, (*parts, size)))
            left -= used
            if fresh[-1][0] >= size and left:  # still room for this very length
                put(*fresh.pop())
        for room, count, parts in fresh:
            put(room, count, parts)
    return done + [x for group in open_.values() for x in group]


def pack(docs: DataFrame, length: int = LENGTH, end_id: int = END_ID, path: str | None = None) -> DataFrame:
    """Pieces with the sequence each lies in and its offset there."""
    spark = docs.sparkSession
    pieces = materialize(cut(docs, length, end_id, path), "pieces")
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most ``length`` rows
    full = histogram.pop(length, 0)
    slots, first_sequence, taken = [], full, defaultdict(int)
    for count, parts in shortest_pack_first(histogram, length):
        offset = 0
        for size in parts:  # ranks taken[size] .. taken[size]+count-1 of this size go here, one a sequence
            slots.append((size, taken[size], count, first_sequence, offset))
            taken[size] += count
            offset += size
        first_sequence += count
    if full:
        slots.append((length, 0, full, 0, 0))
    plan = spark.createDataFrame(slots, "length long, rank_from long, n long, first_sequence long, offset long")
    ranked = _ranked(pieces, max(16, max([full, *histogram.values()], default=0) // 50_000))
    # patterns have at most length^2/2 slots whatever the input; a slot is found by its first rank
    lookup = plan.groupBy("length").agg(F.sort_array(F.collect_list(F.struct("rank_from", "first_sequence", "offset"))).alias("slots"))
    joined = ranked.join(F.broadcast(lookup), "length")
    found = F.expr("slots[int(aggregate(slots, named_struct('lo', 0, 'n', 0), (a, s) -> named_struct('lo', if(s.rank_from <= rank, a.n, a.lo), 'n', a.n + 1)).lo)]")
    hit = joined.withColumn("slot", found)
    return hit.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("slot.first_sequence") + F.col("rank") - F.col("slot.rank_from")).alias("sequence_id"), F.col("slot.offset").alias("offset"))


def _ranked(pieces: DataFrame, buckets: int) -> DataFrame:
    """Rank of each piece among those of its length, without bringing a length into one task.

    Rows are numbered inside buckets of (length, hash of the document), of some 50,000 rows at most; the bucket sizes give each bucket's first rank.
    """
    keyed = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "start"), F.lit(buckets)).cast("int"))
    sizes = keyed.groupBy("length", "bucket").agg(F.count("*").alias("size"))
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    first = sizes.select("length", "bucket", F.coalesce(F.sum("size").over(before), F.lit(0)).alias("first"))  # at most length x buckets rows
    inside = Window.partitionBy("length", "bucket").orderBy("doc_id", "start", "ids_crc32", "doc_tokens")
    numbered = keyed.withColumn("rank", F.row_number().over(inside) - 1)
    return numbered.join(first, ["length", "bucket"]).withColumn("rank", F.col("rank") + F.col("first")).drop("bucket", "first")
