"""Pieces the text operators share."""

from __future__ import annotations

from collections import ChainMap

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

#: Words are maximal runs without ASCII white space.
SPACE = "[\\x20\\x09-\\x0D]+"
#: Lower-cases A-Z only, so that the JVM and byte-wise Python agree on every text.
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(text: Column) -> Column:
    return F.translate(text, UPPER, LOWER)


def held_out(doc_id: Column, modulus: int, remainder: int) -> Column:
    """True where crc32 of the id's decimal text leaves ``remainder``."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % modulus == remainder, F.lit(False))


def running(lengths: Column) -> Column:
    """Sums of all elements before each one, in n^1.5 steps at most: appending to one long list would copy it each time.

    Lists of about the root of the size are summed on their own, then moved by the sums before them.
    """
    ints = F.array().cast("array<int>")

    def add(a, x):
        return F.struct((a["at"] + x).alias("at"), F.array_append(a["all"], a["at"]).alias("all"))

    def sums(xs):
        return F.aggregate(xs, F.struct(F.lit(0).alias("at"), ints.alias("all")), add)

    def of(v):
        size = F.size(v["xs"])
        step = F.greatest(F.lit(32), F.ceil(F.sqrt(size)).cast("int"))
        parts = F.transform(F.sequence(F.lit(0), F.floor((size - 1) / step).cast("int")), lambda j: sums(F.slice(v["xs"], j * step + 1, step)))
        return F.transform(F.array(parts), joined)[0]

    def joined(parts):
        before = sums(F.transform(parts, lambda x: x["at"]))["all"]
        return F.flatten(F.zip_with(parts, before, lambda x, b: F.transform(x["all"], lambda y: y + b)))

    return F.when(F.size(lengths) > 0, F.transform(F.array(F.struct(lengths.alias("xs"))), of)[0]).otherwise(ints)


def matches(text: Column, pattern: str) -> Column:
    """start, end and text of all leftmost matches of a Java pattern, in order."""
    between, found = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))

    def of(v):
        steps = F.zip_with(v["b"], v["m"], lambda b, m: F.length(b) + F.coalesce(F.length(m), F.lit(0)))
        return F.transform(F.array(F.struct(v["b"].alias("b"), v["m"].alias("m"), running(steps).alias("at"))), placed)[0]

    def placed(v):
        each = F.arrays_zip(v["m"].alias("m"), F.slice(v["b"], F.lit(1), F.size(v["m"])).alias("b"), F.slice(v["at"], F.lit(1), F.size(v["m"])).alias("at"))
        return F.transform(each, lambda x: F.struct((x["at"] + F.length(x["b"])).alias("start"), (x["at"] + F.length(x["b"]) + F.length(x["m"])).alias("end"), x["m"].alias("text")))

    return F.transform(F.array(F.struct(between.alias("b"), found.alias("m"))), of)[0]


def slim(docs: DataFrame, *columns: str) -> DataFrame:
    """Only the named columns, so that extra ones, whatever their names, never travel."""
    return docs.select(*[docs[c] for c in columns])


def byte_texts(column: pa.Array) -> list[bytes]:
    """UTF-8 bytes of each text without decoding; null is empty."""
    return [x if x is not None else b"" for x in column.cast(pa.binary()).to_pylist()]


def crc_modulus(ids: list, modulus: int) -> np.ndarray:
    import zlib

    return np.array([zlib.crc32(str(i).encode()) % modulus if i is not None else -1 for i in ids], dtype=np.int64)


class Memo:
    """Bounded word -> value memory of a Python worker.

    Two generations: when the young one is full it replaces the old one, so what recurs stays and
    memory is at most twice ``size`` entries, of ``longest`` characters at most, whatever the input: longer words are
    filled in anew each time and forgotten with the mapping that is returned. A worker that serves one stage after another keeps
    the words of one memory only: the memory last asked empties the one before.
    """

    _filled: Memo | None = None

    def __init__(self, fill, size: int = 400_000, longest: int = 64):
        self.fill, self.size, self.longest, self.young, self.old = fill, size, longest, {}, {}

    def load(self, words: list) -> dict:
        """A mapping that holds every one of ``words``."""
        if Memo._filled is not self:
            if Memo._filled is not None:
                Memo._filled.young, Memo._filled.old = {}, {}
            Memo._filled = self
        young = self.young
        missing = set(words).difference(young)
        if missing:
            if len(young) + len(missing) > self.size and young:
                self.old, self.young = young, {}
                young, missing = self.young, set(words)
            if old := self.old:
                for w in [w for w in missing if w in old]:
                    young[w] = old[w]
                    missing.discard(w)
            if missing:
                missing = list(missing)
                values = self.fill(missing)
                long_ = {w: x for w, x in zip(missing, values, strict=True) if len(w) > self.longest}
                if long_:
                    young.update((w, x) for w, x in zip(missing, values, strict=True) if w not in long_)
                    return ChainMap(young, long_)
                young.update(zip(missing, values, strict=True))
        return young
