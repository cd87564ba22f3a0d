"""Token counts that follow edits.

Each document keeps a segment tree over pre-token runs (white space and the word after it): a leaf knows
its characters and tokens, an inner node the sums below. An edit re-encodes the leaves it touches and
one neighbour on either side, since a run's ids depend on nothing beyond its own borders, and then
updates the sums on the way to the root. Many small edits of a long document so cost little more
than their own length.

Defined results: null text is empty with 0 tokens. Edits refer to the original text in code points, end
exclusive, are applied from left to right, must not overlap (a later edit that starts inside an earlier one
is ignored, as is one beyond the text) and may be null or empty. Rows that share a doc_id are counted each. Extra columns
are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, functions as F

from hybridrec.llm.texts import Memo, matches
from hybridrec.llm.tokens import vocabulary_path

VOCABULARY = "byte_bpe_50k.tiktoken"
SCHEMA = "doc_id long, tokens_before long, tokens_after long, n_edits long, chars_after long, chars_encoded long"
#: A run is white space and what follows up to the next white space; no pre-token crosses its borders.
RUN = re.compile("[ \t\n\r\x0b\x0c]*[^ \t\n\r\x0b\x0c]+|[ \t\n\r\x0b\x0c]+")
#: Other characters that a vocabulary takes as white space: they may join with ASCII space, so their texts are one run.
ODD_SPACE = re.compile("[\x1c-\x1f\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")


@lru_cache(2)
def encoder(path: str):
    """Token counts of runs, remembered."""
    import base64

    import public_tokenizers
    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    code = tiktoken.Encoding("public", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    return Memo(lambda runs: [len(code.encode_ordinary(x)) for x in runs])


def runs_of(text: str) -> list[str]:
    return RUN.findall(text) if not ODD_SPACE.search(text) else [text] if text else []


class SegmentTree:
    """Characters and tokens of runs, with their sums in a heap of twice the leaves."""

    def __init__(self, runs: list[str], counts: list[int]):
        size = 1
        while size < len(runs):
            size *= 2
        self.size, self.runs, self.origin = size, list(runs), [len(x) for x in runs]
        self.chars = [0] * size + self.origin + [0] * (size - len(runs))
        self.tokens = [0] * size + list(counts) + [0] * (size - len(runs))
        for i in range(size - 1, 0, -1):
            self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
            self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    def find(self, at: int) -> tuple[int, int]:
        """The leaf that holds original position ``at`` and the position it begins on; the last one if beyond."""
        i, begin = 1, 0
        while i < self.size:
            i *= 2
            if at >= begin + self.chars[i] and self.chars[i + 1]:
                begin += self.chars[i]
                i += 1
        return i - self.size, begin

    def set_tokens(self, leaf: int, tokens: int) -> None:
        i = leaf + self.size
        delta = tokens - self.tokens[i]
        while i:
            self.tokens[i] += delta
            i //= 2

    def total(self) -> int:
        return self.tokens[1] if self.runs else 0


def count_with_edits(text: str, edits: list[tuple[int, int, str]], memo: Memo) -> tuple[int, int, int, int, int]:
    """Tokens before and after, edits applied, characters after, characters encoded again."""
    runs = runs_of(text)
    got = memo.load(runs)
    counts = [got[r] for r in runs]
    before = sum(counts)
    if not edits:
        return before, before, 0, len(text), 0
    tree = SegmentTree(runs, counts) if runs else SegmentTree([""], [0])
    # group edits whose touched leaves, with one neighbour either side, meet
    groups: list[list] = []
    done, applied, length = 0, 0, len(text)
    for start, end, new in sorted((e for e in edits if e[0] is not None and e[1] is not None), key=lambda e: (e[0], e[1])):
        if start < done or start > len(text) or end < start or start < 0:
            continue
        end, new = min(end, len(text)), new or ""
        done, applied = end, applied + 1
        length += len(new) - (end - start)
        first, begin = tree.find(start)
        last, _ = tree.find(max(start, end - 1))
        first, last = first - 1, last + 1
        if first >= 0:
            begin -= tree.origin[first] if tree.runs and runs else 0
        first, last = max(first, 0), min(last, max(len(tree.runs) - 1, 0))
        if groups and first <= groups[-1][1]:
            groups[-1][1] = max(last, groups[-1][1])
            groups[-1][3].append((start, end, new))
        else:
            groups.append([first, last, begin, [(start, end, new)]])
    encoded = 0
    for first, last, begin, own in groups:
        old = "".join(tree.runs[first : last + 1])
        parts, at = [], 0
        for start, end, new in own:
            parts += [old[at : start - begin], new]
            at = end - begin
        parts.append(old[at:])
        changed = "".join(parts)
        again = runs_of(changed)
        encoded += len(changed)
        known = memo.load(again)
        tree.set_tokens(first, sum(known[r] for r in again))
        tree.runs[first] = changed
        for leaf in range(first + 1, last + 1):
            tree.set_tokens(leaf, 0)
            tree.runs[leaf] = ""
    return before, tree.total(), applied, length, encoded


def count(docs: DataFrame, edits: Column | None = None, path: str | None = None) -> DataFrame:
    """Token counts of whole texts before and after ``edits``, an array<struct<start, end, new>> column over ``docs``."""
    none = F.array().cast("array<struct<start:int,end:int,new:string>>")

    def run(batches):
        memo = encoder(path or vocabulary_path(VOCABULARY))
        for batch in batches:
            out = []
            for doc, text, marks in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                text = text or ""
                if marks and ODD_SPACE.search(text + "".join(m["new"] or "" for m in marks if m)):
                    after, at, applied = [], 0, 0
                    for m in sorted((m for m in marks if m and m["start"] is not None and m["end"] is not None), key=lambda m: (m["start"], m["end"])):
                        if m["start"] >= at and m["start"] <= len(text) and m["end"] >= m["start"] >= 0:
                            after += [text[at : m["start"]], m["new"] or ""]
                            at, applied = min(m["end"], len(text)), applied + 1
                    after = "".join([*after, text[at:]])
                    totals = [sum(memo.load(r)[x] for x in r) for r in (runs_of(text), runs_of(after))]
                    row = (*totals, applied, len(after), len(after))
                else:
                    row = count_with_edits(text, [(m["start"], m["end"], m["new"]) for m in marks or () if m], memo)
                out.append((doc, *row))
            columns = list(zip(*out, strict=True)) if out else [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=[f.split()[0] for f in SCHEMA.split(", ")])

    return docs.select(F.col("doc_id").cast("long"), "text", (F.coalesce(edits, none) if edits is not None else none).alias("edits")).mapInArrow(run, SCHEMA)


def mask_edits(text: Column, pattern: str, new: str) -> Column:
    """Edits that replace every match of a Java pattern."""
    edits = F.transform(matches(text, pattern), lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), F.lit(new).alias("new")))
    return F.when(text.rlike(pattern), edits)
