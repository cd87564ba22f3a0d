"""Quality rules by tokeniser fertility.

A public vocabulary with byte fallback encodes each white-space word of a text. Three figures tell
natural text from junk: characters (letters and digits) per token, the share of tokens that are raw bytes, and the entropy
of the token distribution. Each language or, failing that, script has a band; a text outside is rejected.
Base counts (words, symbols, repeated lines, repeated three-word windows) come with it.

Defined results: null and empty texts have no words, all counts 0, and fail. Null or unknown ``lang``
falls back to the script of most letters. Copies get equal rows. Extra columns are ignored by
:func:`measure` and kept by :func:`keep`; an empty table gives an empty result. Whole texts count,
however long; memory is bounded by one Arrow batch plus the bounded word memory.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.llm.texts import Memo, byte_texts, slim
from hybridrec.llm.tokens import vocabulary_path


@dataclass(frozen=True)
class Band:
    """Least and most letters and digits per token, most byte share, least entropy and least min-entropy in bits."""

    low: float
    high: float
    bytes_most: float = 0.25
    entropy_least: float = 5.2
    #: Entropy of order infinity: minus log2 of the commonest token's share.
    min_entropy_least: float = 2.85


@dataclass(frozen=True)
class Rules:
    vocabulary: str = "piece_bpe_32k.model"
    min_words: int = 50
    #: Percent of words inside repeated three-word windows above which a text fails.
    max_repeat: int = 50
    #: Entropy of a short text cannot reach a long one's: the bound is this share of log2(tokens) at most.
    entropy_share: float = 0.72
    by_lang: dict = field(default_factory=lambda: {"en": Band(1.66, 7.0), "de": Band(1.8, 7.0), "fr": Band(1.5, 7.0), "es": Band(1.5, 7.0)})
    by_script: dict = field(default_factory=lambda: {"latin": Band(1.45, 7.0), "greek": Band(0.8, 5.0, 0.5), "cyrillic": Band(1.0, 5.0, 0.5), "han": Band(0.3, 3.0, 0.8, 4.5, 2.0), "other": Band(0.25, 7.0, 0.95, 4.0, 1.5)})


#: Rows that :func:`keep` judges and hands on at a time.
STEP = 1024
SYMBOLS = b"#*$%&|<>"
#: ASCII that is neither letter nor digit: punctuation should not make a text look fertile.
_MARKS = bytes(b for b in range(128) if not chr(b).isalnum())
SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_tokens long, chars_per_token double, byte_share double, token_entropy double, min_entropy double, script string, base_failed boolean, kept boolean, reason string"
SCHEMA_FIELDS = [tuple(x.split()) for x in SCHEMA.split(", ")]


@lru_cache(2)
def _encoder(path: str):
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    return Memo(lambda words: [np.array(x, "<u4").tobytes() for x in model.encode([w.decode("utf-8", "replace") for w in words], num_threads=1)])


@lru_cache(2)
def _byte_ids(path: str) -> tuple[int, int]:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    raw = [i for i in range(model.get_piece_size()) if model.is_byte(i)]
    return (min(raw), max(raw) + 1) if raw else (0, 0)


def _repeated(words: list) -> int:
    """Words inside three-word windows that occur twice or more, all occurrences counted."""
    n = len(words)
    if n < 4:
        return 0
    h = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
    with np.errstate(over="ignore"):
        w = (h[:-2] * np.uint64(0x9E3779B97F4A7C15) + h[1:-1]) * np.uint64(0xC2B2AE3D27D4EB4F) + h[2:]
    order = np.argsort(w, kind="stable")
    ranked = w[order]
    same = ranked[1:] == ranked[:-1]
    if not same.any():
        return 0
    twice = np.zeros(n - 2, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(n, bool)
    for k in range(3):
        covered[k : n - 2 + k] |= twice
    return int(covered.sum())


def _letters(words: bytes) -> int:
    bare = words.translate(None, _MARKS)
    return len(bare) if bare.isascii() else len(bare.decode("utf-8", "replace"))


def _repeated_lines(text: bytes) -> int:
    lines = [x for x in text.split(b"\n") if x.strip(b" \t\n\r\x0b\x0c")]
    return len(lines) - len(set(lines))


_NOT_LATIN = re.compile("[^\x00-\u024f\u1e00-\u1eff\u2000-\u206f]")
_SCRIPTS = (("greek", re.compile("[\u0370-\u03ff\u1f00-\u1fff]")), ("cyrillic", re.compile("[\u0400-\u052f]")), ("han", re.compile("[\u3040-\u30ff\u3400-\u9fff\uac00-\ud7af]")))
_LATIN = re.compile("[A-Za-z\u00c0-\u024f\u1e00-\u1eff]")


def _script(text: bytes) -> str:
    """The script of most letters; Latin unless another has more."""
    if text.isascii():
        return "latin"
    s = text.decode("utf-8", "replace")
    if not (foreign := len(_NOT_LATIN.findall(s))):
        return "latin"
    best, most = "latin", len(_LATIN.findall(s))
    for name, pattern in _SCRIPTS:
        if (n := len(pattern.findall(s))) > most:
            best, most = name, n
    return best if most >= foreign or best != "latin" else "other"


def _figures(ids: np.ndarray, raw: tuple[int, int]) -> tuple[int, float, float, float]:
    """Tokens, share of raw bytes, entropy and min-entropy in bits."""
    n = len(ids)
    if not n:
        return 0, 0.0, 0.0, 0.0
    counts = np.bincount(ids)
    counts = counts[counts > 0]
    share = float(((ids >= raw[0]) & (ids < raw[1])).sum()) / n
    return n, share, float(np.log2(n) - (counts * np.log2(counts)).sum() / n), float(np.log2(n / counts.max()))


def measure(docs: DataFrame, rules: Rules = Rules(), path: str | None = None) -> DataFrame:
    """One row of figures and verdict per document (columns of :data:`SCHEMA`)."""
    name = rules.vocabulary

    def run(batches):
        where = path or vocabulary_path(name)
        for batch in batches:
            yield _rows([(doc, *row) for doc, row in zip(batch.column(0).to_pylist(), _judge(batch.column(1), batch.column(2), rules, where), strict=True)])

    return docs.select(*_inputs(docs)).mapInArrow(run, SCHEMA)


def _inputs(docs: DataFrame) -> list:
    return [F.col("doc_id"), F.col("text"), (F.col("lang") if "lang" in docs.columns else F.lit(None)).cast("string").alias("lang")]


def _judge(texts: pa.Array, langs: pa.Array, rules: Rules, where: str) -> list[tuple]:
    """Figures and verdict of each text, in the order of :data:`SCHEMA` without the id."""
    memo, raw, out = _encoder(where), _byte_ids(where), []
    for text, lang in zip(byte_texts(texts), langs.to_pylist(), strict=True):
        words = text.split()
        got = memo.load(words)
        joined = b"".join(words)
        chars = len(joined) if joined.isascii() else len(joined.decode("utf-8", "replace"))
        symbols = len(joined) - len(joined.translate(None, SYMBOLS))
        n, share, entropy, peak = _figures(np.frombuffer(b"".join([got[w] for w in words]), "<u4"), raw)
        repeats, script = _repeated(words), _script(text)
        failed = len(words) < rules.min_words or 100 * repeats > rules.max_repeat * len(words)
        band = rules.by_lang.get(lang) or rules.by_script.get(script) or rules.by_script["other"]
        if script != "latin" and lang in rules.by_lang:
            band = rules.by_script.get(script, band)
        fertility = _letters(joined) / n if n else 0.0
        reason = None
        if failed:
            reason = "base"
        elif not band.low <= fertility <= band.high:
            reason = "characters per token"
        elif share > band.bytes_most:
            reason = "byte fallback"
        elif entropy < min(band.entropy_least, rules.entropy_share * np.log2(max(n, 2))) or peak < band.min_entropy_least:
            reason = "token entropy"
        out.append((len(words), chars, symbols, _repeated_lines(text), repeats, n, fertility, share, entropy, peak, script, failed, reason is None, reason))
    return out


_ARROW = pa.schema([("doc_id", pa.int64()), *[(c, pa.int64()) for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_tokens")], *[(c, pa.float64()) for c in ("chars_per_token", "byte_share", "token_entropy", "min_entropy")], ("script", pa.string()), ("base_failed", pa.bool_()), ("kept", pa.bool_()), ("reason", pa.string())])


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) if rows else [[] for _ in _ARROW]
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, _ARROW, strict=True)], schema=_ARROW)


def keep(docs: DataFrame, rules: Rules = Rules(), path: str | None = None) -> DataFrame:
    """The documents that pass, with all their columns; every row is judged by its own text, in one pass and without a shuffle."""
    name = rules.vocabulary
    whole = docs.select(*_inputs(docs)[1:], F.struct(*docs.columns).alias("d"))  # one column, so that no name can clash
    into = whole.select("d").schema

    def run(batches):
        where = path or vocabulary_path(name)
        at = [f[0] for f in SCHEMA_FIELDS].index("kept") - 1
        for whole_batch in batches:
            for begin in range(0, whole_batch.num_rows, STEP):
                batch = whole_batch.slice(begin, STEP)
                good = pa.array([row[at] for row in _judge(batch.column(0), batch.column(1), rules, where)], pa.bool_())
                yield pa.RecordBatch.from_arrays([batch.column(2).filter(good)], names=["d"])

    kept = whole.mapInArrow(run, into)
    return kept.select(*[F.col("d")[c].alias(c) for c in docs.columns])


def digest(docs: DataFrame) -> DataFrame:
    return slim(measure(docs), "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_tokens", "chars_per_token", "byte_share", "token_entropy", "min_entropy", "reason")
