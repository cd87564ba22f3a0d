"""Personal data spans: patterns propose, checksums confirm, nearby words adjust.

Everything is a column expression. A pattern's matches and the pieces between them come from the same
leftmost scan, so positions follow from running lengths. Quantifiers are possessive where what follows cannot
start inside, and a look-behind keeps a failed run from being tried again at each of its characters: scans
stay linear and never recurse, however long the text and however many its matches.

Kinds: ``email``, ``ip``, ``card`` (Luhn) and ``phone`` always stay; ``iban`` (mod 97), ``national_id`` (nine digits in
3-2-4 groups), ``birth_date`` and ``secret`` (long runs of mixed characters) are added by the method. A span's score is its kind's base, plus a bonus when the
checksum holds, plus a bonus when a context word of its kind stands within ``WINDOW`` characters before it; added kinds need ``LEAST``, which all but
``iban`` reach by context alone.

Defined results: null text is empty and has no spans. Rows that share a doc_id are scanned each. Extra columns are
ignored; an empty table gives an empty result. Positions are code points, end exclusive.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, functions as F

from hybridrec.llm.texts import matches

WINDOW, LEAST = 40, 0.6
#: What each kind's pattern accepts. Fixed by the contract for the first four.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "iban": r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]{4}){2,7}+(?:\x20?[A-Z0-9]{1,3})?+(?![A-Za-z0-9])",
    "national_id": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "birth_date": r"(?<![0-9])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{1,2}[./][0-9]{1,2}[./][0-9]{4})(?![0-9])",
    "secret": r"(?<![A-Za-z0-9_-])(?=[A-Za-z_-]{0,40}[0-9])[A-Za-z0-9_-]{16,128}+(?![A-Za-z0-9_-])",
}
#: Cheap necessary conditions, tested before a pattern runs.
HINTS = {"email": "@", "phone": "+", "ip": ".", "national_id": "-"}
BASE_SCORE = {"email": 0.9, "ip": 0.7, "card": 0.6, "phone": 0.7, "iban": 0.35, "national_id": 0.4, "birth_date": 0.35, "secret": 0.4}
CHECKED_BONUS, CONTEXT_BONUS = 0.3, 0.25
#: Words that speak for a kind, in the languages at hand.
CONTEXT = {
    "email": "mail|e-mail|contact|kontakt|correo|courriel",
    "ip": "ip|host|server|address|adresse",
    "card": "card|visa|mastercard|karte|carte|tarjeta|credit|kredit",
    "phone": "phone|tel|call|mobile|telefon|handy|fax",
    "iban": "iban|bank|account|konto|compte|cuenta",
    "national_id": "ssn|social|security|id|identity|tax",
    "birth_date": "born|birth|birthday|dob|geboren|geburtsdatum|nacido|nacimiento|naissance",
    "secret": "key|apikey|api_key|secret|token|password|passwd|pwd|bearer|credential|credentials",
}
BASE_KINDS = ("email", "ip", "card", "phone")
ADDED_KINDS = ("iban", "national_id", "birth_date", "secret")
SPAN = "struct<start:int,end:int,kind:string,text:string>"


def _digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def luhn(digits: Column) -> Column:
    """True if the check digit of a digit string holds."""
    back = F.split(F.reverse(digits), "")
    doubled = F.transform(back, lambda d, i: F.when(i % 2 == 0, d.cast("int")).otherwise(F.element_at(F.array(*[F.lit(x) for x in (0, 2, 4, 6, 8, 1, 3, 5, 7, 9)]), d.cast("int") + 1)))
    return F.aggregate(doubled, F.lit(0), lambda a, x: a + F.coalesce(x, F.lit(0))) % 10 == 0


def mod97(code: Column) -> Column:
    """True if an account number, its first four characters moved to the end and letters counted from 10, leaves 1."""
    bare = F.regexp_replace(code, " ", "")
    moved = F.split(F.concat(F.substring(bare, 5, 64), F.substring(bare, 1, 4)), "")
    value = lambda c: F.when(c.between("0", "9"), F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    return F.aggregate(moved, F.lit(0), lambda a, c: F.when(c == "", a).when(value(c) < 10, (a * 10 + value(c)) % 97).otherwise((a * 100 + value(c)) % 97)) == 1


def _valid(kind: str, match: Column) -> Column:
    if kind == "email":
        return F.lit(True)
    if kind == "ip":
        part = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]?[0-9])"
        return match.rlike(f"^{part}(?:\\.{part}){{3}}$")
    if kind == "card":
        d = _digits(match)
        return F.when(F.length(d).between(14, 19), luhn(d)).otherwise(False)
    if kind == "phone":
        return F.length(_digits(match)).between(10, 15)
    if kind == "iban":
        return F.when(F.length(F.regexp_replace(match, " ", "")).between(15, 34), mod97(match)).otherwise(False)
    if kind in ("birth_date", "secret"):
        return F.lit(True)
    return ~match.rlike("^(?:000|666|9)") & ~match.rlike("-00-|-0000$")


def _spans(kind: str, text: Column) -> Column:
    """Valid spans of a kind, in order."""
    pattern = PATTERNS[kind]
    empty = F.array().cast(f"array<{SPAN}>")
    scan = F.filter(matches(text, pattern), lambda x: _valid(kind, x["text"]))
    spans = F.transform(scan, lambda x: F.struct(x["start"].alias("start"), x["end"].alias("end"), F.lit(kind).alias("kind"), x["text"].alias("text")))
    hint = F.contains(text, F.lit(HINTS[kind])) if kind in HINTS else text.rlike("[0-9]{2}|[0-9][ -][0-9]")
    return F.when(hint & text.rlike(pattern), spans).otherwise(empty)


def find(docs: DataFrame) -> DataFrame:
    """doc_id and ``spans``: array of start, end, kind, text, score, in order of start, then kind as listed."""
    text = F.coalesce(F.col("text"), F.lit(""))
    kinds = (*BASE_KINDS, *ADDED_KINDS)
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text")).select("doc_id", "text", F.concat(*[_spans(k, F.col("text")) for k in kinds]).alias("raw"))

    def scored(s, wide):
        size = F.least(s["start"], F.lit(WINDOW))
        before = F.lower(F.decode(F.substring(wide, 4 * (s["start"] - size) + 1, 4 * size), "UTF-32"))
        near = reduce(lambda a, k: a.when(s["kind"] == k, before.rlike(rf"(?<![a-z])(?:{CONTEXT[k]})(?![a-z])")), kinds, F.when(F.lit(False), F.lit(False)))
        base = reduce(lambda a, k: a.when(s["kind"] == k, BASE_SCORE[k]), kinds, F.when(F.lit(False), F.lit(0.0)))
        checked = F.when(s["kind"].isin("card", "iban"), CHECKED_BONUS).otherwise(0.0)
        score = F.least(F.lit(1.0), base + checked + F.when(near, CONTEXT_BONUS).otherwise(0.0))
        order = reduce(lambda a, k: a.when(s["kind"] == k[1], k[0]), enumerate(kinds), F.when(F.lit(False), F.lit(0)))
        return F.struct(s["start"].alias("start"), order.alias("order"), s["end"].alias("end"), s["kind"].alias("kind"), s["text"].alias("text"), score.alias("score"))

    def kept(v):  # four bytes a character, bound once, so that context is a copy from a known place
        return F.filter(F.array_sort(F.transform(v["raw"], lambda s: scored(s, v["wide"]))), lambda s: s["kind"].isin(*BASE_KINDS) | (s["score"] >= LEAST))

    wide = F.when(F.size("raw") > 0, F.encode("text", "UTF-32")).otherwise(F.encode(F.lit(""), "UTF-32"))
    return found.select("doc_id", F.transform(F.array(F.struct("raw", wide.alias("wide"))), kept)[0].alias("spans"))


def _written(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")


def digest(docs: DataFrame) -> DataFrame:
    """Counts of the base kinds, the hash of their positions, all spans as text and their scores in the same order."""
    spans = F.col("spans")
    base = F.filter(spans, lambda s: s["kind"].isin(*BASE_KINDS))
    of = lambda kind: F.size(F.filter(spans, lambda s: s["kind"] == kind))
    counts = [of(k).cast("long").alias(f"n_{k}") for k in BASE_KINDS]
    return find(docs).select("doc_id", *counts, F.sha2(_written(base), 256).alias("base_sha256"), _written(spans).alias("spans"), F.array_join(F.transform(spans, lambda s: F.format_string("%.2f", s["score"])), ",").alias("scores"))
