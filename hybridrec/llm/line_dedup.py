"""Line deduplication with a segment-partition edit join, in column expressions alone.

A line goes if an equal line of at least ``exact_chars`` characters stands earlier in the corpus (by doc_id, then position), or if an
earlier line within ``edits`` edits does (both of at least ``near_chars``). Distinct lines are first reduced to
their first occurrence, so a line that occurs a million times is one row. Each distinct line is cut into edits + 1 even segments: two lines
within the threshold share one of them. A line looks up, for its own length and each shorter one, the substrings that
could be such a segment without exceeding the edits on either side. Candidates are then
verified: equal 16-character blocks are stripped from both ends and a band of 2 edits + 1 diagonals runs through
the rest as bit vectors in one 64-bit word.

A segment that more than ``crowd`` lines of one length share makes no pairs: its lines and those that look it up go into blocks of
``block`` lines, each pair of blocks is one row, and inside it a line asks only whether any earlier one is near, stopping at the first. So a form
filled in a million ways moves blocks and not pairs; the comparisons inside a crowded segment still grow with the square of its lines.

Defined results: null text stays null and has no lines. Rows with a null doc_id are kept as they are and remove nothing. A row is its doc_id and
its text: equal rows are one and keep the same lines; rows that share a doc_id but not the text are ordered among themselves by a hash of
the text and lose lines each on its own. Empty and short lines always stay. A document that loses all its words is
dropped by :func:`keep` if it had any. Extra columns are ignored by the join and kept by :func:`keep`; an empty table gives
an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F

from hybridrec.runtime import materialize


@dataclass(frozen=True)
class Lines:
    #: Edits (insertions, deletions, substitutions) between two lines that count as one.
    edits: int = 2
    exact_chars: int = 20
    near_chars: int = 40
    #: Lines of one length that may share a segment before it counts as crowded, and lines of a block there.
    crowd: int = 8
    block: int = 64


def _keys(line: Column, edits: int, places: list[list[tuple[int, int]]]) -> Column:
    """Keys of a line, for each number of characters less, at (segment, shift).

    A line of ``other`` characters has edits + 1 even segments, the last ones longer by one. The lambda over constant lists is small, since one
    huge generated method would never be compiled; the line is made four bytes a character once, so that a piece is a copy from a known
    place and no walk over variable-length characters. Places need no test of bounds in lines of 2 (edits + 1) characters or more.
    """
    n = edits + 1
    lists = F.array(*[F.struct(F.lit(less).alias("less"), F.array(*[F.struct(F.lit(i).alias("i"), F.lit(s + 1).alias("shift")) for i, s in own]).alias("own")) for less, own in enumerate(places)])

    def of(v):
        def those(p):
            other = v["n"] - p["less"]
            return F.transform(F.array(F.struct(other.alias("other"), F.floor(other / n).cast("int").alias("base"), (n - other % n).alias("short"))), lambda o: F.transform(p["own"], lambda w: one(o, w)))[0]

        def one(o, w):
            at = o["base"] * w["i"] + F.greatest(F.lit(0), w["i"] - o["short"]) + w["shift"]
            size = o["base"] + F.when(w["i"] >= o["short"], 1).otherwise(0)
            return F.xxhash64(o["other"], w["i"], F.substring(v["w"], 4 * at - 3, 4 * size))

        return F.flatten(F.transform(lists, those))

    wide = F.encode(line, "UTF-32")
    return F.transform(F.array(F.struct(wide.alias("w"), F.length(line).alias("n"))), of)[0]


def index_keys(line: Column, edits: int) -> Column:
    return _keys(line, edits, [[(i, 0) for i in range(edits + 1)]])


def probe_keys(line: Column, edits: int) -> Column:
    """Keys of the substrings of a line that may equal a segment of a line of its own length or up to ``edits`` less.

    Substring start and segment start may differ by the edits possible before (i for segment i from 0) and those left after it.
    """
    window = lambda less, i: range(max(-i, less - (edits - i)), min(i, less + (edits - i)) + 1)
    return _keys(line, edits, [[(i, s) for i in range(edits + 1) for s in window(less, i)] for less in range(edits + 1)])


def _common(x: Column, y: Column, block: int, from_end: bool) -> Column:
    """Characters in equal whole blocks at the beginnings or ends of two strings of four bytes a character."""
    wide = 4 * block

    def of(v):
        n = F.floor(F.least(F.octet_length(v["x"]), F.octet_length(v["y"])) / wide).cast("int")
        piece = lambda s, i: F.substring(s, F.octet_length(s) - (i + 1) * wide + 1 if from_end else i * wide + 1, F.lit(wide))
        differs = F.array_position(F.transform(F.sequence(F.lit(0), n - 1), lambda i: piece(v["x"], i) != piece(v["y"], i)), True)
        return F.when(n < 1, 0).otherwise(F.when(differs == 0, n).otherwise(differs - 1) * block).cast("int")

    return F.transform(F.array(F.struct(x.alias("x"), y.alias("y"))), of)[0]


def within(pairs: DataFrame, edits: int, block: int = 16) -> DataFrame:
    """The pairs (string columns ``x``, ``y``) at edit distance ``edits`` at most, with all their columns.

    Equal blocks go from both ends first. The walk then keeps, for each character of ``y``, the vertical differences +1 and -1 of the 2 edits + 1
    cells around the diagonal as bits of two words; the cell on the band's lower edge is counted until it meets the last row.
    What is left after the blocks is written once, so that no optimizer rule evaluates it again for each use.
    """
    top, full, k = 2 * edits, (1 << (2 * edits + 1)) - 1, edits
    cut = pairs.where(F.abs(F.length("x") - F.length("y")) <= edits).withColumns({"_x": F.encode("x", "UTF-32"), "_y": F.encode("y", "UTF-32")})
    cut = cut.withColumn("_p", _common(F.col("_x"), F.col("_y"), block, False)).withColumns({c: F.expr(f"substring({c}, 4 * _p + 1)") for c in ("_x", "_y")})
    cut = cut.withColumn("_s", _common(F.col("_x"), F.col("_y"), block, True)).withColumns({o: F.decode(F.expr(f"substring({c}, 1, octet_length({c}) - 4 * _s)"), "UTF-32") for o, c in (("_a", "_x"), ("_b", "_y"))})
    cut = materialize(cut.drop("_x", "_y", "_p", "_s"), "stripped")
    # distant strings seldom agree even on their beginnings: a prefix may differ by twice the edits at most
    cut = cut.where(F.levenshtein(F.substring("_a", 1, 48), F.substring("_b", 1, 48), 2 * edits) >= 0)
    a, b = F.split("_a", ""), F.split("_b", "")
    rows = F.concat(F.array_repeat(F.lit(""), k), a, F.array_repeat(F.lit(""), 2 * k + 1))  # so that row j + d is at j + d + k
    size = F.length("_b")
    window = [F.slice(rows, d + 1, size).alias(f"r{d}") for d in range(top + 1)]  # for column j the row j + d - k
    # bit that holds the last row in each column; above the band's edge while the walk is still on it
    last = F.sequence(F.length("_a") - 1 + k, F.length("_a") - 1 + k - (size - 1), F.lit(-1)).alias("last")

    def advance(t, c):
        eq, vp, vn = t["eq"], t["vp"], t["vn"]
        inv = lambda z: F.lit(full) - z.bitwiseAND(F.lit(full))
        zero = (eq.bitwiseAND(vp) + vp).bitwiseXOR(vp).bitwiseOR(eq).bitwiseOR(vn).bitwiseAND(F.lit(full))
        hp, hn = vn.bitwiseOR(inv(zero.bitwiseOR(vp))), zero.bitwiseAND(vp)
        bit = lambda z, at: F.call_function("shiftright", z, at).bitwiseAND(F.lit(1))
        at = F.greatest(c["last"], F.lit(0))
        change = F.when(c["last"] >= top, 1 - bit(zero, F.lit(top))).otherwise(bit(hp, at) - bit(hn, at))
        down = F.shiftright(zero, 1)
        return F.struct(hn.bitwiseOR(inv(down.bitwiseOR(hp))).alias("vp"), down.bitwiseAND(hp).alias("vn"), (t["d"] + change).alias("d"))

    columns = F.arrays_zip(b.alias("c"), *window, last)
    masks = F.transform(columns, lambda c: F.struct(_mask(c, top).alias("eq"), c["last"].alias("last")))
    start = F.struct(F.lit(full - ((1 << k) - 1)).alias("vp"), F.lit(0).alias("vn"), F.lit(k).alias("d"))
    distance = F.aggregate(masks, start, lambda s, c: advance(F.struct(c["eq"].alias("eq"), s["vp"].alias("vp"), s["vn"].alias("vn"), s["d"].alias("d")), c))["d"]
    short = F.least(F.length("_a"), F.length("_b")) <= k + 1
    ok = F.when(short, F.levenshtein("_a", "_b") <= edits).otherwise(distance <= edits)
    return cut.where(ok).drop("_a", "_b")


def _mask(c: Column, top: int) -> Column:
    eq = F.lit(0)
    for d in range(top + 1):
        eq = eq.bitwiseOR(F.when(c[f"r{d}"] == c["c"], 1 << d).otherwise(0))
    return eq


PLACE = "decimal(38,0)"
_HALF = 1 << 31


def _row(text: Column) -> Column:
    """Tells rows of one doc_id apart: 31 bits of a hash of the text."""
    return F.pmod(F.xxhash64(text, F.lit(3)), F.lit(_HALF))


def occurrences(docs: DataFrame, rules: Lines) -> DataFrame:
    """doc_id, row, pos, line, two hashes and the place in the corpus of every line long enough to count."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").where("doc_id is not null and text is not null").withColumn("row", _row(F.col("text")))
    lines = own.select("doc_id", "row", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line")).where(F.length("line") >= rules.exact_chars)
    half = F.lit(_HALF).cast(PLACE)
    place = ((F.col("doc_id").cast(PLACE) * half + F.col("row").cast(PLACE)).cast(PLACE) * half + F.col("pos").cast(PLACE)).cast(PLACE)
    return lines.select("doc_id", "row", "pos", "line", F.xxhash64("line").alias("h1"), F.xxhash64(F.lit(1), "line").alias("h2"), place.alias("place"))


def _small(df: DataFrame, most: int = 1_000_000) -> DataFrame:
    """Broadcast if its rows, counted, are so few (keys of 8 bytes); else as it is, for a join by shuffle."""
    return F.broadcast(df) if df.count() <= most else df


def decisions(docs: DataFrame, rules: Lines = Lines()) -> DataFrame:
    """doc_id, row, pos, h1, near of every line occurrence that goes, once; ``near``: only an almost equal line stands earlier."""
    if rules.near_chars < 3 * (rules.edits + 1):
        raise ValueError("near_chars must be three times the segments at least")
    all_ = occurrences(docs, rules)
    lines = materialize(all_.select("h1", "h2", "place").groupBy("h1", "h2").agg(F.min("place").alias("first"), F.max("place").alias("last")), "lines")
    long_ = all_.where(F.length("line") >= rules.near_chars)
    keyed = long_.select("place", "h1", "h2", index_keys(F.col("line"), rules.edits).alias("own"), probe_keys(F.col("line"), rules.edits).alias("looked"))
    keyed = materialize(keyed.join(lines.select(F.col("first").alias("place"), "h1", "h2"), ["place", "h1", "h2"], "left_semi").select("h1", "own", "looked"), "line-keys")
    indexed, probing = keyed.select(F.col("h1").alias("a"), F.explode("own").alias("key")), keyed.select(F.col("h1").alias("b"), F.explode("looked").alias("key"))
    crowded = materialize(indexed.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > rules.crowd), "crowded")
    hot = _small(crowded.select("key"))

    # a look-up meets ``crowd`` lines at most
    sparse = indexed.join(hot, "key", "left_anti").join(probing, "key").where("a != b")
    candidates = materialize(sparse.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "line-pairs")
    meeting = materialize(indexed.join(hot, "key", "left_semi").select("key", F.col("a").alias("h1"), F.lit(True).alias("mine")).unionByName(probing.join(hot, "key", "left_semi").select("key", F.col("b").alias("h1"), F.lit(False).alias("mine"))).distinct(), "crowded-lines")

    wanted = materialize(candidates.select(F.explode(F.array("a", "b")).alias("h1")).unionByName(meeting.select("h1")).distinct(), "wanted-lines")
    few = _small(wanted)
    texts = long_.select("line", "h1", "h2", "place").join(few, "h1", "left_semi")
    texts = materialize(texts.join(lines.join(few, "h1", "left_semi").select(F.col("first").alias("place"), "h1", "h2"), ["place", "h1", "h2"], "left_semi").distinct(), "line-texts")
    side = lambda h, t, p, h2: texts.select(F.col("h1").alias(h), F.col("line").alias(t), F.col("place").alias(p), F.col("h2").alias(h2))
    pairs = candidates.join(side("a", "x", "px", "x2"), "a").join(side("b", "y", "py", "y2"), "b").where(F.abs(F.length("x") - F.length("y")) <= rules.edits)
    close = within(pairs, rules.edits)
    later = close.select(F.when(F.col("px") > F.col("py"), F.struct(F.col("a").alias("h1"), F.col("x2").alias("h2"))).otherwise(F.struct(F.col("b").alias("h1"), F.col("y2").alias("h2"))).alias("l")).select("l.*")
    later = materialize(later.unionByName(_crowded_later(meeting, texts, rules)).distinct().withColumn("near", F.lit(True)), "near-lines")

    repeated = lines.where("first != last").select("h1", "h2").join(later, ["h1", "h2"], "full").select("h1", "h2", F.coalesce("near", F.lit(False)).alias("near"))
    marked = repeated.join(lines.select("h1", "h2", "first"), ["h1", "h2"])
    hit = all_.select("doc_id", "row", "pos", "h1", "h2", "place").join(marked, ["h1", "h2"])
    return hit.where(F.col("near") | (F.col("place") != F.col("first"))).select("doc_id", "row", "pos", "h1", (F.col("place") == F.col("first")).alias("near")).distinct()


def _crowded_later(meeting: DataFrame, texts: DataFrame, rules: Lines) -> DataFrame:
    """h1, h2 of the lines of crowded segments that have an earlier line within the edits.

    Lines of a segment are dealt to blocks by hash; a row is a block of owners and a block of look-ups.
    """
    sizes = meeting.groupBy("key", "mine").agg(F.ceil(F.count("*") / rules.block).cast("int").alias("blocks"))
    dealt = meeting.join(sizes, ["key", "mine"]).withColumn("at", F.pmod(F.xxhash64("h1", F.lit(2)), F.col("blocks")).cast("int")).join(texts, "h1")
    line = F.struct("place", "h1", "h2", "line")
    blocks = materialize(dealt.groupBy("key", "mine", "at").agg(F.collect_list(line).alias("block")), "line-blocks")
    both = blocks.where("mine").select("key", F.col("block").alias("x")).join(blocks.where("not mine").select("key", F.col("block").alias("y")), "key")
    # a block pair is a task's unit of work and may be long: rows are dealt evenly before the work begins
    both = both.repartition(F.xxhash64("key", F.col("x")[0]["h1"], F.col("y")[0]["h1"]))
    early = lambda v, w: (w["place"] < v["place"]) & (F.levenshtein(v["line"], w["line"], rules.edits) >= 0)
    late = lambda xs, ys: F.filter(xs, lambda v: F.exists(ys, lambda w: early(v, w)))
    found = F.concat(*[F.transform(late(F.col(p), F.col(q)), lambda v: F.struct(v["h1"].alias("h1"), v["h2"].alias("h2"))) for p, q in (("x", "y"), ("y", "x"))])
    return both.select(F.explode(found).alias("l")).select("l.*")


def digest(docs: DataFrame, rules: Lines = Lines()) -> DataFrame:
    """Per row: lines, lines that go as equal and as almost equal ones, lines kept, hash of the positions that go."""
    gone = materialize(decisions(docs, rules), "gone-lines")
    per = gone.groupBy("doc_id", "row").agg(F.count_if(~F.col("near")).alias("n_equal"), F.count_if("near").alias("n_near"), F.md5(F.array_join(F.sort_array(F.collect_set("pos")).cast("array<string>"), ",").cast("binary")).alias("gone_md5"))
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _row(F.col("text")).alias("row"), F.when(F.col("text").isNull(), 0).otherwise(F.size(F.split("text", "\n", -1))).cast("long").alias("n_lines"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    out = own.join(per, ["doc_id", "row"], "left").select("doc_id", "n_lines", zero("n_equal"), zero("n_near"), "gone_md5")
    return out.select("doc_id", "n_lines", "n_equal", "n_near", (F.col("n_lines") - F.col("n_equal") - F.col("n_near")).alias("n_kept"), "gone_md5")


def keep(docs: DataFrame, rules: Lines = Lines()) -> DataFrame:
    """The documents without the lines that go; documents left without a word are dropped if they had one."""
    code = lambda pos, h: pos.cast("long") * F.lit(1 << 32) + F.pmod(h, F.lit(1 << 32))  # noqa: E731  a line by its position and 32 bits of its hash
    gone = decisions(docs, rules).groupBy("doc_id", "row").agg(F.collect_set(code(F.col("pos"), F.col("h1"))).alias("gone"))
    own = docs.select(F.struct(*docs.columns).alias("d"))  # one column, so that no name can clash
    joined = own.join(gone, (F.col("d.doc_id").cast("long") == F.col("doc_id")) & (_row(F.col("d.text")) == F.col("row")), "left").select("d", "gone")
    lines = F.split("d.text", "\n", -1)

    def rest(v):
        stay = F.array_except(F.transform(v["lines"], lambda x, i: code(i, F.xxhash64(x))), v["gone"])  # by a hash table, in order
        return F.array_join(F.transform(stay, lambda c: F.get(v["lines"], F.shiftright(c, 32).cast("int"))), "\n")

    bound = F.transform(F.array(F.struct(lines.alias("lines"), F.col("gone").alias("gone"))), rest)[0]
    joined = joined.withColumn("text", F.when(F.col("gone").isNull(), F.col("d.text")).otherwise(bound))
    kept = joined.where(F.col("gone").isNull() | F.col("text").rlike("[^\\x20\\x09-\\x0D]"))
    chars = F.when(F.col("gone").isNull(), F.col("d")["n_chars"] if "n_chars" in docs.columns else None).otherwise(F.length("text").cast("long"))
    return kept.select(*[F.col("text") if c == "text" else chars.alias(c) if c == "n_chars" else F.col("d")[c].alias(c) for c in docs.columns])
