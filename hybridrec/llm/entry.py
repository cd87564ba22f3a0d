"""Queries of the text operators and, where SQL can express them, their oracles."""

from __future__ import annotations

from pyspark.sql import functions as F

from hybridrec.llm import langid, line_dedup, lm, mixing, near_dedup, packing, pii, quality, token_counts, vptree
from hybridrec.sources import table


def op4_language_id(spark, sf_dir):
    """Language of every document by partial matching of byte contexts."""
    return langid.identify(table(spark, sf_dir, "documents"))


def op10_quality_rules(spark, sf_dir):
    """Tokeniser fertility and base counts of every document."""
    return quality.digest(table(spark, sf_dir, "documents"))


def op1_nearest_neighbours(spark, sf_dir):
    """Ten nearest vectors of every hundredth one, by vantage-point trees, exactly."""
    vectors = table(spark, sf_dir, "embeddings")
    return vptree.search(vectors, vectors.where(vptree.every(vectors["vec_id"], 100)), k=10, relax=1.0)


def op2_pii(spark, sf_dir):
    """Personal data spans of every whole text."""
    return pii.digest(table(spark, sf_dir, "documents"))


def op3_token_counts(spark, sf_dir):
    """Tokens of every document before and after masking its e-mail addresses, by edits on its segment tree."""
    docs = table(spark, sf_dir, "documents")
    return token_counts.count(docs, token_counts.mask_edits(docs["text"], pii.PATTERNS["email"], "<email>"))


def op5_mixing(spark, sf_dir):
    """Rates that bring the domains' token totals to their targets."""
    return mixing.rates(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op6_packing(spark, sf_dir):
    """All documents packed into sequences of 4096 tokens."""
    return packing.pack(table(spark, sf_dir, "documents"))


def op7_lm_scores(spark, sf_dir):
    """Base and model log-probabilities of every document."""
    return lm.fit_and_score(table(spark, sf_dir, "documents"))


def op8_near_duplicates(spark, sf_dir):
    """Groups of documents that share 85 % of their three-word shingles."""
    return near_dedup.groups(table(spark, sf_dir, "documents"), near_dedup.Near(words=3, percent=85))


def op9_line_dedup(spark, sf_dir):
    """Lines of every document that repeat an earlier line exactly or within two edits."""
    return line_dedup.digest(table(spark, sf_dir, "documents"))


def pipeline(spark, sf_dir):
    """All stages of the corpus pipeline over the documents."""
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


# ---- what SQL can express of the operators' results, from the operators' own rows
def nearest_neighbours_rounded(spark, sf_dir):
    """The lists of operator 1 with scores to six digits."""
    return op1_nearest_neighbours(spark, sf_dir).select("query_id", F.col("rank").cast("bigint").alias("rank"), "vec_id", (F.round("score", 6) + F.lit(0.0)).alias("score"))


def personal_data_counts(spark, sf_dir):
    """Base counts of operator 2."""
    return op2_pii(spark, sf_dir).select("doc_id", *[f"n_{k}" for k in pii.BASE_KINDS])


def shingle_counts(spark, sf_dir):
    """Set sizes of operator 8."""
    return op8_near_duplicates(spark, sf_dir).select("doc_id", "n_shingles")


def equal_line_counts(spark, sf_dir):
    """Lines of operator 9, and those that go because an equal one stands earlier."""
    return op9_line_dedup(spark, sf_dir).select("doc_id", "n_lines", "n_equal")


def base_quality_counts(spark, sf_dir):
    """Base counts and base verdict of operator 10."""
    return op10_quality_rules(spark, sf_dir).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")


_WORD = "[^ \\t\\n\\x0B\\x0C\\r]+"
_WORDS = f"w AS MATERIALIZED (SELECT doc_id, regexp_extract_all(translate(COALESCE(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '{_WORD}') AS w FROM documents)"
_DIGITS = "regexp_replace(x, '[^0-9]', '', 'g')"
_LUHN = f"list_sum(list_transform(string_split({_DIGITS}, ''), lambda c, i: CASE WHEN (length({_DIGITS}) - i) % 2 = 0 THEN CAST(c AS INTEGER) WHEN CAST(c AS INTEGER) > 4 THEN 2 * CAST(c AS INTEGER) - 9 ELSE 2 * CAST(c AS INTEGER) END)) % 10 = 0"

SQL = {
    "nearest_neighbours_rounded": "WITH e AS MATERIALIZED (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND list_bool_and(list_transform(embedding, lambda x: x IS NOT NULL AND isfinite(x))) AND list_bool_or(list_transform(embedding, lambda x: x <> 0))), "
    "s AS (SELECT q.vec_id AS query_id, c.vec_id, list_distance(q.v, c.v) AS score FROM e q JOIN e c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v) WHERE q.vec_id % 100 = 0) "
    "SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS rank, vec_id, ROUND(score, 6) + 0.0 AS score FROM s QUALIFY rank <= 10",
    "personal_data_counts": "WITH d AS (SELECT doc_id, COALESCE(text, '') AS t FROM documents) SELECT doc_id, len(regexp_extract_all(t, '[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\\.[A-Za-z0-9-]+)+')) AS n_email, "
    "len(list_filter(regexp_extract_all(t, '[0-9]+(\\.[0-9]+)(\\.[0-9]+)(\\.[0-9]+)'), lambda x: list_bool_and(list_transform(string_split(x, '.'), lambda p: length(ltrim(p, '0')) <= 3 AND CAST('0' || right(p, 3) AS INTEGER) <= 255)))) AS n_ip, "
    f"len(list_filter(regexp_extract_all(t, '[0-9]([ -]?[0-9])+'), lambda x: length({_DIGITS}) BETWEEN 14 AND 19 AND {_LUHN})) AS n_card, "
    f"len(list_filter(regexp_extract_all(t, '\\+[0-9][ ().0-9-]+[0-9]'), lambda x: length({_DIGITS}) BETWEEN 10 AND 15)) AS n_phone FROM d",
    "shingle_counts": f"WITH {_WORDS}, g AS (SELECT DISTINCT doc_id, w[i:i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 1, 2))) AS i FROM w WHERE len(w) > 0)) SELECT w.doc_id, COALESCE(n, 0) AS n_shingles FROM w LEFT JOIN (SELECT doc_id, COUNT(*) AS n FROM g GROUP BY 1) USING (doc_id)",
    "equal_line_counts": "WITH l AS (SELECT doc_id, pos, l[pos] AS line FROM (SELECT doc_id, l, unnest(range(1, len(l) + 1)) AS pos FROM (SELECT doc_id, string_split(text, chr(10)) AS l FROM documents WHERE text IS NOT NULL))), "
    "r AS (SELECT doc_id, row_number() OVER (PARTITION BY line ORDER BY doc_id, pos) AS r FROM l WHERE length(line) >= 20) "
    "SELECT d.doc_id, CAST(COALESCE(len(string_split(text, chr(10))), 0) AS BIGINT) AS n_lines, COALESCE(n, 0) AS n_equal FROM documents d LEFT JOIN (SELECT doc_id, COUNT(*) AS n FROM r WHERE r > 1 GROUP BY 1) USING (doc_id)",
    "base_quality_counts": f"WITH b AS MATERIALIZED (SELECT doc_id, COALESCE(text, '') AS t, regexp_extract_all(COALESCE(text, ''), '{_WORD}') AS w FROM documents), "
    "g AS (SELECT doc_id, i, w[i:i + 2] AS g FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM b WHERE len(w) > 2)), "
    "tw AS (SELECT doc_id, i FROM g QUALIFY COUNT(*) OVER (PARTITION BY doc_id, g) > 1), "
    "rp AS (SELECT doc_id, COUNT(DISTINCT i + k) AS n FROM tw, (VALUES (0), (1), (2)) t(k) GROUP BY 1), "
    f"ln AS (SELECT doc_id, COUNT(*) - COUNT(DISTINCT l) AS n FROM (SELECT doc_id, unnest(string_split(t, chr(10))) AS l FROM b) WHERE regexp_matches(l, '{_WORD}') GROUP BY 1), "
    "c AS (SELECT b.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(COALESCE(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars, CAST(length(regexp_replace(t, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, COALESCE(ln.n, 0) AS n_dup_lines, COALESCE(rp.n, 0) AS n_repeat_words FROM b LEFT JOIN ln USING (doc_id) LEFT JOIN rp USING (doc_id)) "
    "SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM c",
}


def queries():
    own = (op1_nearest_neighbours, op2_pii, op3_token_counts, op4_language_id, op5_mixing, op6_packing, op7_lm_scores, op8_near_duplicates, op9_line_dedup, op10_quality_rules, pipeline)
    return {f.__name__: f for f in (*own, nearest_neighbours_rounded, personal_data_counts, shingle_counts, equal_line_counts, base_quality_counts)}


def oracle_sql():
    """SQL of the parts of the results that it can express; the rest is tested against brute force."""
    return dict(SQL)
