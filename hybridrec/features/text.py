"""Text features: documents, tokens, vocabulary, sparse counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window, functions as F

from hybridrec.sources import table

LANGUAGES = {"en": "english", "de": "german", "fr": "french", "es": "spanish"}


def item_texts(spark: SparkSession, sf_dir: str, content_map: str = "modulo") -> DataFrame:
    """item_id, title, description, reviews. ``modulo`` covers every item; ``exact`` leaves items without a document of their own id."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.col("text").alias("description"))
    talk = table(spark, sf_dir, "conversations").where(F.col("role") == "user")
    reviews = talk.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "text"))), lambda x: x["text"]), " ").alias("reviews"))
    items = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("item_id"), F.col("p_name").alias("title"))
    if content_map == "exact":
        return items.join(docs, items["item_id"] == docs["doc_id"], "left").select("item_id", "title", "description", F.lit(None).cast("string").alias("reviews"))
    sizes = table(spark, sf_dir, "documents").agg(F.count("*").alias("nd")).crossJoin(table(spark, sf_dir, "conversations").agg(F.count_distinct("conv_id").alias("nc")))
    keyed = items.crossJoin(F.broadcast(sizes)).select("item_id", "title", (F.col("item_id") % F.col("nd")).alias("doc_id"), (F.col("item_id") % F.col("nc")).alias("conv_id"))
    return keyed.join(docs, "doc_id", "left").join(reviews, "conv_id", "left").select("item_id", "title", "description", "reviews")


def assemble(texts: DataFrame, parts: tuple[str, ...] = ("title", "description", "reviews")) -> DataFrame:
    """item_id, text: the parts that exist, joined by spaces."""
    return texts.select("item_id", F.concat_ws(" ", *parts).alias("text"))


def tokenize(text: Column) -> Column:
    """Lower-case letter runs."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"\p{L}+"), F.lit(0))


def stop_words(languages: tuple[str, ...] = tuple(LANGUAGES)) -> list[str]:
    from pyspark.ml.feature import StopWordsRemover

    return sorted({w for lang in languages for w in StopWordsRemover.loadDefaultStopWords(LANGUAGES[lang])})


def drop_stop_words(tokens: Column, words: list[str]) -> Column:
    return F.filter(tokens, lambda t: ~t.isin(words))


#: Endings a light stemmer strips, longest first. Fixed values.
ENDINGS = {"en": ("ingly", "edly", "ing", "ies", "ed", "es", "ly", "s"), "de": ("ungen", "ung", "en", "er", "es", "em", "e", "n", "s"), "fr": ("ements", "ement", "euses", "euse", "eux", "es", "er", "s", "e"), "es": ("amente", "mente", "ciones", "ción", "es", "as", "os", "a", "o")}


def stem(token: Column, lang: Column) -> Column:
    """A light suffix stemmer: the longest listed ending goes if three letters remain. A column expression, no UDF."""
    out = F.when(F.lit(False), token)
    for code, endings in ENDINGS.items():
        out = out.when(lang == code, F.regexp_replace(token, f"(?<=.{{3}})({'|'.join(endings)})$", ""))
    return out.otherwise(token)


def stemmed_vocabulary(tokens: DataFrame, lang: Column) -> DataFrame:
    """term, stem for the distinct vocabulary, to be joined back: each word is stemmed once."""
    return tokens.select(F.explode("tokens").alias("term")).distinct().select("term", stem(F.col("term"), lang).alias("stem"))


def term_statistics(tokens: DataFrame) -> DataFrame:
    """term, cf, df over (item_id, tokens)."""
    flat = tokens.select("item_id", F.explode("tokens").alias("term")).groupBy("term", "item_id").agg(F.count("*").alias("c"))
    return flat.groupBy("term").agg(F.sum("c").alias("cf"), F.count("*").alias("df"))


def tfidf_vocabulary(tokens: DataFrame, size: int = 20_000) -> DataFrame:
    """term, term_id, score of the ``size`` terms with the largest corpus frequency x log inverse document frequency, ties by term."""
    n = tokens.agg(F.count("*").alias("n"))
    scored = term_statistics(tokens).crossJoin(F.broadcast(n)).select("term", (F.col("cf") * F.log(F.col("n") / F.col("df"))).alias("score"))
    top = scored.orderBy(F.desc(F.round("score", 9)), "term").limit(size)
    return top.withColumn("term_id", F.row_number().over(Window.orderBy(F.desc(F.round("score", 9)), "term")) - 1).select("term", "term_id", "score")  # ``size`` rows at most


def word_counts(tokens: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """item_id, term_id, c in long form. The vocabulary is bounded by its size and broadcast."""
    flat = tokens.select("item_id", F.explode("tokens").alias("term"))
    return flat.join(F.broadcast(vocabulary.select("term", "term_id")), "term").groupBy("item_id", "term_id").agg(F.count("*").alias("c"))


def sparse(counts: DataFrame, size: int, items: DataFrame | None = None, value: str = "c") -> DataFrame:
    """item_id, f: struct of size, sorted indices and values. With ``items``, those without an entry get an empty vector."""
    per = counts.groupBy("item_id").agg(F.sort_array(F.collect_list(F.struct("term_id", value))).alias("e"))
    if items is not None:
        per = items.select("item_id").distinct().join(per, "item_id", "left").withColumn("e", F.coalesce("e", F.array().cast(per.schema["e"].dataType)))
    return per.select("item_id", F.struct(F.lit(size).alias("size"), F.col("e.term_id").alias("idx"), F.transform(f"e.{value}", lambda x: x.cast("double")).alias("val")).alias("f"))


def word_vectors(tokens: DataFrame, vocabulary: DataFrame, size: int) -> DataFrame:
    return sparse(word_counts(tokens, vocabulary), size, tokens)


def tokens_of(texts: DataFrame, parts: tuple[str, ...] = ("title", "description", "reviews"), stop: list[str] | None = None) -> DataFrame:
    t = tokenize(F.col("text"))
    return assemble(texts, parts).select("item_id", (drop_stop_words(t, stop) if stop else t).alias("tokens"))
