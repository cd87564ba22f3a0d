"""Metadata tokens and their binary vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from hybridrec.features.descriptors import SENT_BYTES
from hybridrec.features.text import sparse
from hybridrec.runtime import broadcastable
from hybridrec.sources import table


def meta_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    """item_id, token, distinct: brand, type, size band, suppliers with nation and region, language, source and quality of the document."""
    named = lambda key, col: F.concat(F.lit(f"{key}="), col.cast("string"))
    part = table(spark, sf_dir, "part")
    nd = table(spark, sf_dir, "documents").agg(F.count("*").alias("nd"))
    own = part.select(F.col("p_partkey").alias("item_id"), F.explode(F.array(named("brand", F.col("p_brand")), named("type", F.col("p_type")), named("size", F.floor(F.col("p_size") / 10)))).alias("token"))
    # an item's lines meet once; its suppliers, nations and regions are told apart where they are
    shipped = table(spark, sf_dir, "lineitem").select(F.col("l_partkey").alias("item_id"), F.col("l_suppkey").alias("s_suppkey")).repartition("item_id").distinct()
    place = table(spark, sf_dir, "supplier").join(F.broadcast(table(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    place = place.select("s_suppkey", "n_name", "r_name")
    held = shipped.join(F.broadcast(place) if broadcastable(table(spark, sf_dir, "supplier"), SENT_BYTES) else place, "s_suppkey")
    supply = held.select("item_id", F.explode(F.array(named("supp", F.col("s_suppkey")), named("snation", F.col("n_name")), named("sregion", F.col("r_name")))).alias("token"))
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source").join(table(spark, sf_dir, "labels").select("doc_id", "quality"), "doc_id", "left")
    about = part.select(F.col("p_partkey").alias("item_id")).crossJoin(F.broadcast(nd)).withColumn("doc_id", F.col("item_id") % F.col("nd")).join(docs, "doc_id")
    described = about.select("item_id", F.explode(F.array(named("lang", F.col("lang")), named("source", F.col("source")), named("quality", F.col("quality")))).alias("token")).where("token is not null")
    # tokens of different origin differ in their first letters, so each origin can be made distinct alone
    return own.distinct().unionByName(supply.distinct()).unionByName(described.distinct())


def meta_vocabulary(tokens: DataFrame, size: int = 20_000) -> DataFrame:
    """token, term_id, n: the ``size`` tokens on most items, ties by token."""
    top = tokens.groupBy("token").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "token").limit(size)
    return top.withColumn("term_id", F.row_number().over(Window.orderBy(F.desc("n"), "token")) - 1)


def meta_vectors(tokens: DataFrame, vocabulary: DataFrame, size: int) -> DataFrame:
    """item_id, f: sparse vector of ones."""
    hits = tokens.join(F.broadcast(vocabulary.select("token", "term_id")), "token").select("item_id", "term_id", F.lit(1.0).alias("c"))
    return sparse(hits, size, tokens)
