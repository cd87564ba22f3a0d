"""A corpus from raw documents to packed sequences, stage by stage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hybridrec.llm import line_dedup, mixing, near_dedup, packing, quality
from hybridrec.runtime import materialize, scratch
from hybridrec.sources import table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents inside their language's band of tokeniser fertility."""
    return quality.keep(docs)


def unique_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that stand earlier in the corpus, exactly or within two edits."""
    return line_dedup.keep(docs)


def unique_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates."""
    return near_dedup.keep_one(docs)


#: All the good text there is, no document twice: the other domains are thinned to their shares of that, as far as they have so much.
TARGETS = mixing.Mix(shares={"good": 0.9, "plain": 0.05, "toxic": 0.05}, size=None, most=1.0, priors="labels")


def target_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents drawn at the rates that bring the domains to their targets."""
    return mixing.mix(docs, table(spark, sf_dir, "labels"), TARGETS)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 4096 tokens."""
    return packing.pack(docs)


STAGES = [("quality", quality_rules), ("lines", unique_lines), ("near_duplicates", unique_documents), ("mixing", target_mix), ("packing", packed)]

#: No SQL reaches the tokenisers, signatures and fits of these stages; each is tested against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each written and read again; what a stage wrote on its way, and the stage before, is deleted as soon as it is done.

    Null texts and texts without a word fail the first stage; rows that share a doc_id are judged each by its own text; extra columns travel along up to
    the last stage; an empty table gives an empty result.
    """
    docs, last = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        with scratch(spark) as used:
            docs = materialize(stage(spark, docs, sf_dir), name)
            done = used.pop()
            if last:
                used.append(last)
        last = done
    return docs
