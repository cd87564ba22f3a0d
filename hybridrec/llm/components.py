"""Connected components of an edge table, by alternating large-star and small-star steps.

Edges point to smaller ids and shrink to stars; each step is one aggregation and one join, so no vertex's
neighbours ever meet in one task beyond what the skew-join split allows. Every round is written to the
shared folder, so a lost executor costs a round at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from hybridrec.runtime import materialize


def _sum(edges: DataFrame) -> tuple:
    r = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).collect()[0]
    return r["n"], r["s"]


def _least_neighbour(edges: DataFrame) -> DataFrame:
    return edges.groupBy("u").agg(F.min("v").alias("m"))


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """``id``, ``label`` for every vertex of ``links`` (columns a, b), label being the smallest id reachable.

    Null ends and loops are ignored; no links give no rows.
    """
    pairs = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u != v and v is not null").distinct()
    edges = materialize(pairs, "links")
    before = _sum(edges)
    for _ in range(rounds):
        if not before[0]:
            break
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = _least_neighbour(both).withColumn("m", F.least("u", "m"))
        large = both.where("v > u").join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = materialize(large, "large-star")
        small = large.join(_least_neighbour(large), "u")
        edges = materialize(small.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(small.select("u", F.col("m").alias("v"))).distinct(), "small-star")
        now = _sum(edges)
        if now == before:
            break
        before = now
    else:
        raise RuntimeError("components did not settle")
    roots = edges.select(F.col("v").alias("id"), F.col("v").alias("label"))
    return edges.select(F.col("u").alias("id"), F.col("v").alias("label")).unionByName(roots).groupBy("id").agg(F.min("label").alias("label"))
