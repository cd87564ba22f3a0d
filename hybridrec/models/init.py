"""Starting vectors that depend on the id alone."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from hybridrec.functions import M, portable_hash


def hash_vectors(ids: DataFrame, column: str, k: int, seed: int, scale: float = 0.1) -> DataFrame:
    """id, v: k values in (-scale, scale) from the portable hash, equal on any partitioning and engine."""
    own = ids.select(F.col(column).cast("long").alias("id")).distinct()
    return own.select("id", F.array(*[(portable_hash(F.lit(i), F.col("id"), seed) / float(M) * 2 - 1) * scale for i in range(k)]).alias("v"))
