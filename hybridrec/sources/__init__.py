"""Reading: the given tables, other batch formats, file and rate streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from hybridrec.schemas import TABLES


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables by name; Spark reads the path, so any file system works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The same with the declared schema, so that a changed file fails early instead of being inferred."""
    return spark.read.schema(TABLES[name]).parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, fmt: str, path: str, schema: str | None = None, **options) -> DataFrame:
    """CSV, JSON, ORC, text, binary files or Parquet with an explicit schema."""
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def rows(spark: SparkSession, data: list, schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)


def read_stream(spark: SparkSession, fmt: str, path: str | None = None, schema: str | None = None, **options) -> DataFrame:
    """A file stream with an explicit schema, or a rate stream."""
    reader = spark.readStream.format(fmt).options(**options)
    if schema:
        reader = reader.schema(schema)
    return reader.load(path) if path else reader.load()
