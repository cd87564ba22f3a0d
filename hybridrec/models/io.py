"""Saving and loading of fits: parameters as JSON, tables as Parquet, one directory per version."""

from __future__ import annotations

import json
from dataclasses import asdict, is_dataclass

from pyspark.sql import DataFrame, SparkSession

from hybridrec.models import Model


def save(model: Model, path: str, version: int = 0) -> str:
    root = f"{path}/v{version:04d}"
    tables = {"user_factors": model.user_factors, "item_factors": model.item_factors, "content_latents": model.content_latents}
    for name, df in tables.items():
        if df is not None:
            df.write.mode("overwrite").parquet(f"{root}/{name}")
    p = model.extra.get("params")
    text = json.dumps({"params": asdict(p) if is_dataclass(p) else None, "history": model.history, "tables": [n for n, t in tables.items() if t is not None]})
    spark = model.user_factors.sparkSession
    spark.createDataFrame([(text,)], "value string").coalesce(1).write.mode("overwrite").text(f"{root}/meta")
    return root


def load(spark: SparkSession, root: str) -> Model:
    meta = json.loads("".join(r["value"] for r in spark.read.text(f"{root}/meta").collect()))
    read = lambda name: spark.read.parquet(f"{root}/{name}") if name in meta["tables"] else None
    users: DataFrame = read("user_factors")
    return Model(users, read("item_factors"), read("content_latents"), meta["history"], {"params": meta["params"]})
