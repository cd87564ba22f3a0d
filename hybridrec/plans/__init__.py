"""Looking at physical plans: what a query scans, pushes down, exchanges and broadcasts."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame


def text(df: DataFrame) -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString("formatted"))


def summary(df: DataFrame) -> dict[str, int]:
    """How often each costly operator stands in the plan."""
    t = text(df).split("\n\n\n")[0]
    kinds = ("Exchange", "BroadcastExchange", "SortMergeJoin", "ShuffledHashJoin", "BroadcastHashJoin", "BroadcastNestedLoopJoin", "CartesianProduct", "Window", "WindowGroupLimit", "MapInPandas", "FlatMapGroupsInPandas")
    return {k: len(re.findall(rf"[ -]{k}(?: \(\d+\))?$", t, re.M)) + len(re.findall(rf"[ -]{k} ", t)) for k in kinds}


def pushed_filters(df: DataFrame) -> list[str]:
    return re.findall(r"PushedFilters: \[(.+?)\]\n", text(df))


def read_columns(df: DataFrame) -> list[str]:
    return [re.sub(r":[^,>]*", "", c) for c in re.findall(r"ReadSchema: struct<(.*?)>\n", text(df))]
