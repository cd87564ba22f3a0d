"""Writing: partitioned or bucketed tables, and streams."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql.streaming import StreamingQuery


def write_table(df: DataFrame, path: str, partition_by: tuple[str, ...] = (), mode: str = "error", fmt: str = "parquet") -> None:
    w = df.write.format(fmt).mode(mode)
    (w.partitionBy(*partition_by) if partition_by else w).save(path)


def write_bucketed(df: DataFrame, name: str, buckets: int, column: str, mode: str = "overwrite") -> None:
    """A catalogue table bucketed and sorted by an id: later joins on it need no exchange."""
    df.write.mode(mode).bucketBy(buckets, column).sortBy(column).saveAsTable(name)


def write_stream(df: DataFrame, sink: str, checkpoint: str, mode: str = "append", name: str | None = None, path: str | None = None, each: Callable | None = None, trigger: dict | None = None) -> StreamingQuery:
    """Memory, file or foreachBatch sink; a checkpoint location is mandatory."""
    w = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True}))
    if sink == "foreach":
        return w.foreachBatch(each).start()
    w = w.format(sink)
    if name:
        w = w.queryName(name)
    return w.start(path) if path else w.start()
