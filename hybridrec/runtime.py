"""Session-level services every module may use: shared scratch space and lineage cuts."""

from __future__ import annotations

import os
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

_FALLBACK: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share.

    The cluster names it in ``spark.checkpoint.dir``. Only where nothing is set and everything runs in one
    process (tests) a temporary folder of that machine is used; on a cluster that would lose files, so it is an error.
    """
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if named:
        return named
    if not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    app = spark.sparkContext.applicationId
    if app not in _FALLBACK:
        _FALLBACK[app] = tempfile.mkdtemp(prefix="hybridrec-")
        spark.sparkContext.setCheckpointDir(_FALLBACK[app])
    return _FALLBACK[app]


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it back.

    Cuts the lineage, survives the loss of executors, gives later joins true sizes and keeps
    column pruning, which an RDD checkpoint would not. What the write has shuffled goes as soon as it is written.
    """
    spark = df.sparkSession
    path = os.path.join(shared_dir(spark), f"stage-{name}-{uuid.uuid4().hex}")
    with _without_shuffle_files(spark):
        df.write.parquet(path)
    for scope in _SCOPES:
        scope.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.stage = path
    return out


def discard(*written: DataFrame | None) -> None:
    """Deletes what ``materialize`` has written for these frames; nothing may read them any more."""
    for df in written:
        if path := getattr(df, "stage", None):
            _delete(df.sparkSession, [path])
            for scope in _SCOPES:
                if path in scope:
                    scope.remove(path)


def _delete(spark: SparkSession, paths: list[str]) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for name in paths:
        path = jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(conf).delete(path, True)


@contextmanager
def _without_shuffle_files(spark: SparkSession):
    """Within, Spark deletes the shuffle files of an execution at its end, not when the driver happens to collect its garbage."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(key)
        else:
            spark.conf.set(key, before)


_SCOPES: list[list[str]] = []


@contextmanager
def scratch(spark: SparkSession):
    """Deletes on leaving all that was materialized inside, but for the paths moved out of the list it yields."""
    own: list[str] = []
    _SCOPES.append(own)
    try:
        yield own
    finally:
        _SCOPES.remove(own)
        _delete(spark, own)


def row_count(df: DataFrame) -> int:
    return df.count()


def broadcastable(df: DataFrame, max_bytes: int) -> bool:
    """True if Catalyst's own size estimate of ``df`` is within ``max_bytes``."""
    plan = df._jdf.queryExecution().optimizedPlan()
    return int(str(plan.stats().sizeInBytes())) <= max_bytes
