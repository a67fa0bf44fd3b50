"""Tables between the steps of a job, in the folder that the cluster names in ``spark.checkpoint.dir``.

A written table cuts lineage and survives lost executors; it is read again by column and by filter.
"""

from __future__ import annotations

import gc
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_SCOPES: list[list[str]] = []


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors see.

    Only an application that runs in one process may do without the setting: it gets a folder of the warehouse.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = held.get() if held.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_gistloom_scratch"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/gistloom/{name}-{uuid.uuid4().hex}"


def _file_system(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def is_folder(spark: SparkSession, path: str) -> bool:
    files, where = _file_system(spark, path)
    return files.getFileStatus(where).isDirectory()


def remove_path(spark: SparkSession, path: str) -> None:
    files, where = _file_system(spark, path)
    files.delete(where, True)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write once to the shared folder and read back.

    The shuffle files of the write go as soon as it has ended; the table replaces them.
    """
    spark = df.sparkSession
    path = fresh_path(spark, name)
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)
    table = spark.read.schema(df.schema).parquet(path)
    table._gl_path = path
    if _SCOPES:
        _SCOPES[-1].append(path)
    return table


def discard(*tables: DataFrame) -> None:
    """Delete materialised tables that nothing will read again."""
    for t in tables:
        remove_path(t.sparkSession, t._gl_path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables that ``materialize`` writes inside go at the end; results must have been written by then."""
    _SCOPES.append([])
    try:
        yield
    finally:
        for path in _SCOPES.pop():
            remove_path(spark, path)


def release(spark: SparkSession) -> None:
    """Let Spark delete shuffle files that no live plan needs; else they stay until the driver collects garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
