"""The folder that driver and executors share, and tables written there."""

from __future__ import annotations

import gc
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def shared_base(spark: SparkSession) -> str:
    """The shared folder: ``spark.checkpoint.dir``.

    Where that is unset the session's checkpoint folder is used; a session that
    runs on this machine alone is given one beside its warehouse, any other
    must name one.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        sc = spark.sparkContext
        if sc.getCheckpointDir() is None:
            if not sc.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
            sc.setCheckpointDir(spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/shared")
        base = sc.getCheckpointDir()
    return base.rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path under the shared folder."""
    return f"{shared_base(spark)}/{name}-{uuid.uuid4().hex}"


def exists(spark: SparkSession, path: str) -> bool:
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).exists(hadoop)


def local_path(uri: str) -> str:
    """The plain path of a ``file:`` URI; other stores are for Spark's own readers."""
    if uri.startswith("file:"):
        return "/" + uri[5:].lstrip("/")
    if "://" in uri:
        raise ValueError(f"{uri} is not a mounted folder")
    return uri


#: Setting of the engine that frees the shuffle files of an execution as it ends.
CLEAN_UP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def write_then_free(spark: SparkSession, write: Callable[[], None], after: float = 1.0) -> None:
    """Runs ``write``, whose shuffle files are freed as it ends.

    Left alone, the engine frees the files of a shuffle when the driver's
    collector finds it unreachable, which on a driver with room to spare is
    long after the query that wrote them has ended.  Executions inside the
    write that the setting does not reach are left to the collector, which is
    run if the write took ``after`` seconds or more.
    """
    before = spark.conf.get(CLEAN_UP)
    start = time.monotonic()
    spark.conf.set(CLEAN_UP, "true")
    try:
        write()
    finally:
        spark.conf.set(CLEAN_UP, before)
    if time.monotonic() - start >= after:
        gc.collect()
        spark._jvm.System.gc()
