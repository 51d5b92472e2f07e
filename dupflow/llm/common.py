"""Shared plumbing of the training-data operators."""

from __future__ import annotations

import contextlib
import contextvars
import os
import time
import uuid
from collections.abc import Callable
from urllib.parse import urlparse

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from dupflow.shared import write_then_free


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session.

    A session without that setting, as in a notebook on one machine, must name
    a folder by ``SparkContext.setCheckpointDir``; a session that runs on this
    machine alone is given one beside its warehouse.
    """
    conf = spark.conf.get("spark.checkpoint.dir", None)
    if conf:
        return conf.rstrip("/")
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/shared")
    return sc.getCheckpointDir().rstrip("/")


def shared_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


#: Tables that were written inside the innermost call of :func:`settled`.
_written: contextvars.ContextVar[list[str] | None] = contextvars.ContextVar("written", default=None)


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Writes ``df`` as a table in the shared folder and reads it back: lineage ends there.

    The table stays until the call of :func:`settled` that it was written in has
    its result, or else until the owner of the folder in ``spark.checkpoint.dir``
    clears it after the job.
    """
    spark = df.sparkSession
    path = shared_path(spark, name)
    write_then_free(spark, lambda: df.write.parquet(path))
    if (mine := _written.get()) is not None:
        mine.append(path)
    return spark.read.schema(df.schema).parquet(path)


def settled(make: Callable[[], DataFrame], name: str, patience: float = 30.0) -> DataFrame:
    """The result of ``make`` as a table; the tables that ``make`` wrote on its way are removed then.

    No plan but that of the result may read them.  A query that ends early,
    because a side of a join was empty, can leave a stage behind that still
    reads its inputs, so nothing is removed while the engine is at work on any
    stage; after ``patience`` seconds the tables are left to the folder's owner.
    """
    outer, mine = _written.get(), []
    mark = _written.set(mine)
    try:
        df = make()
    finally:
        _written.reset(mark)
    out = materialize(df, name)
    spark, end = out.sparkSession, time.monotonic() + patience
    tracker = spark.sparkContext.statusTracker()
    while busy := tracker.getActiveStageIds():
        if time.monotonic() >= end:
            break
        time.sleep(0.02)
    if busy:
        if outer is not None:
            outer.extend(mine)
        return out
    for path in mine:
        hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).delete(hadoop, True)
    return out


def local_part(uri: str) -> str | None:
    """The plain path of a ``file:`` URI or bare path, None for any other store."""
    parsed = urlparse(uri)
    return parsed.path if parsed.scheme in ("", "file") else None


@contextlib.contextmanager
def shared_writer(uri: str):
    """A binary writer of a file that readers see whole or not at all; a retry writes the same file again."""
    path = local_part(uri)
    if path is not None:
        os.makedirs(os.path.dirname(path), exist_ok=True)
        tmp = f"{path}.{uuid.uuid4().hex}.tmp"
        with open(tmp, "wb") as out:
            yield out
        os.replace(tmp, path)
        return
    from pyarrow import fs

    store, where = fs.FileSystem.from_uri(uri)
    store.create_dir(os.path.dirname(where), recursive=True)
    with store.open_output_stream(where) as out:
        yield out


def open_shared(uri: str):
    """A seekable binary reader of a file in the shared folder."""
    path = local_part(uri)
    if path is not None:
        return open(path, "rb")
    from pyarrow import fs

    store, where = fs.FileSystem.from_uri(uri)
    return store.open_input_file(where)


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def sha256_hex(c: Column) -> Column:
    return F.sha2(c.cast("binary"), 256)
