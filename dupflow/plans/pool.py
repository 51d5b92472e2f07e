"""Pools of records in memory or storage, their index, and fetches by locator."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dupflow.shared import shared_base, shared_path, write_then_free


def available_storage(spark: SparkSession) -> int:
    """Bytes that executors have left for stored blocks; the driver counts where it runs the tasks."""
    status = spark.sparkContext._jsc.sc().getExecutorMemoryStatus()
    it, left = status.iterator(), []
    while it.hasNext():
        left.append(int(it.next()._2()._2()))
    return sum(left)


def input_bytes(spark: SparkSession, path: str) -> int:
    """Size of the files under a path."""
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    return int(hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(hadoop).getLength())


def choose_mode(size: int, storage_memory_bytes: int, expansion: float = 2.5) -> str:
    """Memory mode only if the expanded records fit in the memory that executors keep for storage."""
    return "memory" if size * expansion <= storage_memory_bytes else "storage"


def pool(records: DataFrame, mode: str = "storage", path: str | None = None) -> DataFrame:
    """The pooled records: persisted (spilling, never dropped) or written as Parquet in input layout."""
    if mode == "memory":
        return records.persist(StorageLevel.MEMORY_AND_DISK)
    path = path or shared_path(records.sparkSession, "pool")
    write_then_free(records.sparkSession, lambda: records.write.option("compression", "zstd").parquet(path))
    return records.sparkSession.read.schema(records.schema).parquet(path)


def is_stored(records: DataFrame) -> bool:
    """Whether ``records`` are a whole table in the shared folder as it was written, by nothing but a read."""
    plan = records._jdf.queryExecution().analyzed()
    if plan.getClass().getSimpleName() != "LogicalRelation":
        return False
    base = _plain(shared_base(records.sparkSession)) + "/"
    files = records.inputFiles()
    return bool(files) and all(_plain(f).startswith(base) for f in files)


def _plain(uri: str) -> str:
    """A file's URI with one slash after the scheme, as both forms are in use."""
    return "file:/" + uri[5:].lstrip("/") if uri.startswith("file:") else uri if "://" in uri else "file:/" + uri.lstrip("/")


def pool_once(records: DataFrame, mode: str = "storage", path: str | None = None) -> DataFrame:
    """:func:`pool`, but a table that is stored already is its own pool, whole and in input layout.

    In memory mode what does not fit stays in that table and is read again,
    where other records would spill to disk.
    """
    if path is not None or not is_stored(records):
        return pool(records, mode, path)
    return records.persist(StorageLevel.MEMORY_ONLY) if mode == "memory" else records


def release(pooled: DataFrame) -> None:
    """Gives back the memory of a pool in memory mode; a stored pool stays until its folder is removed."""
    pooled.unpersist()


def with_locator(records: DataFrame, tier: str = "storage") -> DataFrame:
    """A virtual address for each record: tier and seq, which packs file number and byte offset where files were read."""
    return records.withColumn("locator", F.struct(F.lit(tier).alias("tier"), F.col("seq").alias("seq")))


def resolve(locators: DataFrame, pooled: DataFrame) -> DataFrame:
    """Records of the given locators by a shuffle join; never by single seeks."""
    return pooled.join(locators.select(F.col("locator.seq").alias("seq")), "seq", "left_semi")


def fetch_lines(locators: DataFrame, path: str, block_bytes: int = 1 << 20) -> DataFrame:
    """(seq, value): the lines at the given addresses, read from the files themselves.

    Addresses are dealt by block and ascend inside a task, so each block of a
    file is read by one task in one direction; only blocks that hold a wanted
    line are read.  ``path`` is the folder or file that ``read_taf`` read.
    """
    from dupflow.sources.taf import data_files

    files = data_files(path)
    at = F.col("locator.seq")
    rows = locators.select(at.alias("seq"), F.shiftright(at, 48).cast("int").alias("file_id"), at.bitwiseAND(F.lit((1 << 48) - 1)).alias("start"))
    rows = rows.repartition("file_id", F.floor(F.col("start") / block_bytes)).sortWithinPartitions("file_id", "start")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, f = -1, None
        for b in batches:
            out = []
            for file_id, start in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True):
                if file_id != held:
                    if f:
                        f.close()
                    held, f = file_id, open(files[file_id], "rb")  # noqa: SIM115
                f.seek(start)
                out.append(f.readline().rstrip(b"\n").decode("utf-8", "replace"))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.string())], names=["seq", "value"])
        if f:
            f.close()

    return rows.mapInArrow(run, "seq long, value string")


def groups(digests: DataFrame, kind: str = "clipped") -> DataFrame:
    """Number and seq range of the records at each place; the group's rows need not be gathered."""
    key = ["ref_id", "pos"] if kind == "clipped" else ["ref_id", "u5"]
    return digests.where(F.col("ref_id") >= 0).groupBy(*key).agg(F.count("*").alias("n"), F.min("seq").alias("first_seq"), F.max("seq").alias("last_seq"), F.max("score").alias("best_score"))


def at(digests: DataFrame, ref: int, pos: int, kind: str = "clipped") -> DataFrame:
    """All digests at one place."""
    return digests.where((F.col("ref_id") == ref) & (F.col("pos" if kind == "clipped" else "u5") == pos))


def with_mates(digests: DataFrame) -> DataFrame:
    """Each mapped primary end with its mate's place, by a join on the template."""
    from dupflow.operators.dupmark import eligible

    d = eligible(digests)
    m = d.select("tid", F.col("end_no").alias("mate_end"), F.col("ref_id").alias("m_ref"), F.col("u5").alias("m_u5"), F.col("rev").alias("m_rev"))
    return d.join(m, (d["tid"] == m["tid"]) & (d["end_no"] != m["mate_end"])).select(d["seq"], d["ref_id"], d["u5"], d["rev"], "m_ref", "m_u5", "m_rev")


def decompose(digests: DataFrame, workers: int, blocks_per_worker: int, lengths: list[int] | None = None) -> DataFrame:
    """The index in workers x blocks contiguous ranges of the reference space, as column ``piece``.

    With the references' ``lengths``, as a header has them, ranges are equal in
    length; without, they hold about equally many records, by sampled cut
    points.  Inside a piece order is by place, so any piece can be analysed
    alone.
    """
    n = workers * blocks_per_worker
    mapped = digests.where(F.col("ref_id") >= 0)
    if lengths:
        total, before = sum(lengths), [sum(lengths[:i]) for i in range(len(lengths))]
        line = F.get(F.array(*[F.lit(x).cast("long") for x in before]), F.col("ref_id")) + F.greatest(F.col("u5"), F.lit(0))
        return mapped.withColumn("piece", F.least(F.floor(line * n / total), F.lit(n - 1)).cast("int"))
    line = F.shiftleft(F.col("ref_id").cast("long"), 40) + F.greatest(F.col("u5"), F.lit(0))
    cuts = sorted(set(mapped.agg(F.percentile_approx(line, [i / n for i in range(1, n)], 10_000).alias("c")).first()["c"] or []))
    return mapped.withColumn("piece", F.size(F.filter(F.array(*[F.lit(c) for c in cuts]), lambda c: c < line)).cast("int") if cuts else F.lit(0))
