"""Ordered dispatch of records into blocks by their sizes alone, and parallel compression."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LIMIT = 65536


def pack_prefix(sizes: DataFrame, order: list[str], limit: int = LIMIT, shards: int = 64) -> DataFrame:
    """Blocks by running size: a record goes to block floor(bytes before it / limit).

    Two passes instead of one task: totals of key ranges, then a sum inside
    each.  The ranges are cut points of the first order column, a bounded
    number of them, so only ``shards`` totals are ever brought together.
    """
    lead = order[0]
    cuts = sizes.selectExpr(f"percentile_approx({lead}, array({', '.join(f'{i / shards}D' for i in range(1, shards))}), 1000) c").first()["c"] or []
    cuts = sorted(set(cuts))
    shard = F.lit(0)
    for c in cuts:
        shard = shard + F.when(F.col(lead) > F.lit(c), 1).otherwise(0)
    rows = sizes.withColumn("__shard", shard)
    totals = rows.groupBy("__shard").agg(F.sum("rec_bytes").alias("__total"))
    before = totals.withColumn("__before", F.coalesce(F.sum("__total").over(Window.partitionBy(F.lit(0)).orderBy("__shard").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("__total")  # at most `shards` rows
    inside = Window.partitionBy("__shard").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    joined = rows.join(F.broadcast(before), "__shard")
    at = F.col("__before") + F.coalesce(F.sum("rec_bytes").over(inside), F.lit(0))
    return joined.withColumn("block_no", F.floor(at / limit).cast("long")).drop("__shard", "__before")


def greedy_blocks(sizes: list[int], limit: int = LIMIT) -> list[int]:
    """Block of each record when a block is closed before it would pass the limit; a larger record is alone."""
    out, block, used = [], 0, 0
    for s in sizes:
        if used and used + s > limit:
            block, used = block + 1, 0
        out.append(block)
        used += s
    return out


def pack_greedy(sizes: DataFrame, limit: int = LIMIT) -> DataFrame:
    """(part, block_no) of each row in the order of its partition; at most one short block a partition."""
    fields = sizes.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part, block, used = TaskContext.get().partitionId(), 0, 0
        for b in batches:
            blocks = []
            for s in b.column(b.schema.get_field_index("rec_bytes")).to_pylist():
                if used and used + s > limit:
                    block, used = block + 1, 0
                blocks.append(block)
                used += s
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([part] * len(blocks), pa.int32()), pa.array(blocks, pa.int64())], names=[*b.schema.names, "part", "block_no"])

    from pyspark.sql import types as T

    return sizes.mapInArrow(run, T.StructType([*fields.fields, T.StructField("part", T.IntegerType()), T.StructField("block_no", T.LongType())]))


def compress_payloads(df: DataFrame, column: str, codec_name: str = "software") -> DataFrame:
    """(id columns, raw_len, packed_len, crc, back_crc): each payload compressed and read back in parallel tasks."""
    keep = [c for c in df.columns if c != column]
    from pyspark.sql import types as T

    out = T.StructType([*[df.schema[c] for c in keep], T.StructField("raw_len", T.LongType()), T.StructField("packed_len", T.LongType()), T.StructField("crc", T.LongType()), T.StructField("back_crc", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from dupflow.operators.codecs import codec

        c = codec(codec_name)
        for b in batches:
            rows = [(x or "").encode() if not isinstance(x, bytes) else x for x in b.column(b.schema.get_field_index(column)).to_pylist()]
            packed = [c.compress(x, i) for i, x in enumerate(rows)]
            back = [zlib.decompress(x, 31) for x in packed]
            cols = [b.column(b.schema.get_field_index(k)) for k in keep]
            yield pa.RecordBatch.from_arrays([*cols, *[pa.array(v, pa.int64()) for v in ([len(x) for x in rows], [len(x) for x in packed], [zlib.crc32(x) for x in rows], [zlib.crc32(x) for x in back])]], names=[*keep, "raw_len", "packed_len", "crc", "back_crc"])

    return df.mapInArrow(run, out)
