"""Block-compressed alignment files: gzip members of about 64 KB with a block index.

Each part file is a run of gzip members, so parts joined byte by byte are one
legal file.  The header is a member of its own, before all parts.  Beside the
parts a Parquet index holds each block's place and, for every reference in it,
the least start and the greatest end, so a region read opens only the blocks
that hold a record of the region, whether the records are sorted or not.
"""

from __future__ import annotations

import gzip
import os
import struct
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from dupflow.functions.geometry import span
from dupflow.shared import local_path, write_then_free
from dupflow.sources.taf import Header, parse_taf, render_line

LIMIT = 65536
SPANS = "array<struct<ref:int,first:long,last:long>>"
INDEX = f"part int, path string, block_no long, offset long, length long, n_rec int, raw_len int, codec string, spans {SPANS}"
_SPANS = pa.list_(pa.struct([("ref", pa.int32()), ("first", pa.int64()), ("last", pa.int64())]))
_ARROW = pa.schema([("part", pa.int32()), ("path", pa.string()), ("block_no", pa.int64()), ("offset", pa.int64()), ("length", pa.int64()), ("n_rec", pa.int32()), ("raw_len", pa.int32()), ("codec", pa.string()), ("spans", _SPANS)])
HEADER = "header.baf"


def _member(raw: bytes) -> bytes:
    return gzip.compress(struct.pack(">I", len(raw)) + raw, mtime=0)


def write_header(out: str, header: Header) -> None:
    """The header's lines as the first member of the folder."""
    folder = local_path(out)
    os.makedirs(folder, exist_ok=True)
    with open(os.path.join(folder, HEADER), "wb") as f:
        f.write(_member("\n".join(header.lines).encode()))


def read_baf_header(path: str) -> Header:
    """The header written by :func:`write_header`; one without lines if there is none."""
    where = os.path.join(local_path(path), HEADER)
    if not os.path.exists(where):
        return Header([])
    with open(where, "rb") as f:
        text = next(block_records(gzip.decompress(f.read()))).decode()
    return Header(text.split("\n") if text else [])


def block_ends(sizes: np.ndarray, limit: int) -> list[int]:
    """Where blocks end, in records: each closes before it would pass the limit; a larger record is alone."""
    ends, at, total = [], 0, np.concatenate([[0], np.cumsum(sizes)])
    while at < len(sizes):
        at = max(at + 1, int(np.searchsorted(total, total[at] + limit, "right")) - 1)
        ends.append(at)
    return ends


def write_baf(records: DataFrame, out: str, codec: str = "software", limit: int = LIMIT, header: Header | None = None) -> DataFrame:
    """Packs, compresses and writes each partition in its order; returns the block index.

    A record is its seq, its library and its line, length first, built inside
    the JVM as one binary column; a task cuts that column's buffer into blocks
    of whole records by running sizes and hands the slices to the codec.  Files
    appear whole, and a task that runs again writes the same file.
    """
    body = F.concat_ws("\t", F.col("seq").cast("string"), F.coalesce("lib", F.lit("")), render_line(refs=header.refs() if header else None)).cast("binary")
    end = F.col("pos") + F.greatest(span(F.col("cigar")), F.lit(1)) - 1
    rows = records.select(F.coalesce("ref_id", F.lit(-1)).cast("int").alias("ref"), F.coalesce("pos", F.lit(0)).cast("long").alias("pos"), F.coalesce(end, F.lit(0)).alias("end"), body.alias("body"))
    rows = rows.select("ref", "pos", "end", F.concat(F.unhex(F.lpad(F.hex(F.octet_length("body")), 8, "0")), F.col("body")).alias("data"))
    folder = local_path(out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from dupflow.operators.codecs import codec as make

        c, part = make(codec), TaskContext.get().partitionId()
        path = os.path.join(folder, f"part-{part:05d}.baf")
        os.makedirs(folder, exist_ok=True)
        tmp = f"{path}.{uuid.uuid4().hex}"
        index: list[dict] = []
        offset = 0
        with open(tmp, "wb") as f:

            def blocks(waiting: pa.Table, last: bool) -> pa.Table:
                """Writes the full blocks of what waits, all of it at the end; returns the rest."""
                nonlocal offset
                waiting = waiting.combine_chunks()
                data = waiting.column("data").chunk(0) if len(waiting) else pa.array([], pa.binary())
                at = np.frombuffer(data.buffers()[1], np.int32)[data.offset : data.offset + len(data) + 1] if len(data) else np.zeros(1, np.int32)
                ref, pos, end = (waiting.column(k).to_numpy() for k in ("ref", "pos", "end"))
                ends, lo = block_ends(np.diff(at), limit), 0
                for hi in ends if last else ends[:-1]:
                    raw = memoryview(data.buffers()[2])[at[lo] : at[hi]]
                    packed = c.compress(bytes(raw), len(index))
                    f.write(packed)
                    held = ref[lo:hi]
                    spans = [{"ref": int(r), "first": int(pos[lo:hi][held == r].min()), "last": int(end[lo:hi][held == r].max())} for r in np.unique(held) if r >= 0]
                    index.append({"part": part, "path": path, "block_no": len(index), "offset": offset, "length": len(packed), "n_rec": hi - lo, "raw_len": len(raw), "codec": c.name, "spans": spans})
                    offset, lo = offset + len(packed), hi
                return waiting.slice(lo)

            rest = None
            for b in batches:
                new = pa.Table.from_batches([b])
                rest = blocks(new if rest is None else pa.concat_tables([rest, new]), False)
            if rest is not None and len(rest):
                blocks(rest, True)
        if index:
            os.replace(tmp, path)
            yield pa.RecordBatch.from_pylist(index, schema=_ARROW)
        else:
            os.remove(tmp)

    if header is not None:
        write_header(out, header)
    write_then_free(records.sparkSession, lambda: rows.mapInArrow(run, INDEX).write.parquet(f"{out}/_index"))
    return records.sparkSession.read.schema(INDEX).parquet(f"{out}/_index")


def block_records(raw: bytes) -> Iterator[bytes]:
    at = 0
    while at < len(raw):
        (size,) = struct.unpack_from(">I", raw, at)
        yield raw[at + 4 : at + 4 + size]
        at += 4 + size


def _lines(path: str, block: int, offset: int, length: int) -> pa.RecordBatch:
    """Records of one block as (block_no, seq, lib, value)."""
    with open(path, "rb") as f:
        f.seek(offset)
        rows = [r.decode().split("\t", 2) for r in block_records(gzip.decompress(f.read(length)))]
    return pa.RecordBatch.from_arrays([pa.array([block] * len(rows), pa.int64()), *[pa.array(c, pa.string()) for c in zip(*rows, strict=True)]], names=["block_no", "seq", "lib", "value"])


def index_of(spark: SparkSession, path: str, region: tuple[int, int, int] | None = None) -> DataFrame:
    """The block index, with a region only the blocks that hold a record of it."""
    index = spark.read.schema(INDEX).parquet(f"{path}/_index")
    if region is None:
        return index
    ref, start, end = region
    return index.where(F.exists("spans", lambda x: (x["ref"] == ref) & (x["first"] <= end) & (x["last"] >= start)))


def read_baf(spark: SparkSession, path: str, region: tuple[int, int, int] | None = None, seq_type: str = "decimal(38,0)") -> DataFrame:
    """Records of a folder written by :func:`write_baf`; a region opens only blocks that hold a record of it.

    The caller's overlap filter picks the records themselves.  ``tid`` is the
    hash of the read name that :func:`dupflow.sources.taf.read_taf` has.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for where, block, offset, length in zip(*[b.column(i).to_pylist() for i in range(4)], strict=True):
                yield _lines(where, block, offset, length)

    lines = index_of(spark, path, region).select("path", "block_no", "offset", "length").mapInArrow(run, "block_no long, seq string, lib string, value string")
    parsed = parse_taf(lines.select(F.col("seq").cast(seq_type).alias("seq"), F.when(F.col("lib") != "", F.col("lib")).alias("lib"), "value"), keep=["seq", "lib"], refs=read_baf_header(path).refs() or None).drop("_corrupt")
    return parsed.withColumn("tid", F.unhex(F.md5(F.col("qname").cast("binary"))))


class _Part(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _BafReader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder = local_path(options["path"])

    def partitions(self):
        return [_Part(os.path.join(self.folder, n)) for n in sorted(os.listdir(self.folder)) if n.startswith("part-") and n.endswith(".baf")] or [_Part("")]

    def read(self, p: _Part) -> Iterator[pa.RecordBatch]:
        """A part's records from its bytes alone, member by member, without the index."""
        import zlib

        if not p.path:
            return
        with open(p.path, "rb") as f:
            block, left = 0, b""
            while left or (left := f.read(1 << 20)):
                d, raw = zlib.decompressobj(31), []
                while not d.eof:
                    raw.append(d.decompress(left))
                    left = d.unused_data if d.eof else f.read(1 << 20)
                rows = [r.decode().split("\t", 2) for r in block_records(b"".join(raw))]
                yield pa.RecordBatch.from_arrays([pa.array([block] * len(rows), pa.int64()), *[pa.array(c, pa.string()) for c in zip(*rows, strict=True)]], names=["block_no", "seq", "lib", "value"])
                block += 1


class BafSource(DataSource):
    """``format('baf')``: (block_no, seq, lib, value) of all records of a folder, one task for each part."""

    @classmethod
    def name(cls):
        return "baf"

    def schema(self):
        return "block_no long, seq string, lib string, value string"

    def reader(self, schema):
        return _BafReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(BafSource)


def concat_parts(path: str, out: str) -> None:
    """Joins header and part files in order into one; gzip members follow each other legally."""
    folder = local_path(path)
    with open(out, "wb") as o:
        for name in [HEADER] * os.path.exists(os.path.join(folder, HEADER)) + sorted(n for n in os.listdir(folder) if n.startswith("part-") and n.endswith(".baf")):
            with open(os.path.join(folder, name), "rb") as f:
                while chunk := f.read(1 << 20):
                    o.write(chunk)
