"""Text alignment format: rendering, parsing, and the source that reads byte ranges."""

from __future__ import annotations

import os
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from dupflow.schema import TAG
from dupflow.shared import local_path

FIELDS = 11


def ref_name(ref: Column, refs: list[str] | None = None) -> Column:
    """Name of a reference number: its place in ``refs``, or ``ref<number>``."""
    named = F.concat(F.lit("ref"), ref.cast("string")) if not refs else F.get(F.array(*map(F.lit, refs)), ref)
    return F.when(ref < 0, "*").otherwise(named)


def render_line(refs: list[str] | None = None) -> Column:
    """One line of eleven tab-joined fields and the optional ones, in their order."""
    mate = F.when((F.col("mate_ref_id") == F.col("ref_id")) & (F.col("ref_id") >= 0), "=").otherwise(ref_name(F.col("mate_ref_id"), refs))
    tags = F.transform("tags", lambda t: F.concat_ws(":", t["tag"], t["type"], t["value"]))
    fixed = ["qname", "flag", ref_name(F.col("ref_id"), refs), "pos", "mapq", "cigar", mate, "mate_pos", "tlen", "bases", "quals"]
    fixed = [F.col(c) if isinstance(c, str) else c for c in fixed]
    return F.concat_ws("\t", *[c.cast("string") for c in fixed], F.array_join(tags, "\t"))


def render_taf(records: DataFrame, refs: list[str] | None = None) -> DataFrame:
    """(seq, value): each record as a line."""
    return records.select("seq", render_line(refs).alias("value"))


def _ref(name: Column, refs: list[str] | None = None) -> Column:
    """Number of a reference name: its place in ``refs``, or the digits of ``ref<digits>``; -1 for none."""
    if refs is None:
        known = F.regexp_extract(name, r"^ref([0-9]+)$", 1).try_cast("int")
    else:
        known = F.element_at(F.create_map(*[F.lit(x) for i, r in enumerate(refs) for x in (r, i)]), name) if refs else F.lit(None).cast("int")
    return F.when(name == "*", -1).otherwise(known)


def parse_taf(lines: DataFrame, mode: str = "permissive", keep: list[str] | None = None, refs: list[str] | None = None) -> DataFrame:
    """Typed records from lines in ``value``; header lines (first character ``@``) are no records.

    ``refs`` are the reference names in the order of the header.

    ``permissive`` keeps a line that has too few fields or a bad number as nulls
    with its text in ``_corrupt``; ``lenient`` drops it; ``strict`` fails.
    Parsing never leaves the JVM.
    """
    keep = keep or []
    p = lines.where(~F.col("value").startswith("@")).select(*keep, "value", F.split("value", "\t").alias("p"))
    at = lambda i: F.get(F.col("p"), F.lit(i))
    ref, mate = _ref(at(2), refs), F.when(at(6) == "=", _ref(at(2), refs)).otherwise(_ref(at(6), refs))
    tag = lambda t: F.struct(F.substring_index(t, ":", 1).alias("tag"), F.get(F.split(t, ":"), F.lit(1)).alias("type"), F.substr(t, F.length(F.substring_index(t, ":", 2)) + 2).alias("value"))
    tags = F.when(F.size("p") > FIELDS, F.transform(F.slice("p", F.lit(FIELDS + 1), F.greatest(F.size("p") - FIELDS, F.lit(0))), tag)).otherwise(F.expr(f"cast(array() as array<{TAG}>)"))
    rows = p.select(
        *keep, "value", at(0).alias("qname"), at(1).try_cast("int").alias("flag"), ref.alias("ref_id"), at(3).try_cast("long").alias("pos"), at(4).try_cast("int").alias("mapq"), at(5).alias("cigar"),
        mate.alias("mate_ref_id"), at(7).try_cast("long").alias("mate_pos"), at(8).try_cast("long").alias("tlen"), at(9).alias("bases"), at(10).alias("quals"), tags.alias("tags"),
    )
    bad = F.col("quals").isNull()
    for c in ("flag", "ref_id", "pos", "mapq", "mate_ref_id", "mate_pos", "tlen"):
        bad = bad | F.col(c).isNull()
    if mode == "lenient":
        return rows.where(~bad).drop("value")
    if mode == "strict":
        checked = F.when(bad, F.raise_error(F.concat(F.lit("bad alignment line: "), F.substring("value", 1, 80)))).otherwise(F.col("qname"))
        return rows.withColumn("qname", checked).drop("value")
    return rows.withColumn("_corrupt", F.when(bad, F.col("value"))).drop("value")


def with_sequence(df: DataFrame, how: str, local_bits: int = 33) -> DataFrame:
    """A global sequence number in input order, without any coordination between tasks.

    ``offset``: (file_id, start) packed; ``block_local``: block number and local
    number packed; ``table_key``: the given column ``key``.
    """
    if how == "offset":
        return df.withColumn("seq", F.shiftleft(F.col("file_id").cast("long"), 48).bitwiseOR(F.col("start")))
    if how == "block_local":
        return df.withColumn("seq", F.shiftleft(F.col("block_id"), local_bits).bitwiseOR(F.col("line_no").cast("long")))
    return df.withColumn("seq", F.col("key"))


class BlockRange(InputPartition):
    def __init__(self, file_id: int, path: str, first: int, last: int, size: int):
        self.file_id, self.path, self.first, self.last, self.size = file_id, path, first, last, size


def repaired(f, start: int, end: int, size: int, own: str) -> tuple[int, int]:
    """The byte range of the block [start, end) after repair, so that it holds whole lines.

    ``own='end'``: a line belongs to the block that holds its last byte (its
    newline, or the end of the file); ``own='start'``: to the block that holds
    its first byte.  Only the neighbourhood of each edge is read.
    """

    def line_start(x: int) -> int:
        """Start of the line that holds byte x, looking backwards."""
        step = 256
        while x > 0:
            lo = max(0, x - step)
            f.seek(lo)
            cut = f.read(x - lo).rfind(b"\n")
            if cut >= 0:
                return lo + cut + 1
            x, step = lo, step * 2
        return 0

    def next_line(x: int) -> int:
        """First line start at or after x, looking forwards."""
        if x <= 0:
            return 0
        f.seek(x - 1)
        at = x - 1
        while chunk := f.read(4096):
            cut = chunk.find(b"\n")
            if cut >= 0:
                return at + cut + 1
            at += len(chunk)
        return size

    edge = line_start if own == "end" else next_line
    return (0 if start == 0 else edge(start)), (size if end >= size else edge(end))


def cut_positions(data: bytes, block_bytes: int, own: str) -> list[tuple[int, int, int]]:
    """(block, start, end) of the repaired blocks of a byte string; empty blocks are left out."""
    import io

    f, out = io.BytesIO(data), []
    for b in range(-(-len(data) // block_bytes)):
        lo, hi = repaired(f, b * block_bytes, min(len(data), (b + 1) * block_bytes), len(data), own)
        if lo < hi:
            out.append((b, lo, hi))
    return out


def data_files(path: str) -> list[str]:
    """The files of a folder in name order, or the file itself; a file's place here is its number."""
    path = local_path(path)
    if os.path.isdir(path):
        return sorted(os.path.join(path, n) for n in os.listdir(path) if not n.startswith((".", "_")))
    return [path]


def block_lines(file_id: int, block: int, start: int, data: bytes, types: list[pa.DataType]) -> list[pa.Array]:
    """The lines of a block's bytes with their places, as columns; places and lengths are bytes of the file, bad ones in a text are replaced."""
    import pyarrow.compute as pc

    lines = pc.split_pattern(pa.array([data[: -1 if data.endswith(b"\n") else None]], pa.binary()), b"\n").flatten()
    sizes = pc.binary_length(lines).to_numpy()
    starts = start + np.cumsum(sizes + 1, dtype=np.int64) - sizes - 1
    try:
        values = lines.cast(pa.string())
    except pa.ArrowInvalid:
        values = pa.array([x.decode("utf-8", "replace") for x in lines.to_pylist()], pa.string())
    n = len(lines)
    same = lambda v, t: pa.array(np.full(n, v), t)
    return [same(file_id, types[0]), same(block, types[1]), pa.array(np.arange(n), types[2]), pa.array(starts, types[3]), pa.array(sizes, types[4]), values]


class _BlockReader(DataSourceReader):
    def __init__(self, options: dict, lines: bool):
        self.path, self.block, self.own, self.lines = local_path(options["path"]), int(options.get("block_bytes", 65536)), options.get("own", "end"), lines
        self.task = int(options.get("task_bytes", 256 << 20))

    def partitions(self):
        files = data_files(self.path)
        out, per = [], max(1, self.task // self.block)
        for i, p in enumerate(files):
            size = os.path.getsize(p)
            blocks = -(-size // self.block)
            out += [BlockRange(i, p, b, min(blocks, b + per), size) for b in range(0, blocks, per)]
        return out or [BlockRange(0, "", 0, 0, 0)]

    def read(self, r: BlockRange) -> Iterator[pa.RecordBatch]:
        names = ["file_id", "block_id", "line_no", "start", "length", "value"] if self.lines else ["file_id", "block_id", "start", "bytes"]
        types = [pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.string()] if self.lines else [pa.int32(), pa.int64(), pa.int64(), pa.binary()]
        rows: list[tuple] = []
        held: list[pa.RecordBatch] = []
        if r.path:
            with open(r.path, "rb") as f:
                for b in range(r.first, r.last):
                    lo, hi = repaired(f, b * self.block, min(r.size, (b + 1) * self.block), r.size, self.own)
                    if lo >= hi:
                        continue
                    f.seek(lo)
                    data = f.read(hi - lo)
                    if not self.lines:
                        rows.append((r.file_id, b, lo, data))
                    else:
                        held.append(pa.RecordBatch.from_arrays(block_lines(r.file_id, b, lo, data, types), names=names))
                        if sum(map(len, held)) >= 4096:
                            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
                            held = []
                    if len(rows) >= 4096:
                        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)
                        rows = []
        if held:
            yield from pa.Table.from_batches(held).combine_chunks().to_batches()
        if rows:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)


class BlockSource(DataSource):
    """``format('taf_blocks')``: repaired byte blocks; ``format('taf_lines')``: their lines with places."""

    @classmethod
    def name(cls):
        return "taf_blocks"

    def schema(self):
        return "file_id int, block_id long, start long, bytes binary"

    def reader(self, schema):
        return _BlockReader(self.options, False)


class LineSource(BlockSource):
    @classmethod
    def name(cls):
        return "taf_lines"

    def schema(self):
        return "file_id int, block_id long, line_no int, start long, length int, value string"

    def reader(self, schema):
        return _BlockReader(self.options, True)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(BlockSource)
    spark.dataSource.register(LineSource)


def cut_blocks(spark: SparkSession, path: str, block_bytes: int = 65536, own: str = "end") -> DataFrame:
    register(spark)
    return spark.read.format("taf_blocks").options(path=path, block_bytes=block_bytes, own=own).load()


def read_lines(spark: SparkSession, path: str, block_bytes: int = 65536, own: str = "end") -> DataFrame:
    """Lines of the repaired blocks with their places: reading, repair and splitting in one narrow stage."""
    register(spark)
    return spark.read.format("taf_lines").options(path=path, block_bytes=block_bytes, own=own).load()


class Header:
    """Header lines of an alignment file, kept as they are and in their order."""

    def __init__(self, lines: list[str]):
        self.lines = lines

    def rows(self) -> list[tuple[str, int, dict[str, str]]]:
        """(kind, place, fields) of each line."""
        out = []
        for i, line in enumerate(self.lines):
            kind, *fields = line[1:].split("\t")
            out.append((kind, i, dict(f.split(":", 1) for f in fields if ":" in f)))
        return out

    def refs(self) -> list[str]:
        return [f["SN"] for kind, _, f in self.rows() if kind == "SQ"]

    def lengths(self) -> list[int]:
        return [int(f["LN"]) for kind, _, f in self.rows() if kind == "SQ"]

    def libraries(self) -> dict[str, str]:
        """Library of each read group that names one."""
        return {f["ID"]: f["LB"] for kind, _, f in self.rows() if kind == "RG" and "ID" in f and "LB" in f}

    def with_program(self, name: str, sort_order: str | None = None) -> Header:
        """The header of an output: version and lines stay, a program line is added, the order of records renewed."""
        lines = [re.sub(r"\tSO:[^\t]*", "", x) + f"\tSO:{sort_order}" if sort_order and x.startswith("@HD") else x for x in self.lines]
        return Header([*lines, f"@PG\tID:{name}\tPN:{name}"])


def read_header(spark: SparkSession, path: str) -> Header:
    """The leading ``@`` lines of the first file; its size is that of the header, not of the input."""
    first = sorted(f for f in spark.read.text(path).inputFiles())[:1]
    if not first:
        return Header([])
    # line by line: an iterator over the rows of a table would fetch a whole split of the file to the driver
    jvm = spark._jvm
    where = jvm.org.apache.hadoop.fs.Path(jvm.java.net.URI(first[0]))
    source = where.getFileSystem(spark._jsc.hadoopConfiguration()).open(where)
    reader = jvm.java.io.BufferedReader(jvm.java.io.InputStreamReader(source, "UTF-8"))
    lines: list[str] = []
    try:
        while (line := reader.readLine()) is not None and line.startswith("@"):
            lines.append(line)
    finally:
        reader.close()
    return Header(lines)


def read_taf(spark: SparkSession, path: str, block_bytes: int = 65536, mode: str = "permissive") -> tuple[DataFrame, Header]:
    """Records of text alignment files, and their header.

    ``seq`` packs file number and byte offset, so it ascends in input order
    without any coordination; ``tid`` is a 128-bit hash of the read name, as two
    ends of a template share it; ``lib`` is the read group's library, or the
    read group if the header names none.  Files, blocks, lines and fields are
    read in one narrow stage.
    """
    header = read_header(spark, path)
    lines = with_sequence(read_lines(spark, path, block_bytes), "offset").select("seq", "value")
    records = parse_taf(lines, mode, keep=["seq"], refs=header.refs() or None)
    group = F.get(F.transform(F.filter("tags", lambda t: t["tag"] == "RG"), lambda t: t["value"]), F.lit(0))
    named = header.libraries()
    lib = F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in named.items() for x in kv]), group), group) if named else group
    return records.withColumn("tid", F.unhex(F.md5(F.col("qname").cast("binary")))).withColumn("lib", lib), header


def line_places(texts: DataFrame, id_col: str, text_col: str, block_bytes: int, own: str = "end") -> DataFrame:
    """Lines of texts in a column, each text a file of its own, with byte places and blocks.

    Built-in expressions only: a line's start is the bytes of the lines before it.
    """
    lines = texts.select(F.col(id_col).alias("file_id"), F.octet_length(text_col).alias("size"), F.split(text_col, "\n", -1).alias("ls"))
    starts = F.aggregate("ls", F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<int>)").alias("xs")), lambda a, l: F.struct((a["at"] + F.octet_length(l) + 1).alias("at"), F.concat(a["xs"], F.array(a["at"])).alias("xs")), lambda a: a["xs"])  # noqa: E741
    each = lines.select("file_id", "size", F.posexplode(F.arrays_zip(F.col("ls").alias("value"), starts.alias("start"))).alias("line_no", "x")).select("file_id", "size", "line_no", F.col("x.value").alias("value"), F.col("x.start").alias("start"))
    each = each.withColumn("length", F.octet_length("value"))
    each = each.where((F.col("start") < F.col("size")) | (F.col("length") > 0))  # what follows a last newline is no line
    last = F.least(F.col("start") + F.col("length"), F.col("size") - 1)
    byte = last if own == "end" else F.col("start")
    return each.withColumn("block_id", F.floor(byte / block_bytes).cast("long")).drop("size")
