"""Token-id files: independent zstandard frames, a document index, a trailing seek table.

Layout of a file, all integers little-endian:

* data frames, each an independent zstandard frame over at most ``FRAME_IDS``
  ids (unsigned 32-bit); frames cut the file's id stream anywhere;
* one skippable frame with the compressed document index: for each document in
  file order its id (64-bit), a null flag and its number of ids;
* one skippable frame with the seek table in the published seekable layout:
  for each data frame its compressed size, its decompressed size and the low 32
  bits of XXH64 over the decompressed bytes, then the frame count, a descriptor
  byte and the table's magic number.

A reader takes the index and the table from the end of the file and then
decompresses only the frames that a requested document touches, checking each.
"""

from __future__ import annotations

import itertools
import struct
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from dupflow.llm.chunks import ENCODER_BATCH, batches_by_size
from dupflow.llm.common import open_shared, shared_path, shared_writer, text_or_empty

#: Fixed values of the published seekable format.
SEEK_FRAME_MAGIC = 0x184D2A5E
SEEK_TABLE_MAGIC = 0x8F92EAB1
CHECKSUM_FLAG = 0x80
#: Skippable frame used for the document index.
INDEX_FRAME_MAGIC = 0x184D2A50

FRAME_IDS = 1 << 18


class TokenFileWriter:
    """Writes one file frame by frame to ``out``: ids wait only until a frame is full, and only the index and the table grow."""

    def __init__(self, out, frame_ids: int = FRAME_IDS, level: int = 3):
        self.frame_bytes = 4 * frame_ids
        self.zip = zstandard.ZstdCompressor(level=level, write_checksum=True, write_content_size=True)
        self.out, self.raw = out, bytearray()
        self.table: list[bytes] = []
        self.ids, self.nulls, self.counts = array("q"), array("B"), array("q")

    def add(self, doc_id: int | None, ids: bytes) -> None:
        self.ids.append(doc_id or 0)
        self.nulls.append(doc_id is None)
        self.counts.append(len(ids) // 4)
        self.raw += ids
        while len(self.raw) >= self.frame_bytes:
            self._frame(self.frame_bytes)

    def _frame(self, n: int) -> None:
        part = bytes(self.raw[:n])
        del self.raw[:n]
        packed = self.zip.compress(part)
        self.out.write(packed)
        self.table.append(struct.pack("<III", len(packed), len(part), xxhash.xxh64_intdigest(part) & 0xFFFFFFFF))

    def finish(self) -> None:
        if self.raw:
            self._frame(len(self.raw))
        index = self.zip.compress(np.array(self.ids, "<i8").tobytes() + np.array(self.counts, "<i8").tobytes() + np.array(self.nulls, "u1").tobytes())
        index += struct.pack("<QI", len(self.ids), len(index))
        self.out.write(struct.pack("<II", INDEX_FRAME_MAGIC, len(index)) + index)
        seek = b"".join(self.table) + struct.pack("<IBI", len(self.table), CHECKSUM_FLAG, SEEK_TABLE_MAGIC)
        self.out.write(struct.pack("<II", SEEK_FRAME_MAGIC, len(seek)) + seek)


class TokenFileReader:
    """Random access to the documents of one file."""

    def __init__(self, handle):
        self.f = handle
        self.f.seek(0, 2)
        end = self.f.tell()
        n, flag, magic = struct.unpack("<IBI", self._at(end - 9, 9))
        if magic != SEEK_TABLE_MAGIC or flag != CHECKSUM_FLAG:
            raise ValueError("no seek table at the end of the file")
        seek = end - 9 - 12 * n - 8
        rows = np.frombuffer(self._at(seek + 8, 12 * n), "<u4").reshape(n, 3).astype(np.int64)
        self.sums = rows[:, 2]
        self.at = np.concatenate([[0], np.cumsum(rows[:, 0])])
        self.first = np.concatenate([[0], np.cumsum(rows[:, 1])])
        docs, size = struct.unpack("<QI", self._at(seek - 12, 12))
        index = zstandard.ZstdDecompressor().decompress(self._at(seek - 12 - size, size))
        self.doc_ids = np.frombuffer(index[: 8 * docs], "<i8")
        self.counts = np.frombuffer(index[8 * docs : 16 * docs], "<i8")
        self.nulls = np.frombuffer(index[16 * docs :], "u1").astype(bool)
        self.starts = np.concatenate([[0], np.cumsum(self.counts)])
        self.unzip = zstandard.ZstdDecompressor()
        self.held: tuple[int, bytes] = (-1, b"")
        self.frames_read = 0

    def _at(self, where: int, n: int) -> bytes:
        self.f.seek(where)
        return self.f.read(n)

    def _frame(self, k: int) -> bytes:
        if self.held[0] != k:
            raw = self.unzip.decompress(self._at(int(self.at[k]), int(self.at[k + 1] - self.at[k])))
            if xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != self.sums[k]:
                raise ValueError(f"checksum of frame {k} differs")
            self.held = (k, raw)
            self.frames_read += 1
        return self.held[1]

    def read(self, i: int) -> bytes:
        """Id bytes of the i-th document of the file."""
        lo, hi = 4 * int(self.starts[i]), 4 * int(self.starts[i + 1])
        if lo == hi:
            return b""
        k = int(np.searchsorted(self.first, lo, "right")) - 1
        parts = []
        while lo < hi:
            base, end = int(self.first[k]), int(self.first[k + 1])
            parts.append(self._frame(k)[lo - base : min(hi, end) - base])
            lo, k = end, k + 1
        return b"".join(parts)


MANIFEST = "part int, path string, n_docs long, n_tokens long"


def write_token_files(docs: DataFrame, out_dir: str, vocab: str, end_id: int | None = 2, id_col: str = "doc_id", text_col: str = "text") -> list[tuple]:
    """Encodes every text and writes one file for each range of ``doc_id``; returns the manifest in order.

    Rows are dealt by ranges of the id, so files and the rows in them ascend
    together and no task needs another's.  Null ids come first, equal ids are
    ordered by text; a null or empty text is a document of the end id alone.
    Columns other than the two named are not read.  The manifest has one row
    for each file, whatever the input holds.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    end = b"" if end_id is None else end_id.to_bytes(4, "little")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from dupflow.llm.hf_tokens import encoder

        encode, part = encoder(vocab).encode, TaskContext.get().partitionId()
        first = next(batches, None)
        if first is None:
            return
        path = f"{out_dir}/tokens-{part:06d}.zst"
        with shared_writer(path) as handle:
            out = TokenFileWriter(handle)
            for batch in itertools.chain([first], batches):
                ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
                for lo, hi in batches_by_size(texts, ENCODER_BATCH):
                    for doc_id, packed in zip(ids[lo:hi], encode(texts[lo:hi]), strict=True):
                        out.add(doc_id, packed + end)
            out.finish()
        if out.ids:
            yield pa.RecordBatch.from_pylist([{"part": part, "path": path, "n_docs": len(out.ids), "n_tokens": sum(out.counts)}], schema=pa.schema([("part", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_tokens", pa.int64())]))

    manifest = rows.repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text").mapInArrow(write, MANIFEST)
    return sorted(tuple(r) for r in manifest.collect())


READ = "doc_id long, start long, n_tokens long, ids_crc32 long"


def read_token_files(spark: SparkSession, manifest: list[tuple]) -> DataFrame:
    """One row for each document in the files: its id, the ids before it, its ids' number and crc32."""
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])
    bases, total = [], 0
    for _, path, _, n_tokens in manifest:
        bases.append((path, total))
        total += n_tokens

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                with open_shared(path) as handle:
                    file = TokenFileReader(handle)
                    n = len(file.doc_ids)
                    for lo in range(0, n, 8192):
                        hi = min(n, lo + 8192)
                        sums = [zlib.crc32(file.read(i)) for i in range(lo, hi)]
                        yield pa.RecordBatch.from_arrays([pa.array(file.doc_ids[lo:hi], pa.int64(), mask=file.nulls[lo:hi]), pa.array(file.starts[lo:hi] + base), pa.array(file.counts[lo:hi]), pa.array(sums, pa.int64())], schema=schema)

    files = spark.createDataFrame(bases, "path string, base long") if bases else spark.createDataFrame([], "path string, base long")
    return files.repartition(max(1, min(len(bases), 10_000))).mapInArrow(read, READ)


def token_round_trip(docs: DataFrame, vocab: str, end_id: int = 2) -> DataFrame:
    """Writes the files of all documents in the shared folder and reads them back."""
    spark = docs.sparkSession
    return read_token_files(spark, write_token_files(docs, shared_path(spark, "token-files"), vocab, end_id))
