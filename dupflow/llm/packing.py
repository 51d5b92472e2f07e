"""Sum-of-squares online packing of token ids into windows.

An item of size s goes to the fill level h (0 is a new window) for which the
sum over levels of the squared number of open windows is least afterwards.
Only documents longer than a window are cut on arrival.  When a partition ends,
its open windows are topped up from the emptiest ones, and the last remainder
is laid out in sequences whose lengths are powers of two, so nothing is padded.
Each partition packs its own rows: no shuffle, memory bounded by one open
window for each fill level times the few that share a level.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dupflow.llm.chunks import ENCODER_BATCH, batches_by_size
from dupflow.llm.common import text_or_empty

WINDOW = 2048

#: Sequences of one partition are numbered from its partition number times this.
PER_PARTITION = 1 << 40


class SumOfSquaresPacker:
    """Takes (key, id bytes) and gives pieces (key, start, ids, total, sequence, offset)."""

    def __init__(self, window: int = WINDOW, first_sequence: int = 0):
        self.window = window
        self.open: list[list[list]] = [[] for _ in range(window)]
        self.count = np.zeros(window + 1, np.int64)
        self.next = first_sequence
        self.max_open = 0

    def _emit(self, pieces: list) -> Iterator[tuple]:
        offset = 0
        for key, start, ids, total in pieces:
            yield key, start, ids, total, self.next, offset
            offset += len(ids) // 4
        self.next += 1

    def level_for(self, size: int) -> int:
        """Level whose use gives the least sum of squares; ties to the fullest."""
        top = self.window - size
        after = 2 * self.count[size : self.window + 1] + 1
        after[-1] = 0
        before = 1 - 2 * self.count[: top + 1]
        cost = np.where(self.count[: top + 1] > 0, after + before, np.iinfo(np.int64).max)
        cost[0] = after[0]
        return top - int(np.argmin(cost[::-1]))

    def add(self, key, ids: bytes) -> Iterator[tuple]:
        total, at, full = len(ids) // 4, 0, 4 * self.window
        while len(ids) - 4 * at >= full:
            yield from self._emit([(key, at, ids[4 * at : 4 * at + full], total)])
            at += self.window
        rest = ids[4 * at :]
        size = len(rest) // 4
        if not size:
            return
        level = self.level_for(size)
        pieces = self.open[level].pop() if level else []
        if level:
            self.count[level] -= 1
        pieces.append((key, at, rest, total))
        if level + size == self.window:
            yield from self._emit(pieces)
        else:
            self.open[level + size].append(pieces)
            self.count[level + size] += 1

    def finish(self) -> Iterator[tuple]:
        left = [(level, p) for level in range(self.window - 1, 0, -1) for p in self.open[level]]
        self.open = [[] for _ in range(self.window)]
        self.count[:] = 0
        lo, hi = 0, len(left) - 1
        while lo < hi:
            level, pieces = left[lo]
            while level < self.window and lo < hi:
                give, source = left[hi]
                key, start, ids, total = source.pop()
                take = min(self.window - level, len(ids) // 4)
                cut = len(ids) - 4 * take
                pieces.append((key, start + cut // 4, ids[cut:], total))
                if cut:
                    source.append((key, start, ids[:cut], total))
                level, give = level + take, give - take
                left[hi] = (give, source)
                if not give:
                    hi -= 1
            left[lo] = (level, pieces)
            if level == self.window:
                yield from self._emit(pieces)
                lo += 1
        if lo == hi:
            level, pieces = left[lo]
            for bit in range(level.bit_length() - 1, -1, -1):
                need, run = level & (1 << bit), []
                while need:
                    key, start, ids, total = pieces.pop(0)
                    take = min(need, len(ids) // 4)
                    run.append((key, start, ids[: 4 * take], total))
                    if 4 * take < len(ids):
                        pieces.insert(0, (key, start + take, ids[4 * take :], total))
                    need -= take
                if run:
                    yield from self._emit(run)


PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def pack_documents(docs: DataFrame, vocab: str, end_id: int = 1, window: int = WINDOW, with_ids: bool = False) -> DataFrame:
    """Pieces of all documents, each id in exactly one; ``with_ids`` adds the ids as bytes.

    Null or empty texts are documents of the end id alone; null and repeated
    ids are kept as they are; other columns are not read; an empty table gives
    no pieces.
    """
    names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"] + ["ids"] * with_ids
    schema = pa.schema([(n, pa.binary() if n == "ids" else pa.int64()) for n in names])
    end = end_id.to_bytes(4, "little")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from dupflow.llm.hf_tokens import encoder

        encode, packer = encoder(vocab).encode, SumOfSquaresPacker(window, TaskContext.get().partitionId() * PER_PARTITION)
        made: list[list] = [[] for _ in names]

        def keep(pieces: Iterator[tuple]) -> None:
            for key, start, ids, total, sequence, offset in pieces:
                row = (key, start, len(ids) // 4, zlib.crc32(ids), total, sequence, offset, ids)
                for column, value in zip(made, row, strict=False):
                    column.append(value)

        def flush() -> pa.RecordBatch:
            batch = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(made, schema, strict=True)], schema=schema)
            for c in made:
                c.clear()
            return batch

        for batch in batches:
            ids, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lo, hi in batches_by_size(texts, ENCODER_BATCH):
                for doc_id, packed in zip(ids[lo:hi], encode(texts[lo:hi]), strict=True):
                    keep(packer.add(doc_id, packed + end))
                if len(made[0]) > 5_000:
                    yield flush()
        keep(packer.finish())
        if made[0]:
            yield flush()

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    return rows.mapInArrow(pack, PIECE + ", ids binary" * with_ids)
