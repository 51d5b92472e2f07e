"""Byte-level encoding by ranks in two tiers, and decoding.

Tier one: a minimal perfect hash over the vocabulary resolves a pre-token that
is itself an entry.  Tier two: any other pre-token becomes a doubly linked list
of bytes, and a heap of (rank, place) joins the lowest-ranked neighbours first,
leftmost on ties, until no neighbours form an entry.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dupflow.llm.chunks import ChunkEncoder, ENCODER_BATCH, batches_by_size, simple_words
from dupflow.llm.common import text_or_empty
from dupflow.llm.hf_tokens import little_endian


class MinimalPerfectHash:
    """Hash-and-displace over ``keys``: n keys fill exactly n slots; a stored key rejects strangers."""

    def __init__(self, keys: list[bytes], per_bucket: int = 2):
        n = self.n = len(keys)
        self.buckets = max(1, n // per_bucket)
        groups: list[list[tuple[int, bytes]]] = [[] for _ in range(self.buckets)]
        for k in keys:
            h = xxhash.xxh3_64_intdigest(k)
            groups[h % self.buckets].append((h, k))
        self.shift = [0] * self.buckets
        self.keys: list[bytes] = [b""] * n
        used = bytearray(n)
        for b in sorted(range(self.buckets), key=lambda b: -len(groups[b])):
            group = groups[b]
            if len(group) < 2:
                break
            d = 1
            while True:
                slots = {self._slot(h, d) for h, _ in group}
                if len(slots) == len(group) and not any(used[s] for s in slots):
                    break
                d += 1
            self.shift[b] = d
            for h, k in group:
                s = self._slot(h, d)
                used[s], self.keys[s] = 1, k
        free = iter([s for s in range(n) if not used[s]])
        for b, group in enumerate(groups):
            if len(group) == 1:
                s = next(free)
                self.shift[b], self.keys[s] = -1 - s, group[0][1]

    def _slot(self, h: int, d: int) -> int:
        x = (h + d * 0x9E3779B97F4A7C15) & 0xFFFFFFFFFFFFFFFF
        x = ((x ^ (x >> 31)) * 0xBF58476D1CE4E5B9) & 0xFFFFFFFFFFFFFFFF
        return (x ^ (x >> 29)) % self.n

    def slot(self, key: bytes) -> int:
        """The key's slot, or -1 for a key outside the set."""
        if not self.n:
            return -1
        h = xxhash.xxh3_64_intdigest(key)
        d = self.shift[h % self.buckets]
        s = -1 - d if d < 0 else self._slot(h, d)
        return s if self.keys[s] == key else -1


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(word): int(rank) for word, rank in map(bytes.split, f)}


class RankCoder:
    """Encodes and decodes by a rank file and a pre-token pattern."""

    def __init__(self, path: str, pattern: str):
        self.ranks = read_ranks(path)
        self.hash = MinimalPerfectHash(list(self.ranks))
        self.rank_of_slot = [self.ranks[k] for k in self.hash.keys]
        self.words = [b""] * (max(self.ranks.values(), default=-1) + 1)
        for word, rank in self.ranks.items():
            self.words[rank] = word
        # the white space of the Unicode property, as the reference engine has it
        self.find = regex.compile(pattern.replace(r"\S", r"\P{White_Space}").replace(r"\s", r"\p{White_Space}")).findall
        self.memo: dict[str, bytes] = {}
        self.chunks = ChunkEncoder(self._encode_chunks)

    def merge(self, word: bytes) -> list[int]:
        """Ids of one pre-token that is not an entry."""
        ranks, n = self.ranks, len(word)
        part: list[bytes | None] = [word[i : i + 1] for i in range(n)]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(r, i, word[i : i + 2]) for i in range(n - 1) if (r := ranks.get(word[i : i + 2])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, joined = heapq.heappop(heap)
            left = part[i]
            j = after[i]
            if left is None or j >= n or len(left) + len(part[j]) != len(joined):
                continue  # one side has changed since
            part[i], part[j] = joined, None
            k = after[i] = after[j]
            if k < n:
                before[k] = i
                both = joined + part[k]
                if (r := ranks.get(both)) is not None:
                    heapq.heappush(heap, (r, i, both))
            h = before[i]
            if h >= 0:
                both = part[h] + joined
                if (r := ranks.get(both)) is not None:
                    heapq.heappush(heap, (r, h, both))
        return [ranks[p] for p in part if p is not None]

    def encode_word(self, word: bytes) -> list[int]:
        s = self.hash.slot(word)
        return [self.rank_of_slot[s]] if s >= 0 else self.merge(word)

    def _encode_chunks(self, chunks: list[str]) -> tuple[np.ndarray, np.ndarray]:
        memo = self.memo
        if len(memo) > 300_000:
            memo.clear()
        out = []
        for c in chunks:
            parts = []
            for w in simple_words(c) or self.find(c):
                if (packed := memo.get(w)) is None:
                    packed = memo[w] = little_endian(self.encode_word(w.encode()))
                parts.append(packed)
            out.append(b"".join(parts))
        return np.frombuffer(b"".join(out), "<u4"), np.fromiter(map(len, out), np.int64, len(out)) // 4

    def encode(self, texts: list[str]) -> list[bytes]:
        """Little-endian 32-bit id bytes of each whole text."""
        return self.chunks.encode(texts)

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.words.__getitem__, ids))


_CACHE: dict[tuple[str, str], RankCoder] = {}


def coder(path: str, pattern: str) -> RankCoder:
    """One coder for each worker process and rank file."""
    if (path, pattern) not in _CACHE:
        _CACHE[path, pattern] = RankCoder(path, pattern)
    return _CACHE[path, pattern]


def encode_texts(df: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id and its whole text's ids as an array; a null text has no ids; rows and null ids stay as they are."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = coder(path, pattern)
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for lo, hi in batches_by_size(texts, ENCODER_BATCH):
                ids = [np.frombuffer(x, "<i4") for x in c.encode(texts[lo:hi])]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(ids, pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).mapInArrow(run, "doc_id long, ids array<int>")


def decode_ids(df: DataFrame, path: str, pattern: str) -> DataFrame:
    """The inverse of :func:`encode_texts`: doc_id and the bytes that its ids stand for."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = coder(path, pattern)
        for batch in batches:
            data = [c.decode(x or []) for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(data, pa.binary())], names=["doc_id", "data"])

    return df.select("doc_id", "ids").mapInArrow(run, "doc_id long, data binary")


DIGEST = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def coding_digest(df: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encodes every whole text, decodes the ids again, and digests both in one pass.

    Null and empty texts have no ids and decode to no bytes; rows with null or
    repeated ids stay rows of their own; other columns are not read.
    """
    schema = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = coder(path, pattern)
        decimal = [str(i) for i in range(len(c.words))]
        for batch in batches:
            texts = batch.column(1).to_pylist()
            n, shas, datas = [], [], []
            for lo, hi in batches_by_size(texts, ENCODER_BATCH):
                for packed in c.encode(texts[lo:hi]):
                    ids = np.frombuffer(packed, "<u4").tolist()
                    n.append(len(ids))
                    shas.append(hashlib.sha256(",".join(map(decimal.__getitem__, ids)).encode()).hexdigest())
                    datas.append(hashlib.sha256(c.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(shas, pa.string()), pa.array(datas, pa.string())], schema=schema)

    return df.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text")).mapInArrow(run, DIGEST)
