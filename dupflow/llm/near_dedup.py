"""Near-duplicate classes: probability MinHash over shingles, banding, exact verification.

Every distinct shingle of five words emits arrivals of a Poisson process with
its weight as rate, each arrival in a random register; a register keeps the
element that arrives first.  An element stops as soon as its time is past every
register.  Registers of two texts agree with the probability Jaccard of their
weights.  All shingles of a text weigh the same here, however often it repeats
them, so that this is the Jaccard similarity of the sets, which is what pairs
are verified by.  Bands of registers give buckets; inside
a bucket texts are compared with representatives, never all with all
(:mod:`dupflow.llm.groups`).  What a crowded bucket holds after three rounds is
dealt anew by bands of twice as many registers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dupflow.llm.chunks import batches_by_size
from dupflow.llm.common import materialize, text_or_empty
from dupflow.llm.components import components
from dupflow.llm.groups import linked

SHINGLE, SIMILARITY = 5, 0.8
BANDS, ROWS = 20, 4
#: All registers; the bands use the first of them, the estimate uses four bits of each.
REGISTERS = 192
#: Pairs whose estimate is lower are not read in full: 6.9 standard errors below the wanted similarity.
DOUBTFUL = 0.6

_GOLD = np.uint64(0x9E3779B97F4A7C15)
_BASE = np.uint64(0x100000001B3)
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def _mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_POWERS = _BASE ** np.arange(64, dtype=np.uint64)


def _powers(n: int) -> np.ndarray:
    global _POWERS
    if n > len(_POWERS):
        _POWERS = np.cumprod(np.concatenate([[np.uint64(1)], np.full(2 * n, _BASE)]), dtype=np.uint64)
    return _POWERS


def word_hashes(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all lower-case words between ASCII white space, and each text's first word in them."""
    raw = [t.lower().encode() for t in texts]
    b = np.frombuffer(b"\n".join([*raw, b""]), np.uint8)
    solid = ~_SPACE[b]
    edge = np.diff(np.concatenate([[False], solid, [False]]).astype(np.int8))
    first, last = np.nonzero(edge == 1)[0], np.nonzero(edge == -1)[0]
    ends = np.cumsum([len(r) + 1 for r in raw])
    if not len(first):
        return np.zeros(0, np.uint64), np.zeros(len(texts) + 1, np.int64)
    lengths = last - first
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    place = np.arange(int(lengths.sum())) - np.repeat(starts, lengths)
    terms = (b[solid].astype(np.uint64) + np.uint64(1)) * _powers(int(lengths.max()))[place]
    hashes = _mix(np.add.reduceat(terms, starts) + lengths.astype(np.uint64) * _GOLD)
    return hashes, np.concatenate([[0], np.searchsorted(first, ends)])


def shingles(words: np.ndarray) -> np.ndarray:
    """Hashes of the runs of five words of one text; a shorter text has its whole as one run, an empty one none."""
    n = len(words)
    if n == 0:
        return words
    k = min(n, SHINGLE)
    out = np.full(n - k + 1, np.uint64(k))
    for j in range(k):
        out = _mix(out + words[j : n - k + 1 + j]) * _GOLD
    return out


def signatures(elements: np.ndarray, weights: np.ndarray, owner: np.ndarray, n: int, m: int = REGISTERS) -> np.ndarray:
    """First-arrived element of each of ``m`` registers of each of ``n`` texts (every text has an element)."""
    time = np.full(n * m, np.inf)
    winner = np.zeros(n * m, np.uint64)
    e, w, d = elements, weights.astype(np.float64), owner
    x, turn = np.zeros(len(e)), 0
    while len(e):
        turn += 1
        r = _mix(e + np.uint64(turn * int(_GOLD) & 0xFFFFFFFFFFFFFFFF))
        x = x - np.log(((r >> np.uint64(11)).astype(np.float64) + 1) / (1 << 53)) / w
        place = d * m + (_mix(r ^ _GOLD) % np.uint64(m)).astype(np.int64)
        np.minimum.at(time, place, x)
        won = time[place] == x
        winner[place[won]] = e[won]
        alive = x < time.reshape(n, m).max(1)[d]
        e, w, d, x = e[alive], w[alive], d[alive], x[alive]
    return winner.reshape(n, m)


def bands(sig: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A bucket number for each band of registers, and one for each band and as many further registers."""
    parts = sig[:, : 2 * BANDS * ROWS].reshape(len(sig), 2, BANDS, ROWS)
    h = np.arange(BANDS, dtype=np.uint64)[None, :] * _GOLD
    out = []
    for parcel in (0, 1):
        for j in range(ROWS):
            h = _mix(h + parts[:, parcel, :, j]) * _GOLD
        out.append(h)
    return out[0], out[1]


def nibbles(sig: np.ndarray) -> np.ndarray:
    """Four bits of each register, sixteen registers to a number."""
    low = (_mix(sig) & np.uint64(15)).reshape(len(sig), -1, 16)
    return (low << (np.arange(16, dtype=np.uint64) * np.uint64(4))).sum(2, dtype=np.uint64)


def estimate(a: Column, b: Column) -> Column:
    """Similarity estimated from the numbers of :func:`nibbles` of two texts: registers that agree, less chance."""
    differ = F.lit(0)
    for i in range(REGISTERS // 16):
        x = a[i].bitwiseXOR(b[i])
        x = x.bitwiseOR(F.shiftrightunsigned(x, 1))
        x = x.bitwiseOR(F.shiftrightunsigned(x, 2)).bitwiseAND(F.lit(0x1111111111111111))
        differ = differ + F.bit_count(x)
    return 1 - differ / REGISTERS * 16 / 15


def _grouped(texts: list[str]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(place, words, shingle hashes) of each text."""
    words, first = word_hashes(texts)
    for i in range(len(texts)):
        w = words[first[i] : first[i + 1]]
        yield i, w, shingles(w)


SKETCH = "doc_id long, rid long, node binary, buckets array<struct<bucket:long,deep:long>>, bits array<long>"


def sketch(docs: DataFrame) -> DataFrame:
    """(doc_id, rid, node, buckets, bits): rid tells texts with equal ids apart, node is the same for texts of the same words."""
    kind = pa.list_(pa.struct([("bucket", pa.int64()), ("deep", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(2).to_pylist()
            for lo, hi in batches_by_size(texts):
                nodes, elements, weights, owners, has = [], [], [], [], []
                for i, w, s in _grouped(texts[lo:hi]):
                    nodes.append(xxhash.xxh3_128_digest(w.tobytes()) if len(w) else xxhash.xxh3_128_digest(texts[lo + i].encode()))
                    if len(s):
                        e = np.unique(s)
                        elements.append(e)
                        weights.append(np.ones(len(e)))
                        owners.append(np.full(len(e), len(has)))
                        has.append(i)
                found: list = [[] for _ in nodes]
                bits: list = [[] for _ in nodes]
                if has:
                    sig = signatures(np.concatenate(elements), np.concatenate(weights), np.concatenate(owners), len(has))
                    wide, deep = bands(sig)
                    for i, row, fine, few in zip(has, wide.view(np.int64).tolist(), deep.view(np.int64).tolist(), nibbles(sig).view(np.int64), strict=True):
                        found[i], bits[i] = [{"bucket": x, "deep": y} for x, y in zip(row, fine, strict=True)], few
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), batch.column(1).slice(lo, hi - lo), pa.array(nodes, pa.binary()), pa.array(found, kind), pa.array(bits, pa.list_(pa.int64()))], names=["doc_id", "rid", "node", "buckets", "bits"])

    t = text_or_empty()
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(t).alias("rid"), t.alias("text")).mapInArrow(run, SKETCH)


def shingle_sets(rows: DataFrame) -> DataFrame:
    """(node, set) from (node, text): the distinct shingle hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(1).to_pylist()
            for lo, hi in batches_by_size(texts):
                sets = [np.unique(s).view(np.int64) for _, _, s in _grouped(texts[lo:hi])]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, hi - lo), pa.array(sets, pa.list_(pa.int64()))], names=["node", "set"])

    return rows.select("node", "text").mapInArrow(run, "node binary, set array<long>")


def _alike(a: Column, b: Column, similarity: float) -> Column:
    """Whether two sets have at least the given Jaccard similarity; sets of too different sizes are not intersected."""
    both = F.size(a) + F.size(b)
    sizes = F.least(F.size(a), F.size(b)) >= similarity * F.greatest(F.size(a), F.size(b))
    # common >= similarity * (both - common), with the intersection taken once
    common = F.transform(F.array(F.size(F.array_intersect(a, b))), lambda n: n >= similarity * (both - n))[0]
    return sizes & common


def _verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs (a, b, ...) whose shingle sets have at least the given Jaccard similarity."""
    left = sets.select(F.col("node").alias("a"), F.col("set").alias("sa"))
    right = sets.select(F.col("node").alias("b"), F.col("set").alias("sb"))
    return pairs.join(left, "a").join(right, "b").where(_alike(F.col("sa"), F.col("sb"), similarity))


def classes(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """(doc_id, rid, row, node, comp, class_id) for every row: class_id is the least doc_id of the class.

    Texts of the same words, case and white space aside, are one node and one
    class; different nodes are linked by verified similarity, and classes are
    the connected sets.  Texts without words are in one class only with equal
    texts.  Null texts are empty; null ids stay and are never a class id unless
    the class has no other; repeated rows are rows of one class, each with a
    ``row`` of its own; texts of any length are read whole; other columns are
    not read; an empty table gives no rows.
    """
    sketches = materialize(sketch(docs).withColumn("row", F.monotonically_increasing_id()), "sketches")
    each = sketches.select("node", F.explode("buckets").alias("x")).select("node", "x.bucket", "x.deep").distinct()
    full = each.groupBy("bucket").agg(F.count("*").alias("n")).where(F.col("n") > 1).select("bucket")
    marks = sketches.select("node", "bits").dropDuplicates(["node"])
    members = materialize(each.join(full, "bucket").join(marks, "node"), "members")
    comps = None
    if not members.isEmpty():
        t = text_or_empty()
        wanted = members.select("node").distinct().join(sketches.groupBy("node").agg(F.min("rid").alias("rid")), "node")
        texts = docs.select(t.alias("text"), F.xxhash64(t).alias("rid")).join(wanted, "rid").dropDuplicates(["node"])
        sets = materialize(shingle_sets(texts), "shingle-sets")
        least = DOUBTFUL - SIMILARITY + similarity
        links = linked(members, lambda x, y: estimate(x("bits"), y("bits")) >= least, lambda pairs: _verified(pairs, sets, similarity), lambda rest: rest.withColumn("bucket", F.col("deep")), whole=(sets, lambda x, y: _alike(x("set"), y("set"), similarity)))
        comps = components(links)
    named = sketches if comps is None else sketches.join(comps, "node", "left")
    rows = named.select("doc_id", "rid", "row", "node", (F.col("node") if comps is None else F.coalesce("comp", "node")).alias("comp"))
    first = rows.groupBy("comp").agg(F.min("doc_id").alias("class_id"))
    return rows.join(first, "comp").select("doc_id", "rid", "row", "node", "comp", "class_id")


def first_rows(c: DataFrame) -> DataFrame:
    """The one row of each class that stays: the least doc_id (a null id only if there is no other), then the least hash of the text, then any row."""
    order = F.struct(F.col("doc_id").isNull().alias("null"), "doc_id", "rid", "row")
    return c.groupBy("comp").agg(F.min(order).alias("first")).select("comp", "first.doc_id", "first.rid", "first.row")


def class_digest(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """One row for each document: its class id and whether it is the one that stays.

    Of each class exactly one row stays, the one that :func:`keep_one` keeps,
    also among rows of equal ids; odd rows are as in :func:`classes`.
    """
    c = classes(docs, similarity)
    chosen = first_rows(c).select(F.col("row").alias("first"))
    return c.join(chosen, c["row"] == chosen["first"], "left").select("doc_id", "class_id", F.col("first").isNotNull().alias("stays"))


def keep_one(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """One document of each class, that of :func:`first_rows`; all columns stay.

    Null texts are empty texts and keep their null; of repeated rows one stays;
    an empty table gives none.
    """
    key = lambda df, i, r: df.select("*", F.col(i).isNull().alias("__no_id"), F.coalesce(F.col(i).cast("long"), F.lit(0)).alias("__id"), r.alias("__rid"))
    chosen = key(first_rows(classes(docs, similarity)), "doc_id", F.col("rid")).select("__no_id", "__id", "__rid")
    rows = key(docs, "doc_id", F.xxhash64(text_or_empty()))
    names = ["__no_id", "__id", "__rid"]
    return rows.join(chosen, names, "left_semi").dropDuplicates(names).select(*docs.columns)
