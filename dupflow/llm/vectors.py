"""Exact inner-product top-k by a vector-approximation file.

Every vector is stored twice: as one small cell number for each component, and
exactly.  A query scans the cells for an upper and a lower bound of each score,
then reads exact vectors in the order of their upper bounds until the k-th
result beats every bound that is left.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from dupflow.llm.common import materialize

#: Cells for each component.
CELLS = 64

INDEX = "uid long, vec_id long, n int, cells binary, exact binary"


def integer_vectors(df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 256) -> DataFrame:
    """(vec_id, ints): floor(scale * x) for each component; rows that hold null or non-finite components are left out."""
    ok = F.col(vec_col).isNotNull() & F.forall(vec_col, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    ints = F.transform(vec_col, lambda x: F.floor(x.cast("double") * scale).cast("long"))
    return df.where(ok).select(F.col(id_col).cast("long").alias("vec_id"), ints.alias("ints"))


def build_index(rows: DataFrame) -> tuple[DataFrame, dict]:
    """The approximation table and its grid: for each vector length, each component's least value and cell width.

    The grid is as large as a vector, whatever the number of rows.
    """
    each = rows.select(F.size("ints").alias("n"), F.posexplode("ints").alias("pos", "v"))
    grid: dict[int, tuple[np.ndarray, np.ndarray]] = {}
    ends = sorted(tuple(r) for r in each.groupBy("n", "pos").agg(F.min("v").alias("lo"), F.max("v").alias("hi")).collect())
    for n in {e[0] for e in ends}:
        lo = np.array([e[2] for e in ends if e[0] == n], np.float64)
        hi = np.array([e[3] for e in ends if e[0] == n], np.float64)
        grid[n] = (lo, (hi - lo + 1) / CELLS)

    def approximate(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ns, cells, exact = [], [], []
            for v in batch.column(2).to_pylist():
                a = np.array(v, np.int64)
                ns.append(len(a))
                exact.append(a.tobytes())
                if len(a):
                    lo, width = grid[len(a)]
                    cells.append(np.clip((a - lo) // width, 0, CELLS - 1).astype(np.uint8).tobytes())
                else:
                    cells.append(b"")
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(ns, pa.int32()), pa.array(cells, pa.binary()), pa.array(exact, pa.binary())], names=["uid", "vec_id", "n", "cells", "exact"])

    numbered = rows.select(F.monotonically_increasing_id().alias("uid"), "vec_id", "ints")
    return materialize(numbered.mapInArrow(approximate, INDEX), "vector-cells"), grid


class _Best:
    """The k best (score, vec_id) of one query; smaller ids win ties, null ids lose them."""

    __slots__ = ("k", "rows")

    def __init__(self, k: int):
        self.k, self.rows = k, []

    def floor(self) -> float:
        return self.rows[-1][0] if len(self.rows) == self.k else -np.inf

    def offer(self, scores, ids) -> None:
        rows = self.rows + [(s, i) for s, i in zip(scores, ids, strict=True)]
        rows.sort(key=lambda r: (-r[0], r[1] is None, r[1] or 0))
        self.rows = rows[: self.k]


def _search_block(index: DataFrame, grid: dict, block: list[tuple], k: int) -> DataFrame:
    """Each partition's own k best for each query of the block (query number, vec_id, score)."""
    by_n: dict[int, list[int]] = {}
    for q, (_, _, n, _) in enumerate(block):
        by_n.setdefault(n, []).append(q)
    exact_q = {n: np.stack([np.frombuffer(block[q][3], np.int64) for q in qs]) for n, qs in by_n.items()}
    uids = [b[0] for b in block]

    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = [_Best(k) for _ in uids]
        for batch in batches:
            n_of = np.asarray(batch.column(2))
            uid, vec = np.asarray(batch.column(0)), batch.column(1).to_pylist()
            cells, exact = batch.column(3), batch.column(4)
            for n in np.unique(n_of).tolist():
                if n not in by_n:
                    continue
                for lo in range(0, int((n_of == n).sum()), 4096):
                    rows = np.nonzero(n_of == n)[0][lo : lo + 4096]
                    take = pa.array(rows)
                    lows, width = grid.get(n, (np.zeros(0), np.zeros(0)))
                    mid = lows + (np.frombuffer(b"".join(cells.take(take).to_pylist()), np.uint8).reshape(len(rows), n) + 0.5) * width
                    full = np.frombuffer(b"".join(exact.take(take).to_pylist()), np.int64).reshape(len(rows), n)
                    for at in range(0, len(by_n[n]), 256):
                        _refine(exact_q[n][at : at + 256], by_n[n][at : at + 256], uids, mid, width / 2, full, rows, uid, vec, best, k)
        out = [(q, i, int(s)) for q, b in enumerate(best) for s, i in b.rows]
        cols = list(zip(*out, strict=True)) if out else [[], [], []]
        yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64())], names=["q", "vec_id", "score"])

    return index.select("uid", "vec_id", "n", "cells", "exact").mapInArrow(search, "q int, vec_id long, score long")


def _refine(queries, numbers, uids, mid, half, full, rows, uid, vec, best, k) -> None:
    """Bounds of all pairs from the cells, then exact scores in the order of upper bounds."""
    q = queries.astype(np.float64)
    middle = q @ mid.T
    slack = np.abs(q) @ half
    slack = (slack + 1e-9 * (1 + np.abs(middle).max(initial=0)))[:, None]
    for j, number in enumerate(numbers):
        own = uid[rows] != uids[number]
        upper = np.where(own, middle[j] + slack[j], -np.inf)
        floor = best[number].floor()
        if len(rows) > k:  # k candidates besides the query's own row score this at least
            floor = max(floor, float(np.partition(np.where(own, middle[j] - slack[j], -np.inf), -k)[-k]))
        some = np.nonzero(own & (upper >= floor))[0]
        some = some[np.argsort(-upper[some], kind="stable")]
        for at in range(0, len(some), 16):
            part = some[at : at + 16]
            if upper[part[0]] < best[number].floor():
                break
            best[number].offer((full[part] @ queries[j]).tolist(), [vec[rows[x]] for x in part])


def top_k(df: DataFrame, is_query: Column, k: int = 5, block: int = 4096, **how) -> DataFrame:
    """Each query's k best scores over all rows but its own: query_id, rank, vec_id, score.

    ``is_query`` is a condition on vec_id.  Queries are taken in blocks of
    ``block`` rows, the only vectors that ever reach the driver; every block
    scans the whole index.  Vectors of other lengths than the query's are not
    compared.  Rows with equal ids are rows of their own; a null vec_id can be
    found but is no query and loses ties.  Fewer than k candidates give all of
    them; an empty table gives none.
    """
    index, grid = build_index(integer_vectors(df, **how))
    held, results, spark = [], [], df.sparkSession
    several = False

    def flush() -> None:
        found = _search_block(index, grid, list(held), k)
        ids = spark.createDataFrame([(q, h[1]) for q, h in enumerate(held)], "q int, query_id long")
        order = Window.partitionBy("q").orderBy(F.desc("score"), F.asc_nulls_last("vec_id"))
        ranked = found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).join(F.broadcast(ids), "q")  # ids: one row a query of the block
        out = ranked.select("query_id", "rank", "vec_id", "score")
        results.append(materialize(out, "vector-results") if several else out)
        held.clear()

    for r in index.where(is_query).select("uid", "vec_id", "n", "exact").toLocalIterator():
        if len(held) == block:
            several = True
            flush()
        held.append((r["uid"], r["vec_id"], r["n"], bytes(r["exact"])))
    if held:
        flush()
    if not results:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    out = results[0]
    for x in results[1:]:
        out = out.unionAll(x)
    return out
