"""Nearest neighbours by largest inner product: a block matrix join over int8 tiles.

Each vector is stored as int8 with its own scale. A product of two int8 tiles (whole numbers,
exact in single precision while ``127 * 127 * width < 2**24``, else in double) gives
approximate inner products together with a bound on the rounding error. A pair survives if its upper
bound reaches the k-th largest lower bound that its query has seen; survivors are recomputed in double from the
original vectors and merged into each query's heap. The bounds are proven, so the
result is exact; int8 only saves work.

The k best of each query and lane are merged by a second, small top-k. Vectors that are null, zero, or hold
null or non-finite components take no part; neither do rows without id. Rows that
repeat an id are candidates of their own, but never of their own id; of query rows that repeat an id the one with the
least vector is asked. Fewer candidates than ``k``: all.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treefix.llm.shared import tidied
from treefix.llm.vectors import asked, blocks, cells, grid, storage, usable

K, QUERY_ROWS, CANDIDATE_ROWS, SIDE_BLOCKS, LANE_BLOCKS = 20, 1024, 4096, 4, 16
FOUND = "query_id bigint, vec_id bigint, score double"


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """int8 rows and their scales: ``x`` is within half a scale of ``q * scale``."""
    scale = np.abs(x).max(axis=1) / 127.0
    return np.rint(x / np.maximum(scale, 5e-324)[:, None]).clip(-127, 127).astype(np.int8), scale


def exact_products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row-wise inner products in double, summed from the first component to the last."""
    out = np.zeros(len(a))
    for d in range(a.shape[1]):
        out += a[:, d] * b[:, d]
    return out


class Heaps:
    """The k best (score, smaller id first) of each query of a block."""

    def __init__(self, ids: np.ndarray, k: int):
        self.ids, self.k = ids, k
        self.query = np.zeros(0, dtype=np.int64)
        self.vec = np.zeros(0, dtype=np.int64)
        self.score = np.zeros(0)
        self.floor = np.full(len(ids), -np.inf)  # the k-th best so far

    def push(self, query: np.ndarray, vec: np.ndarray, score: np.ndarray) -> None:
        q, v, s = np.concatenate([self.query, query]), np.concatenate([self.vec, vec]), np.concatenate([self.score, score])
        order = np.lexsort((v, -s, q))
        q, v, s = q[order], v[order], s[order]
        first = np.searchsorted(q, np.arange(len(self.ids)))
        keep = np.arange(len(q)) - first[q] < self.k
        self.query, self.vec, self.score = q[keep], v[keep], s[keep]
        last = first + self.k - 1
        full = (last < len(q)) & (q[np.minimum(last, max(len(q) - 1, 0))] == np.arange(len(self.ids))) if len(q) else np.zeros(len(self.ids), dtype=bool)
        self.floor[full] = s[last[full]]

    def batch(self) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(self.ids[self.query]), pa.array(self.vec), pa.array(self.score)], names=["query_id", "vec_id", "score"])


def _search(k: int, q_kind: str, c_kind: str):
    def tile(heaps: Heaps, q: np.ndarray, c_ids: np.ndarray, c: np.ndarray) -> None:
        width = q.shape[1]
        kind = np.float32 if 127 * 127 * width < 1 << 24 else np.float64
        (qi, qs), (ci, cs) = quantise(q), quantise(c)
        product = (qi.astype(kind) @ ci.astype(kind).T).astype(np.float64)
        unit = qs[:, None] * cs[None, :]
        q_sum, c_sum = (np.abs(x.astype(np.int32)).sum(axis=1) for x in (qi, ci))
        error = unit * (0.5 * q_sum[:, None] + 0.5 * c_sum[None, :] + 0.25 * width) * (1 + 1e-9)
        product *= unit
        own = heaps.ids[:, None] == c_ids[None, :]
        low = np.where(own, -np.inf, product - error)
        floor = heaps.floor.copy()
        if low.shape[1] >= k:
            floor = np.maximum(floor, np.partition(low, low.shape[1] - k, axis=1)[:, low.shape[1] - k])
        row, col = np.nonzero((product + error >= floor[:, None]) & ~own)
        for at in range(0, len(row), 1 << 18):
            r, j = row[at : at + (1 << 18)], col[at : at + (1 << 18)]
            heaps.push(r, c_ids[j], exact_products(q[r], c[j]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, asked_of = None, []  # the cell, and its query blocks with their heaps
        for cell, side, ids, matrix in cells(batches):
            if cell != held:
                yield from (heaps.batch() for heaps, _ in asked_of if len(heaps.query))
                held, asked_of = cell, []
            ids = np.frombuffer(ids, dtype="<i8")
            rows = np.frombuffer(matrix, dtype=c_kind if side else q_kind).astype(np.float64).reshape(len(ids), -1)
            if not side:
                asked_of.append((Heaps(ids, k), rows))
                continue
            for heaps, q in asked_of:
                tile(heaps, q, ids, rows)
        yield from (heaps.batch() for heaps, _ in asked_of if len(heaps.query))

    return run


def merged(found: DataFrame, k: int) -> DataFrame:
    """The k best rows of each query, ranked from 1; ties go to the smaller id. ``k`` rows of each
    query and lane come in."""
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), F.asc("vec_id"))
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def nearest(queries: DataFrame, candidates: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", k: int = K) -> DataFrame:
    """``query_id, rank, vec_id, score``: the k candidates of largest inner product for each query row."""
    q_kind, c_kind = storage(queries, vec_col), storage(candidates, vec_col)
    q = blocks(asked(usable(queries, id_col, vec_col, False)), QUERY_ROWS, lambda m: m.astype(q_kind))
    c = blocks(usable(candidates, id_col, vec_col, False), CANDIDATE_ROWS, lambda m: m.astype(c_kind))
    return merged(grid(q, c, SIDE_BLOCKS, LANE_BLOCKS).mapInArrow(tidied(_search(k, q_kind, c_kind)), FOUND), k)
