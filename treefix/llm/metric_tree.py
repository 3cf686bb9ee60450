"""Exact top-k by inner product over M-trees, searched best first.

Vectors become whole numbers, ``floor(scale * x)``. Inner products are no metric, but with one more
component ``sqrt(m - |x|**2)``, ``m`` the largest squared norm of a tree, every stored
vector lies on one sphere, and ``|q|**2 + m - 2 <q, x>`` is the squared Euclidean distance to the query
(whose extra component is zero). The nearest vectors are then those of largest product.

Candidates are dealt to shards of bounded size, each a paged M-tree: an entry holds its routing
vector, its covering radius and its distance to the parent's routing vector; a leaf page
holds vectors and their distances to its routing vector. A query takes pages from a queue by the
least distance they may hold. The triangle inequality over the stored parent distances rules
entries and vectors out before any distance to them is computed. Bounds carry a slack for rounding,
products are whole numbers, so the result is exact, ties to the smaller id.

Vectors that are null or hold null or non-finite components, and rows without id, take no part. Zero
vectors do. Products must fit in 64 bits. Fewer candidates than ``k``: all. Of query rows that repeat an id the one with the least vector is asked.
"""

from __future__ import annotations

import heapq
import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.llm.block_neighbours import merged
from treefix.llm.shared import tidied
from treefix.llm.vectors import BLOCK, asked, blocks, cells, grid, usable

K, SCALE, PAGE, FANOUT, SHARD_ROWS, QUERY_ROWS, SIDE_BLOCKS, LANE_BLOCKS = 20, 64, 512, 16, 16384, 512, 8, 4
SLACK = 1e-6


class MetricTree:
    """A paged M-tree over whole-number rows. Nodes lie level by level, so the
    children of a node, and the rows of a leaf, are slices."""

    FIELDS = ("ids", "rows", "reach", "lift", "to_parent", "route", "route_lift", "radius", "above", "first", "last", "leaf", "top")

    def __init__(self, **fields):
        self.__dict__.update(fields)

    @classmethod
    def build(cls, ids: np.ndarray, rows: np.ndarray, page: int = PAGE, fanout: int = FANOUT) -> MetricTree:
        norms = (rows * rows).sum(axis=1)
        top = int(norms.max(initial=0))
        points = np.concatenate([rows, np.sqrt(np.maximum(top - norms, 0))[:, None]], axis=1).astype(np.float64)
        rng = np.random.default_rng(len(ids))
        order = np.arange(len(ids))
        nodes = {n: [] for n in ("centre", "radius", "above", "first", "last", "leaf")}
        member_dist = np.zeros(len(ids))

        def far(members: np.ndarray, centre: int) -> np.ndarray:
            return np.sqrt(((points[members] - points[centre]) ** 2).sum(axis=1))

        queue = [(0, len(ids), int(np.argmin(((points - points.mean(axis=0)) ** 2).sum(axis=1))), 0.0)]
        while queue:  # a level at a time: (start, end) in `order`, routing row, distance to the parent's
            following = []
            for start, end, centre, above in queue:
                members = order[start:end]
                dist = far(members, centre)
                nodes["centre"].append(centre)
                nodes["radius"].append(float(dist.max(initial=0.0)))
                nodes["above"].append(above)
                if end - start <= page:
                    nodes["leaf"].append(True)
                    nodes["first"].append(start)
                    nodes["last"].append(end)
                    member_dist[start:end] = dist
                    continue
                count = min(fanout, -(-(end - start) // (page // 2)))
                seeds = members[rng.choice(len(members), count, replace=False)]
                all_far = ((points[members] ** 2).sum(axis=1)[:, None] - 2 * points[members] @ points[seeds].T) + (points[seeds] ** 2).sum(axis=1)[None, :]
                group = all_far.argmin(axis=1)
                if (np.bincount(group, minlength=count) > 0).sum() < 2:  # equal rows: halves by position
                    group = np.arange(len(members)) * 2 // len(members)
                by = np.argsort(group, kind="stable")
                order[start:end] = members[by]
                sizes = np.bincount(group, minlength=count)
                nodes["leaf"].append(False)
                nodes["first"].append(-1)
                nodes["last"].append(len(nodes["leaf"]) - 1)  # whose children they are, set below
                at = start
                for g in np.flatnonzero(sizes):
                    child = int(seeds[g])
                    following.append((at, at + int(sizes[g]), child, float(far(np.array([child]), centre)[0]), len(nodes["leaf"]) - 1))
                    at += int(sizes[g])
            base = len(nodes["leaf"])
            for k, (*_, parent) in enumerate(following):
                if nodes["first"][parent] < 0:
                    nodes["first"][parent] = base + k
                nodes["last"][parent] = base + k + 1
            queue = [f[:4] for f in following]
        centre = np.array(nodes["centre"])
        reach = int(np.abs(rows).max(initial=0)) * max(rows.shape[1], 1)
        return cls(
            ids=ids[order], rows=rows[order].astype(np.float64) if reach < 1 << 53 else rows[order], reach=np.array(min(reach, 1 << 62)), lift=points[order, -1], to_parent=member_dist, route=rows[centre], route_lift=points[centre, -1], radius=np.array(nodes["radius"]),
            above=np.array(nodes["above"]), first=np.array(nodes["first"]), last=np.array(nodes["last"]), leaf=np.array(nodes["leaf"]), top=np.array(top),
        )

    def dump(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, **{f: getattr(self, f) for f in self.FIELDS})
        return out.getvalue()

    @classmethod
    def load(cls, data: bytes) -> MetricTree:
        with np.load(io.BytesIO(data)) as held:
            return cls(**{f: held[f] for f in cls.FIELDS})

    def search(self, q_id: int, q: np.ndarray, k: int, heap: list[tuple[int, int]]) -> int:
        """Merges the tree's best rows into ``heap`` of (score, -id); how many products it computed."""
        q_norm, top = int((q * q).sum()), int(self.top)
        # whole numbers are exact in double below 2**53, and products of doubles are faster
        exact = self.rows.dtype == np.float64 and float(np.abs(q).max(initial=0)) * float(self.reach) < 1 << 53
        own = q.astype(np.float64) if exact else q
        if not exact and self.rows.dtype == np.float64:
            self.rows = self.rows.astype(np.int64)
        computed = 0

        def reach() -> float:
            """The distance beyond which no row can enter the heap."""
            return np.inf if len(heap) < k else np.sqrt(max(q_norm + top - 2 * heap[0][0], 0)) + SLACK

        def distances(products: np.ndarray) -> np.ndarray:
            return np.sqrt(np.maximum(q_norm + top - 2.0 * products, 0.0))

        root = float(distances(self.route[:1] @ q)[0])
        queue = [(max(root - float(self.radius[0]), 0.0), 0, root)]
        while queue:
            least, node, dist = heapq.heappop(queue)
            limit = reach()
            if least > limit:
                break
            first, last = int(self.first[node]), int(self.last[node])
            if self.leaf[node]:
                ruled_in = np.abs(self.to_parent[first:last] - dist) <= limit + SLACK
                count = int(np.count_nonzero(ruled_in))
                if not count:
                    continue
                computed += count
                if 4 * count >= 3 * (last - first):  # nearly all: without copying the page
                    products = self.rows[first:last] @ own
                    good = ruled_in if len(heap) < k else ruled_in & (products >= heap[0][0])
                    near, products = np.flatnonzero(good) + first, products[good]
                else:
                    near = np.flatnonzero(ruled_in) + first
                    products = self.rows[near] @ own
                    if len(heap) == k:
                        good = products >= heap[0][0]
                        near, products = near[good], products[good]
                for score, i in zip(products.astype(np.int64).tolist(), self.ids[near].tolist()):
                    if i == q_id:
                        continue
                    if len(heap) < k:
                        heapq.heappush(heap, (score, -i))
                    elif (score, -i) > heap[0]:
                        heapq.heapreplace(heap, (score, -i))
            else:
                near = np.flatnonzero(np.abs(self.above[first:last] - dist) - self.radius[first:last] <= limit + SLACK) + first
                if not len(near):
                    continue
                there = distances(self.route[near] @ q)
                computed += len(near)
                bound = np.maximum(there - self.radius[near], 0.0)
                for b, n, d in zip(bound.tolist(), near.tolist(), there.tolist()):
                    if b <= limit + SLACK:
                        heapq.heappush(queue, (b, n, d))
        return computed


def _index(page: int, fanout: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                ids, width = np.frombuffer(batch.column("ids")[i].as_py(), dtype="<i8"), batch.column("width")[i].as_py()
                tree = MetricTree.build(ids, np.frombuffer(batch.column("matrix")[i].as_py(), dtype="<i8").reshape(-1, width), page, fanout)
                rest = [batch.column(n).slice(i, 1) for n in ("width", "task", "turn")]
                yield pa.RecordBatch.from_arrays([batch.column("ids").slice(i, 1), pa.array([tree.dump()], pa.binary()), *rest], names=["ids", "matrix", "width", "task", "turn"])

    return run


def _search(k: int):
    def out(blocks_: list) -> pa.RecordBatch:
        flat = [(int(q), -i, s, 0 if n else products) for q_ids, _, heaps, work in blocks_ for q, heap, products in zip(q_ids, heaps, work) for n, (s, i) in enumerate(heap)]
        return pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in zip(*flat)] if flat else [pa.array([], pa.int64())] * 4, names=["query_id", "vec_id", "score", "products"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, asked_of = None, []  # the cell, and its query blocks with their heaps and how many products they took
        for cell, side, ids, matrix in cells(batches):
            if cell != held:
                yield out(asked_of)
                held, asked_of = cell, []
            if not side:
                ids = np.frombuffer(ids, dtype="<i8")
                asked_of.append((ids, np.frombuffer(matrix, dtype="<i8").reshape(len(ids), -1), [[] for _ in ids], [0] * len(ids)))
                continue
            tree = MetricTree.load(matrix)
            for q_ids, q, heaps, work in asked_of:
                for n, (one, vector) in enumerate(zip(q_ids.tolist(), q)):
                    work[n] += tree.search(one, vector, k, heaps[n])
        yield out(asked_of)

    return run


def _found(queries: DataFrame, candidates: DataFrame, id_col: str, vec_col: str, k: int, scale: int, page: int, fanout: int, shard_rows: int) -> DataFrame:
    whole = lambda m: np.floor(scale * m).astype("<i8")
    shards = blocks(usable(candidates, id_col, vec_col, True), shard_rows, whole)
    index = shards.mapInArrow(tidied(_index(page, fanout)), BLOCK)
    q = blocks(asked(usable(queries, id_col, vec_col, True)), QUERY_ROWS, whole)
    return grid(q, index, SIDE_BLOCKS, LANE_BLOCKS).mapInArrow(tidied(_search(k)), "query_id bigint, vec_id bigint, score bigint, products bigint")


def top_products(queries: DataFrame, candidates: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", k: int = K, scale: int = SCALE, page: int = PAGE, fanout: int = FANOUT, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """``query_id, rank, vec_id, score``: the k highest whole-number products for each query row."""
    return merged(_found(queries, candidates, id_col, vec_col, k, scale, page, fanout, shard_rows), k)


def products_computed(queries: DataFrame, candidates: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", k: int = K, scale: int = SCALE, page: int = PAGE, fanout: int = FANOUT, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """``query_id, products``: how many products a search computes for each query that finds anything, routing vectors included."""
    return _found(queries, candidates, id_col, vec_col, k, scale, page, fanout, shard_rows).groupBy("query_id").agg(F.sum("products").alias("products"))
