"""Packing of documents into sequences of ``capacity`` tokens, best fit decreasing.

Documents of more than one window are first cut into full windows; each such piece is a
sequence of its own. The remainders, all shorter than a window, are placed in
decreasing length, each into the open window with the least room that still holds it.

Equal lengths are interchangeable, so the placement is computed on the exact
histogram of remainder lengths (at most ``capacity`` rows, whatever the corpus): a segment
tree indexed by remaining room finds the tightest class of open windows, and a
whole run of equal pieces is placed at once, exactly as one by one. The plan (runs of ranks) is
joined back to the pieces by length and rank. Ranks come from counts per length
and salt, with about ``RANKED`` pieces for each of them, so neither a common length nor a large corpus meets in one task.

Null and empty texts are one end token. Rows with equal or null ids are pieces of their
own. An empty table gives no piece.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treefix.llm.shared import rows_of, stage, tidied
from treefix.llm.tokens import encode, vocabulary_path

CAPACITY, END_ID, RANKED = 1024, 0, 100_000
PIECE = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint"


class RoomTree:
    """A segment tree over remaining room: which rooms have open windows."""

    def __init__(self, capacity: int):
        self.size = 1 << capacity.bit_length()
        self.filled = [0] * (2 * self.size)

    def set(self, room: int, on: bool) -> None:
        at = room + self.size
        self.filled[at] = int(on)
        while at > 1:
            at >>= 1
            self.filled[at] = self.filled[2 * at] | self.filled[2 * at + 1]

    def tightest(self, room: int) -> int | None:
        """The smallest room that is at least ``room`` and has a window."""
        at = room + self.size
        if self.filled[at]:
            return room
        while at > 1:
            if not at & 1 and self.filled[at + 1]:
                at += 1
                while at < self.size:
                    at = 2 * at if self.filled[2 * at] else 2 * at + 1
                return at - self.size
            at >>= 1
        return None


def best_fit_plan(histogram: dict[int, int], capacity: int = CAPACITY) -> list[tuple[int, int, int, int, int, int]]:
    """Rows (length, first rank, pieces, pieces a window, first window, offset): the
    pieces of that length with ranks from the first on fill windows in turn."""
    tree, open_, plan, windows = RoomTree(capacity), {}, [], 0

    def give(room: int, first: int, count: int) -> None:
        if room and count:
            open_.setdefault(room, []).append((first, count))
            tree.set(room, True)

    for length in sorted(histogram, reverse=True):
        rank, left = 0, histogram[length]
        while left:
            room = tree.tightest(length)
            if room is None:
                room, per = capacity, capacity // length
                first, count = windows, -(-left // per)
                windows += count
            else:
                first, count = open_[room].pop(0)
                if not open_[room]:
                    tree.set(room, False)
                per = room // length
            here = min(left, per * count)
            plan.append((length, rank, here, per, first, capacity - room))
            full, over = divmod(here, per)
            give(room - per * length, first, full)
            if over:
                give(room - over * length, first + full, 1)
            untouched = count - full - bool(over)
            if untouched:
                give(room, first + full + bool(over), untouched)
                open_[room].insert(0, open_[room].pop())
            rank, left = rank + here, left - here
    return plan


def _pieces(path: str, capacity: int, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = []
        kinds = (pa.int64(),) * 5
        names = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]

        def out():
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=names)

        for doc_id, text in rows_of(batches, "doc_id", "text"):
            ids = np.append(encode(text, path), np.array([end_id], dtype="<u4")).astype("<u4")
            for start in range(0, len(ids), capacity):
                piece = ids[start : start + capacity]
                rows.append((doc_id, start, len(piece), zlib.crc32(piece.tobytes()), len(ids)))
            if len(rows) >= 8192:
                yield out()
                rows = []
        if rows:
            yield out()

    return run


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID, ranked_at_once: int = RANKED) -> DataFrame:
    """A row for each piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``."""
    spark = docs.sparkSession
    d = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).alias("text"))
    pieces = stage(d.mapInArrow(tidied(_pieces(path or vocabulary_path(), capacity, end_id)), PIECE), "pieces")
    # at most `capacity` rows, whatever the corpus
    salts = [(r["length"], -(-r["count"] // ranked_at_once)) for r in pieces.groupBy("length").count().collect()]
    many = spark.createDataFrame(salts, "length bigint, salts bigint")
    salted = pieces.join(F.broadcast(many), "length").withColumn("salt", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.col("salts"))).drop("salts")
    counts = salted.groupBy("length", "salt").count()
    # a row for each length, and one more for each `ranked_at_once` pieces
    table = {(r["length"], r["salt"]): r["count"] for r in counts.collect()}
    before, ranks, histogram = {}, [], {}
    for (length, s), n in sorted(table.items()):
        ranks.append((length, s, before.get(length, 0)))
        before[length] = before.get(length, 0) + n
    full = before.pop(capacity, 0)
    histogram = before
    plan = best_fit_plan(histogram, capacity)
    if full:
        plan.append((capacity, 0, full, 1, max((p[4] + -(-p[2] // p[3]) for p in plan), default=0), 0))
    bases = spark.createDataFrame(ranks, "length bigint, salt bigint, base bigint")
    runs = spark.createDataFrame(plan, "p_length bigint, first bigint, pieces bigint, per bigint, window bigint, room bigint")
    within = F.row_number().over(Window.partitionBy("length", "salt").orderBy("doc_id", "start", "ids_crc32", "doc_tokens"))
    ranked = salted.join(F.broadcast(bases), ["length", "salt"]).withColumn("rank", F.col("base") + within - 1)
    placed = ranked.join(F.broadcast(runs), (F.col("length") == F.col("p_length")) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("first") + F.col("pieces")))
    at = F.col("rank") - F.col("first")
    return placed.select(
        "doc_id", "start", "length", "ids_crc32", "doc_tokens",
        (F.col("window") + F.floor(at / F.col("per"))).cast("bigint").alias("sequence_id"),
        (F.col("room") + F.pmod(at, F.col("per")) * F.col("length")).cast("bigint").alias("offset"),
    )
