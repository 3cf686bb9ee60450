"""Vectors as blocks: rows packed into matrices that a task can multiply."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.llm.shared import stage

BLOCK = "ids binary, matrix binary, width int, task int, turn int"
CELL = ("width", "lane", "side")


def usable(df: DataFrame, id_col: str, vec_col: str, allow_zero: bool) -> DataFrame:
    """``vec_id, vec`` without vectors that are null, empty or hold null or
    non-finite components; without zero vectors unless they are allowed."""
    v = df.select(F.col(id_col).cast("bigint").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("vec"))
    bad = F.exists("vec", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    v = v.where(F.col("vec").isNotNull() & F.col("vec_id").isNotNull() & (F.size("vec") > 0)).where(~bad)
    return v if allow_zero else v.where(F.exists("vec", lambda x: x != 0))


def storage(df: DataFrame, vec_col: str) -> str:
    """Single precision where the column has it: half the bytes, the same values."""
    return "<f4" if df.schema[vec_col].dataType.simpleString() == "array<float>" else "<f8"


def blocks(vectors: DataFrame, rows: int, to: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """Rows packed by ``rows`` into (ids, matrix) blocks of one width each, numbered within their task. Vectors of
    different widths never share a block."""

    def pack(ids: list, parts: list, width: int, turn: int) -> pa.RecordBatch:
        matrix = to(np.concatenate(parts))
        return pa.RecordBatch.from_arrays(
            [
                pa.array([np.concatenate(ids).astype("<i8").tobytes()], pa.binary()), pa.array([matrix.tobytes()], pa.binary()),
                *(pa.array([x], pa.int32()) for x in (width, TaskContext.get().partitionId(), turn)),
            ],
            names=["ids", "matrix", "width", "task", "turn"],
        )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, tuple[list, list, int]] = {}
        done = 0
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            column = batch.column(1)
            ends = column.offsets.to_numpy()
            values = column.values.to_numpy(zero_copy_only=False)
            widths = np.diff(ends)
            for width in np.unique(widths):
                own = np.flatnonzero(widths == width)
                matrix = values[(ends[own][:, None] + np.arange(width)[None, :])]
                for at in range(0, len(own), rows):
                    i, m, n = held.setdefault(int(width), ([], [], 0))
                    i.append(ids[own[at : at + rows]])
                    m.append(matrix[at : at + rows])
                    n += len(i[-1])
                    held[int(width)] = (i, m, n)
                    if n >= rows:
                        yield pack(i, m, int(width), done)
                        done += 1
                        del held[int(width)]
        for width, (i, m, _) in held.items():
            yield pack(i, m, width, done)
            done += 1

    return vectors.mapInArrow(run, BLOCK)


def numbered(held: DataFrame) -> tuple[DataFrame, int]:
    """Staged blocks with consecutive numbers, and how many there are. A count for each task that made them comes to the driver."""
    counts = sorted((r["task"], r["count"]) for r in held.groupBy("task").count().collect())
    bases, total = [], 0
    for task, n in counts:
        bases.append((task, total))
        total += n
    table = held.sparkSession.createDataFrame(bases, "task int, base long")
    return held.join(F.broadcast(table), "task").withColumn("number", F.col("base") + F.col("turn")).drop("task", "turn", "base"), total


def grid(queries: DataFrame, candidates: DataFrame, q_most: int, c_most: int) -> DataFrame:
    """Every query block beside every candidate block of its width, by cells of a grid.

    Candidate blocks are dealt to lanes and query blocks to sides, at most ``c_most`` and ``q_most`` to each; a cell gets the blocks of
    its lane and of its side. So a block travels once for each side (or lane), not for each block that it meets, and a task holds
    one cell's queries while candidates pass by. The rows of a cell come together, its queries (``kind`` 0) first."""
    q, q_count = numbered(stage(queries, "query_blocks"))
    c, c_count = numbered(stage(candidates, "blocks"))
    lanes, sides = max(1, -(-c_count // c_most)), max(1, -(-q_count // q_most))
    wanted = 2 * queries.sparkSession.sparkContext.defaultParallelism
    while lanes * sides < wanted and (lanes < c_count or sides < q_count):  # small tables: a cell for each core at least
        if lanes < c_count and (c_count / lanes >= q_count / sides or sides >= q_count):
            lanes += 1
        else:
            sides += 1
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = q.select("width", every(lanes).alias("lane"), F.pmod("number", F.lit(sides)).cast("int").alias("side"), F.lit(0).alias("kind"), "number", "ids", "matrix")
    right = c.select("width", F.pmod("number", F.lit(lanes)).cast("int").alias("lane"), every(sides).alias("side"), F.lit(1).alias("kind"), "number", "ids", "matrix")
    met = left.unionByName(right).repartition(max(1, lanes * sides), *CELL)
    return met.sortWithinPartitions(*CELL, "kind", "number")


def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[tuple[int, int, int], int, bytes, bytes]]:
    """Rows of a task of ``grid``: (cell, kind, ids, matrix)."""
    for batch in batches:
        for i in range(batch.num_rows):
            row = {n: batch.column(n)[i].as_py() for n in (*CELL, "kind", "ids", "matrix")}
            yield tuple(row[n] for n in CELL), row["kind"], row["ids"], row["matrix"]


def asked(queries: DataFrame) -> DataFrame:
    """Of query rows that repeat an id the one with the least vector."""
    return queries.groupBy("vec_id").agg(F.min("vec").alias("vec"))
