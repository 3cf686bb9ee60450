"""Helpers that several operators share: staging, Arrow batches, word hashes."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import gc
import shutil
import tempfile
import time
import uuid
import zipfile
from collections.abc import Callable, Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WORD_BUDGET = 400_000  # words that a Python worker holds at once, besides one document


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Let Python workers import this package, on a cluster that doesn't have it installed."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    top = Path(__file__).resolve().parent.parent
    d = tempfile.mkdtemp()  # the driver serves the file from there while the session lasts
    atexit.register(shutil.rmtree, d, ignore_errors=True)
    with zipfile.ZipFile(f"{d}/{top.name}_package.zip", "w") as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, f"{top.name}/{p.relative_to(top)}")
    spark.sparkContext.addPyFile(f"{d}/{top.name}_package.zip")
    _shipped.add(app)


def work_dir(spark: SparkSession) -> str:
    """The shared folder of the session (``spark.checkpoint.dir``).

    Only where none is set, as in local tests, one below ``/tmp`` is set.
    """
    held = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if held:
        return held.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    own = f"/tmp/treefix-checkpoints-{uuid.uuid4().hex}"
    spark.sparkContext.setCheckpointDir(own)
    return own


def stage(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it again: lineage ends there,
    the rows survive the loss of any executor, and nothing is computed twice."""
    spark = df.sparkSession
    path = f"{work_dir(spark)}/treefix/{uuid.uuid4().hex}-{name}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def release(spark: SparkSession) -> None:
    """Let Spark remove the shuffle files behind rows that are written by now: it does so once the driver has
    collected what refers to them. The second collection takes what the listeners of the first run still held."""
    for _ in range(2):
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        time.sleep(0.7)


def lighten(spark: SparkSession) -> None:
    """Executors collect their garbage, whereupon their heaps shrink: what a stage leaves there would stand beside the Python workers
    of the next until the heap is full. There is no way to ask each for it, so twice as many tasks as there are cores do."""
    many = 2 * spark.sparkContext.defaultParallelism
    spark.range(0, many, 1, many).select(F.expr("reflect('java.lang.System', 'gc')").alias("done")).write.format("noop").mode("overwrite").save()


def tidied(run: Callable) -> Callable:
    """``run`` for ``mapInArrow``, after which the worker gives memory back: workers are used again by
    later tasks, and what allocators hold would add to theirs."""

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # only where the C library has it
                ctypes.CDLL(None).malloc_trim(0)

    return wrapped


def as_bytes(value) -> bytes:
    return b"" if value is None else value


def rows_of(batches: Iterator[pa.RecordBatch], *names: str) -> Iterator[tuple]:
    """Rows as Python tuples, a slice of a batch at a time (long texts are not
    all turned into Python objects at once)."""
    for batch in batches:
        for at in range(0, batch.num_rows, 256):
            part = batch.slice(at, 256)
            yield from zip(*(part.column(part.schema.get_field_index(n)).to_pylist() for n in names))


def word_hashes(words: list[bytes], seed: int = 0) -> np.ndarray:
    """A 64-bit hash of each word."""
    digest = xxhash.xxh64_intdigest
    if seed:
        return np.fromiter((digest(w, seed) for w in words), dtype=np.uint64, count=len(words))
    return np.fromiter(map(digest, words), dtype=np.uint64, count=len(words))


def mixed(x: np.ndarray) -> np.ndarray:
    """Finalise 64-bit values so that all bits depend on all bits."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class RollingHash:
    """Hashes of any run of ``width`` words from prefix sums, modulo 2**64."""

    def __init__(self, base: int):
        self.base, self.inverse = base | 1, pow(base | 1, -1, 1 << 64)
        self._up = self._down = np.ones(1, dtype=np.uint64)

    def _powers(self, n: int) -> None:
        size = len(self._up)
        while size < n:
            with np.errstate(over="ignore"):
                self._up = np.concatenate([self._up, self._up * np.uint64(pow(self.base, size, 1 << 64))])
                self._down = np.concatenate([self._down, self._down * np.uint64(pow(self.inverse, size, 1 << 64))])
            size = len(self._up)

    def windows(self, hashes: np.ndarray, starts: np.ndarray, width: int) -> np.ndarray:
        self._powers(len(hashes) + 1)
        with np.errstate(over="ignore"):
            prefix = np.zeros(len(hashes) + 1, dtype=np.uint64)
            np.cumsum(hashes * self._up[: len(hashes)], out=prefix[1:])
            return mixed((prefix[starts + width] - prefix[starts]) * self._down[starts])


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


#: A key is hot if it holds more than this share of the rows (and more than LEAST_HOT of them): at most so many keys are
SHARE_OF_HOT, LEAST_HOT = 10_000, 256


def hot_keys(rows: DataFrame, key: str) -> DataFrame | None:
    """``key, many``: the keys that hold over a ten-thousandth of the rows, so at most ten thousand; None without any."""
    counts = rows.groupBy(key).agg(F.count(F.lit(1)).alias("many"))
    total = rows.count()
    found = counts.where(F.col("many") > max(LEAST_HOT, total // SHARE_OF_HOT)).collect()
    return rows.sparkSession.createDataFrame(found, counts.schema) if found else None


def hot_join(rows: DataFrame, table: DataFrame, key: str, how: str = "inner", hot: DataFrame | None = None, known: bool = False) -> DataFrame:
    """``rows`` joined with ``table`` (small rows, one for a key). Rows of hot keys stay where they are and
    meet the table's rows of these keys, at most ten thousand, by broadcast; others meet by shuffle. ``known``: ``hot`` is given."""
    if not known:
        hot = hot_keys(rows, key)
    if hot is None:
        return rows.join(table, key, how)
    names = F.broadcast(hot.select(key))
    crowd = rows.join(names, key, "left_semi").join(F.broadcast(table.join(names, key, "left_semi")), key, how)
    return crowd.unionByName(rows.join(names, key, "left_anti").join(table, key, how))


def salted_join(rows: DataFrame, table: DataFrame, key: str, by: str, hot: DataFrame | None, each: int = 512) -> DataFrame:
    """``rows`` joined with ``table`` (one row for a key, perhaps a large one): the rows of a key of ``hot`` are dealt by column
    ``by``, about ``each`` together, and its row of the table is sent to each such part."""
    if hot is None:
        return rows.join(table, key)
    parts = F.broadcast(hot.select(key, F.ceil(F.col("many") / each).cast("int").alias("parts_")))
    dealt = rows.join(parts, key, "left").withColumn("salt_", F.coalesce(F.pmod(F.xxhash64(by), F.col("parts_")), F.lit(0)).cast("int")).drop("parts_")
    sent = table.join(parts, key, "left").withColumn("salt_", F.explode(F.sequence(F.lit(0), F.coalesce(F.col("parts_"), F.lit(1)) - 1))).drop("parts_")
    return dealt.join(sent, [key, "salt_"]).drop("salt_")


def free_name(taken: list[str], wanted: str) -> str:
    """``wanted``, with underscores added until no column of ``taken`` has it."""
    low = {t.lower() for t in taken}
    while wanted.lower() in low:
        wanted += "_"
    return wanted
