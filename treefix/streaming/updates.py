"""Updates as streams: batches of additions and retractions, and facts made from windows of events."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from treefix.session import Reasoner


def apply_updates(reasoner: Reasoner, stream: DataFrame, pred: str, op_col: str = "op", checkpoint: str | None = None, available_now: bool = True):
    """Carries each micro-batch into the materialisation. ``op`` is ``+`` or ``-``; a fact with both in
    one batch stays. A batch that is delivered again changes nothing, as facts are sets; late rows are additions like others."""

    def one(batch: DataFrame, _: int) -> None:
        rows = batch.persist()
        try:
            plus, minus = (rows.where(F.col(op_col) == o).drop(op_col) for o in "+-")
            reasoner.update(add={pred: plus}, delete={pred: minus}, task="stream")
        finally:
            rows.unpersist()

    writer = stream.writeStream.foreachBatch(one)
    if checkpoint:
        writer = writer.option("checkpointLocation", checkpoint)
    return (writer.trigger(availableNow=True) if available_now else writer).start()


def deduplicated(stream: DataFrame, time: str, keys: list[str], late: str = "1 hour") -> DataFrame:
    """Each key once while the watermark keeps it."""
    return stream.withWatermark(time, late).dropDuplicatesWithinWatermark(keys)


def windowed_counts(stream: DataFrame, time: str, keys: list[str], length: str, slide: str | None = None, session: bool = False, late: str = "1 hour") -> DataFrame:
    """Counts by key in tumbling, sliding or session windows: facts (window start, keys, count)."""
    span = F.session_window(time, length) if session else F.window(time, length, slide) if slide else F.window(time, length)
    counted = stream.withWatermark(time, late).groupBy(span.alias("w"), *keys).agg(F.count(F.lit(1)).alias("n"))
    return counted.select(F.col("w.start").alias("start"), *keys, "n")


def to_files(stream: DataFrame, path: str, mode: str = "complete") -> str:
    """Runs a stream over what is there; the last result (or all appended rows) is left in files at ``path``."""

    def one(batch: DataFrame, n: int) -> None:
        batch.write.mode("overwrite" if mode == "complete" else "append").parquet(path)

    query = stream.writeStream.outputMode(mode).foreachBatch(one).trigger(availableNow=True).start()
    query.awaitTermination()
    return path
