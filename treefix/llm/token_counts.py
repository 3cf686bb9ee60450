"""Exact token counts of a corpus for every context limit, from one length histogram.

Documents are aggregated by encoded length before anything is shuffled, so the shuffle
carries a row for each length and task. Running sums answer for every context limit: documents and
tokens at or above it, tokens kept if every document is truncated there, and which quantile of the documents it is.

Null and empty texts have length 0 (1 with the end token). An empty table gives no row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from treefix.llm.shared import rows_of
from treefix.llm.tokens import encode, vocabulary_path


def _lengths(path: str, extra: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[int, int] = {}
        for (text,) in rows_of(batches, "text"):
            n = len(encode(text, path)) + extra
            found[n] = found.get(n, 0) + 1
        if found:
            yield pa.RecordBatch.from_arrays([pa.array(np.array(x, dtype=np.int64)) for x in (list(found), list(found.values()))], names=["length", "n_docs"])

    return run


def length_histogram(docs: DataFrame, text_col: str = "text", path: str | None = None, extra: int = 0) -> DataFrame:
    """``length, n_docs``: documents by number of tokens; ``extra`` tokens are added to each."""
    d = docs.select(F.col(text_col).alias("text"))
    counted = d.mapInArrow(_lengths(path or vocabulary_path(), extra), "length bigint, n_docs bigint")
    return counted.groupBy("length").agg(F.sum("n_docs").alias("n_docs"))


BUCKET = 4096


def context_totals(histogram: DataFrame) -> DataFrame:
    """A row for each length that occurs, which answers for every context limit from ``first_limit`` (one above
    the next smaller length) to ``length``: suffix and prefix totals.

    ``docs_from`` / ``tokens_from``: documents of at least that limit and their tokens; ``shorter_tokens``: tokens of all
    others, so ``shorter_tokens + limit * docs_from`` are left if all documents are cut there, and
    ``kept_tokens`` at ``length`` itself; ``quantile``: share of documents that are no longer than ``length``.
    Sums run within ``BUCKET`` lengths and over buckets, so a task gets that many lengths, or a row for each bucket."""
    h = histogram.withColumn("tokens", F.col("length") * F.col("n_docs")).withColumn("bucket", F.floor(F.col("length") / BUCKET))
    sums = h.groupBy("bucket").agg(F.sum("n_docs").alias("docs"), F.sum("tokens").alias("all"), F.max("length").alias("longest"))
    before = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    zero = lambda c: F.coalesce(c, F.lit(0))
    sums = sums.select("bucket", zero(F.sum("docs").over(before)).alias("docs_below"), zero(F.sum("all").over(before)).alias("tokens_below"), F.max("longest").over(before).alias("length_below"), F.sum("docs").over(whole).alias("all_docs"), F.sum("all").over(whole).alias("all_tokens"))
    up = Window.partitionBy("bucket").orderBy("length")
    shorter = up.rowsBetween(Window.unboundedPreceding, -1)
    h = h.join(sums, "bucket")
    h = h.withColumn("shorter_docs", F.col("docs_below") + zero(F.sum("n_docs").over(shorter))).withColumn("shorter_tokens", F.col("tokens_below") + zero(F.sum("tokens").over(shorter)))
    h = h.withColumn("first_limit", zero(F.coalesce(F.lag("length").over(up), "length_below") + 1))
    h = h.withColumn("docs_from", F.col("all_docs") - F.col("shorter_docs"))
    kept = F.col("shorter_tokens") + F.col("length") * F.col("docs_from")
    return h.select("length", "first_limit", "n_docs", "tokens", "docs_from", (F.col("all_tokens") - F.col("shorter_tokens")).alias("tokens_from"), "shorter_tokens", kept.alias("kept_tokens"), ((F.col("shorter_docs") + F.col("n_docs")) / F.col("all_docs")).alias("quantile"))


def kept_at(histogram: DataFrame, limits: list[int]) -> DataFrame:
    """Totals for any limits, whether a document has that length or not."""
    asked = [F.sum(F.least("length", F.lit(n)) * F.col("n_docs")).alias(f"kept_{n}") for n in limits]
    return histogram.agg(F.sum("n_docs").alias("n_docs"), F.sum(F.col("length") * F.col("n_docs")).alias("tokens"), *asked)


def length_quantiles(histogram: DataFrame, shares: list[float]) -> DataFrame:
    """The smallest length that at least each share of the documents doesn't exceed."""
    q = context_totals(histogram)
    found = [F.min(F.when(F.col("quantile") >= s, F.col("length"))).alias(f"q{str(s).replace('.', '_')}") for s in shares]
    return q.agg(*found)
