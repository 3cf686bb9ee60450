"""Operators around the methods: sets, joins by range and by time, tops, groupings."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def union_facts(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.unionByName(b).distinct()


def intersect_facts(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.intersect(b)


def except_facts(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.subtract(b)


def semi_facts(a: DataFrame, b: DataFrame, on: Sequence[str]) -> DataFrame:
    return a.join(b.select(*on).distinct(), list(on), "left_semi")


def anti_facts(a: DataFrame, b: DataFrame, on: Sequence[str]) -> DataFrame:
    return a.join(b.select(*on).distinct(), list(on), "left_anti")


def top_k(df: DataFrame, k: int, *order: Column) -> DataFrame:
    """The first k rows; each task keeps k rows, so nothing is sorted as a whole."""
    return df.orderBy(*order).limit(k)


def top_k_by(df: DataFrame, keys: Sequence[str], k: int, *order: Column) -> DataFrame:
    """The first k rows of each key. Rows are ranked within salted parts first, so a hot key is cut down before it meets."""
    salt = F.pmod(F.xxhash64(*df.columns), F.lit(32)).alias("salt_")
    part = Window.partitionBy(*keys, "salt_").orderBy(*order)
    few = df.select("*", salt).withColumn("rank_", F.row_number().over(part)).where(F.col("rank_") <= k)
    whole = Window.partitionBy(*keys).orderBy(*order)
    return few.withColumn("rank", F.row_number().over(whole)).where(F.col("rank") <= k).drop("salt_", "rank_")


def grouped(df: DataFrame, how: str, keys: Sequence[str], *aggregates: Column) -> DataFrame:
    """``group``, ``rollup`` or ``cube`` over the keys."""
    return {"group": df.groupBy, "rollup": df.rollup, "cube": df.cube}[how](*keys).agg(*aggregates)


def range_join(left: DataFrame, right: DataFrame, left_col: str, right_col: str, gap: int, on: Sequence[str] = ()) -> DataFrame:
    """Pairs with ``0 < right - left <= gap``: an equi-join on steps of the gap (a right row meets its step and the one
    before), then the condition. No pair is compared that is two steps apart."""
    step = lambda c: F.floor(F.col(c) / F.lit(gap))
    a = left.withColumn("step_", step(left_col))
    b = right.withColumn("step_", F.explode(F.array(step(right_col), step(right_col) - 1)))
    joined = a.join(b, [*on, "step_"])
    return joined.where((F.col(right_col) > F.col(left_col)) & (F.col(right_col) - F.col(left_col) <= gap)).drop("step_")


def as_of_join(left: DataFrame, right: DataFrame, time: str, keys: Sequence[str], value: str) -> DataFrame:
    """For each left row the value of the last right row of its key that is not later: one sort of both sides, no pairs."""
    both = left.select(*keys, time, F.lit(None).cast(right.schema[value].dataType).alias(value), F.lit(1).alias("side_"), F.struct(*left.columns).alias("row_"))
    none = F.lit(None).cast(both.schema["row_"].dataType)
    other = right.select(*keys, time, value, F.lit(0).alias("side_"), none.alias("row_"))
    w = Window.partitionBy(*keys).orderBy(time, "side_").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = both.unionByName(other).withColumn("found_", F.last(value, ignorenulls=True).over(w))
    return seen.where("side_ = 1").select("row_.*", F.col("found_").alias(value))


def salted_join(left: DataFrame, right: DataFrame, on: Sequence[str], salts: int = 16, hot: DataFrame | None = None) -> DataFrame:
    """A join whose hot keys are dealt to several tasks: left rows of ``hot`` keys get a salt, right rows of them one copy for each salt."""
    keys = list(on)
    hot = hot if hot is not None else heavy_keys(left, keys)
    mark = hot.select(*keys).distinct().withColumn("hot_", F.lit(True))
    a = left.join(mark, keys, "left").withColumn("salt_", F.when(F.col("hot_"), F.pmod(F.xxhash64(*left.columns), F.lit(salts))).otherwise(0)).drop("hot_")
    b = right.join(mark, keys, "left").withColumn("salt_", F.explode(F.when(F.col("hot_"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("hot_")
    return a.withColumn("salt_", F.col("salt_").cast("int")).join(b, [*keys, "salt_"]).drop("salt_")


def heavy_keys(df: DataFrame, keys: Sequence[str], share: float = 0.01) -> DataFrame:
    """Keys with over ``share`` of the rows: at most 1 / share of them."""
    counts = df.groupBy(*keys).count()
    total = counts.agg(F.sum("count").alias("total_"))
    return counts.join(F.broadcast(total)).where(F.col("count") > share * F.col("total_")).select(*keys)


def full_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of one side only, with which: a diagnostic by full outer join."""
    names = a.columns
    left, right = a.withColumn("left_", F.lit(True)), b.toDF(*names).withColumn("right_", F.lit(True))
    return left.join(right, names, "full").where(F.col("left_").isNull() | F.col("right_").isNull()).select(*names, F.when(F.col("right_").isNull(), "left").otherwise("right").alias("side"))
