"""Functions for computed values: scaled numbers, and registration of vectorised functions for ``:=``."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def hundredths(column: str) -> Column:
    """A number with two decimals as a whole one, so that joins on it are exact."""
    return F.round(F.col(column) * 100).cast("bigint")


def register_vectorised(spark: SparkSession, name: str, function: Callable, returns: str = "bigint") -> None:
    """A pandas function under a name that rules can use in ``v := name(a, b)``."""
    spark.udf.register(name, F.pandas_udf(function, returns))


def encoded(df: DataFrame, column: str, dictionary: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """Strings as whole-number ids from a dictionary, which is extended by new strings; ids are ranks of
    new strings within hash ranges plus what ranges before hold, so no task sorts all of them."""
    from pyspark.sql import Window

    held = dictionary if dictionary is not None else df.sparkSession.createDataFrame([], "term string, id bigint")
    new = df.select(F.col(column).alias("term")).where(F.col("term").isNotNull()).distinct().join(held, "term", "left_anti").withColumn("range", F.pmod(F.xxhash64("term"), F.lit(256)))
    base = held.agg(F.coalesce(F.max("id") + 1, F.lit(0)).alias("base"))
    sizes = new.groupBy("range").count().withColumn("before", F.coalesce(F.sum("count").over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))  # 256 rows at most
    rank = F.row_number().over(Window.partitionBy("range").orderBy("term")) - 1
    ids = new.join(F.broadcast(sizes.select("range", "before")), "range").join(F.broadcast(base)).select("term", (F.col("base") + F.col("before") + rank).cast("bigint").alias("id"))
    full = held.unionByName(ids)
    return df.join(full.withColumnRenamed("term", column), column, "left").drop(column).withColumnRenamed("id", column), full


class Bindings:
    """Rows (variable, value) of bindings as ``Reasoner.why`` gives them, in JSON."""

    def eval(self, bindings: str) -> Iterator[tuple[str, str]]:
        for name, value in sorted(json.loads(bindings).items()):
            yield name, str(value)


def register_bindings(spark: SparkSession, name: str = "bindings_of") -> None:
    """The table function behind ``SELECT ... FROM proofs, LATERAL bindings_of(bindings)``."""
    spark.udtf.register(name, F.udtf(Bindings, returnType="variable string, value string"))


def json_facts(df: DataFrame, key: str, text: str) -> DataFrame:
    """(key, name, value) for each entry of a flat JSON object; malformed objects have none."""
    held = F.from_json(F.col(text), "map<string,string>")
    return df.select(F.col(key).cast("bigint").alias("k"), F.explode(held).alias("name", "value"))


def map_facts(df: DataFrame, key: str, column: str) -> DataFrame:
    """(key, name, value) for each entry of a map column: a map itself can't be an argument."""
    return df.select(key, F.explode(column).alias("name", "value"))
