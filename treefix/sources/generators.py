"""Generated facts: the motivating example and expression trees over rows of values."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

B, C, D = 1_000_000, 2_000_000, 3_000_000  # first ids of the other kinds


def motivating(spark: SparkSession, n: int, k: int) -> dict[str, DataFrame]:
    """Colleague, Cosigner and Match such that the rule's first three atoms have n * k * k bindings
    and all four n * k; two more facts make a second round."""
    grid = spark.range(n * k).select(F.floor(F.col("id") / k).cast("bigint").alias("i"), (F.col("id") % k + 1).alias("j"))
    at = F.col("i") * k + F.col("j")
    pair = lambda a, b: grid.select(a.alias("x"), b.alias("z"))
    one = lambda a, b: spark.range(1).select(F.lit(a).cast("bigint").alias("x"), F.lit(b).cast("bigint").alias("z"))
    return {
        "Colleague": pair(F.col("i"), at + B).union(one(n, 2)),
        "Cosigner": pair(F.col("i"), at + C).union(one(n, 3)),
        "Match": pair(at + B, F.col("j") + D).union(pair(at + C, F.col("j") + D)),
    }


def charge(lineitem: DataFrame) -> dict[str, DataFrame]:
    """The tree of price * (100 - discount) * (100 + tax) over each distinct line, in whole hundredths."""
    spark = lineitem.sparkSession
    keys = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"]
    d = F.concat_ws("|", *keys).alias("d")
    whole = lambda c: F.round(F.col(c) * 100).cast("bigint")
    rows = lineitem.select(d, whole("l_extendedprice").alias("price"), whole("l_discount").alias("disc"), whole("l_tax").alias("tax")).groupBy("d").agg(*[F.min(c).alias(c) for c in ("price", "disc", "tax")])
    leaf = lambda e, c: rows.select(F.lit(e).alias("e"), "d", c.cast("bigint").alias("v"))
    # nodes: 1 price, 2 hundred, 3 discount, 4 tax, 5 = 2 - 3, 6 = 2 + 4, 7 = 1 * 5, 8 = 7 * 6
    leaves = [leaf(1, F.col("price")), leaf(2, F.lit(100)), leaf(3, F.col("disc")), leaf(4, F.col("tax"))]
    return expression_facts(spark, [(5, "sub", 2, 3), (6, "add", 2, 4), (7, "mul", 1, 5), (8, "mul", 7, 6)], reduce(lambda a, b: a.unionByName(b), leaves), rows.select("d"))


OPS = ("add", "sub", "mul")


def expression_facts(spark: SparkSession, nodes: list[tuple[int, str, int, int]], leaves: DataFrame, rows: DataFrame) -> dict[str, DataFrame]:
    inner = spark.createDataFrame(nodes, "e bigint, o string, l bigint, r bigint")
    ops = spark.createDataFrame([(o,) for o in OPS], "o string")
    return {
        "IsExpr": inner.select("e"), "OpOf": inner.select("e", "o"), "Left": inner.select("e", "l"), "Right": inner.select("e", "r"), "Row": rows.select("d").distinct(),
        "AddOp": ops.where("o = 'add'"), "SubOp": ops.where("o = 'sub'"), "MulOp": ops.where("o = 'mul'"), "Val": leaves.select(F.col("e").cast("bigint").alias("e"), "d", "v"),
    }


def generated(lineitem: DataFrame, part: DataFrame, trees: int, values: int, depth: int = 5) -> tuple[dict[str, DataFrame], DataFrame]:
    """Full binary trees, ``trees`` of depths 2 to ``depth``, over ``values`` rows. Node ids are tree * 1000 + place in
    the tree (root 1, children 2p and 2p + 1); operators follow a rule of tree and place, at most two
    multiplications below each other. Also the root of each tree."""
    spark = lineitem.sparkSession
    shape = spark.range(trees).select(F.col("id").alias("t"), (F.col("id") % (depth - 1) + 1).alias("levels"))
    places = shape.select("t", "levels", F.explode(F.sequence(F.lit(1), F.pow(F.lit(2), F.col("levels")).cast("bigint") - 1)).alias("p"))
    op = F.when((F.col("p") < 4) & ((F.col("t") + F.col("p")) % 3 == 0), "mul").when((F.col("t") * 7 + F.col("p") * 5) % 2 == 0, "add").otherwise("sub")
    node = lambda p: F.col("t") * 1000 + p
    inner = places.select(node(F.col("p")).alias("e"), op.alias("o"), node(F.col("p") * 2).alias("l"), node(F.col("p") * 2 + 1).alias("r"))
    low = F.pow(F.lit(2), F.col("levels")).cast("bigint")
    leaf_places = shape.select("t", F.explode(F.sequence(low, 2 * low - 1)).alias("p"))
    lines = lineitem.groupBy("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").agg((F.min("l_quantity").cast("bigint") % 10).alias("q"))
    lines = lines.join(part.select(F.col("p_partkey").alias("l_partkey"), (F.col("p_size") % 10).cast("bigint").alias("z")), "l_partkey")
    d = F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber").alias("d")
    chosen = lines.select(d, "q", (F.col("l_linenumber") % 10).cast("bigint").alias("n"), "z").orderBy(F.md5("d"), "d").limit(values)
    value = F.element_at(F.array("q", "n", "z"), (F.col("p") % 3 + 1).cast("int")) + F.col("t") % 3
    leaves = leaf_places.crossJoin(F.broadcast(chosen)).select(node(F.col("p")).alias("e"), "d", value.alias("v"))  # values is a bound
    facts = expression_facts(spark, [(0, "add", 0, 0)], leaves, chosen)
    facts |= {"IsExpr": inner.select("e"), "OpOf": inner.select("e", "o"), "Left": inner.select("e", "l"), "Right": inner.select("e", "r")}
    return facts, shape.select(node(F.lit(1)).alias("e"))
