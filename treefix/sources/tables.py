"""Predicates over the given tables: projections whose columns are arguments, in order.

Whole-number arguments are bigint, others strings, so joins across predicates need no casts. Rows
become sets when they are loaded.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from treefix.store import work_dir

EVENT_TYPES = ("view", "click", "purchase", "signup", "error")


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Forward edges span at most this, in every folder and in the SQL.
GAP = 20


def _long(*pairs: tuple[str, str]) -> list:
    return [F.col(c).cast("bigint").alias(a) for c, a in pairs]


def handoffs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event type, user, next user of that type). One type is a fifth of the events: the table is dealt by type and day,
    ``lead`` runs within a day, and the last event of a day meets the first of the next day that has one."""
    e = read(spark, sf_dir, "events").select("event_type", F.col("user_id").cast("bigint").alias("u"), "ts", "event_id", F.to_date("ts").alias("day"))
    within = Window.partitionBy("event_type", "day").orderBy("ts", "event_id")
    inner = e.withColumn("v", F.lead("u").over(within))
    ends = e.groupBy("event_type", "day").agg(F.min_by("u", F.struct("ts", "event_id")).alias("first"), F.max_by("u", F.struct("ts", "event_id")).alias("last"))
    across = ends.withColumn("v", F.lead("first").over(Window.partitionBy("event_type").orderBy("day")))  # a row for each type and day
    both = inner.select("event_type", "u", "v").unionByName(across.select("event_type", F.col("last").alias("u"), "v"))
    return both.where(F.col("v").isNotNull() & (F.col("u") != F.col("v"))).distinct()


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = read(spark, sf_dir, "orders").select(*_long(("o_orderkey", "o"), ("o_custkey", "c")))
    return read(spark, sf_dir, "lineitem").select(*_long(("l_orderkey", "o"), ("l_partkey", "p"), ("l_suppkey", "s"))).join(orders, "o")


def _sign_buckets(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "embeddings")
    bits = lambda k: F.concat(F.lit(f"{k}:"), F.array_join(F.transform(F.slice("embedding", 8 * k + 1, 8), lambda x: F.when(x >= 0, "1").otherwise("0")), ""))
    return e.select(F.col("vec_id").cast("bigint").alias("v"), F.explode(F.array(*[bits(k) for k in range(4)])).alias("x"))


def _doc_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = read(spark, sf_dir, "documents").select(*_long(("doc_id", "d")), F.explode(F.split("text", "\n")).alias("line"))
    return lines.where(F.length("line") >= 20).select("d", F.md5("line").alias("f"))


def mentions(spark: SparkSession, sf_dir: str, tokens: int = 4, width: int = 24) -> DataFrame:
    """(document, benchmark item) where the text contains the item's.

    Between two spaces of an item stand whole tokens, which must be whole tokens of the text too. Both sides meet by a
    hash of the item's first ``tokens`` such tokens (fewer if it has no more), which texts have one of for each token, and
    ``contains`` decides. Items without such a token meet texts by their first ``width`` characters, at every character."""
    items = read(spark, sf_dir, "benchmark").where(F.length("text") > 0).select(*_long(("item_id", "i")), F.col("text").alias("item"))
    docs = read(spark, sf_dir, "documents").select(*_long(("doc_id", "d")), "text")
    within = F.greatest(F.size(F.split("item", " ")) - 2, F.lit(0))
    items = items.withColumn("t", F.least(within, F.lit(tokens))).withColumn("w", F.when(F.col("t") == 0, F.least(F.length("item"), F.lit(width))).otherwise(0))
    items = items.withColumn("h", F.expr("CASE WHEN t > 0 THEN xxhash64(t, array_join(slice(split(item, ' '), 2, t), ' ')) ELSE xxhash64(-w, substring(item, 1, w)) END"))
    kinds = items.select("t", "w").distinct().collect()  # at most `tokens` + `width` of them
    found = docs.select("d", F.lit(0).cast("bigint").alias("i")).limit(0)
    for t, w in sorted(tuple(k) for k in kinds):
        if t:
            spots = F.expr(f"transform(sequence(0, greatest(size(split(text, ' ')) - {t}, 0)), p -> xxhash64({t}, array_join(slice(split(text, ' '), p + 1, {t}), ' ')))")
        else:
            spots = F.expr(f"transform(sequence(1, greatest(length(text) - {w} + 1, 1)), p -> xxhash64(-{w}, substring(text, p, {w})))")
        own = items.where((F.col("t") == t) & (F.col("w") == w)).select("h", "i")
        found = found.unionByName(docs.select("d", F.explode(F.array_distinct(spots)).alias("h")).join(own, "h").select("d", "i"))
    return found.distinct().join(items.select("i", "item"), "i").join(docs, "d").where(F.contains("text", "item")).select("d", "i")


TABLES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "LivesIn": lambda s, d: read(s, d, "customer").select(*_long(("c_custkey", "c"), ("c_nationkey", "n"))),
    "Segment": lambda s, d: read(s, d, "customer").select(*_long(("c_custkey", "c")), F.col("c_mktsegment").alias("g")),
    "BasedIn": lambda s, d: read(s, d, "supplier").select(*_long(("s_suppkey", "s"), ("s_nationkey", "n"))),
    "InRegion": lambda s, d: read(s, d, "nation").select(*_long(("n_nationkey", "n"), ("n_regionkey", "r"))),
    "RegionName": lambda s, d: read(s, d, "region").select(*_long(("r_regionkey", "r")), F.col("r_name").alias("x")),
    "Placed": lambda s, d: read(s, d, "orders").select(*_long(("o_custkey", "c"), ("o_orderkey", "o"))),
    "Status": lambda s, d: read(s, d, "orders").select(*_long(("o_orderkey", "o")), F.col("o_orderstatus").alias("x")),
    "Priority": lambda s, d: read(s, d, "orders").select(*_long(("o_orderkey", "o")), F.col("o_orderpriority").alias("x")),
    "Line": lambda s, d: read(s, d, "lineitem").select(*_long(("l_orderkey", "o"), ("l_partkey", "p"), ("l_suppkey", "s"))),
    "Supplies": lambda s, d: read(s, d, "lineitem").select(*_long(("l_suppkey", "s"), ("l_partkey", "p"))),
    "Bought": lambda s, d: _lines(s, d).select("c", "p"),
    "BoughtFrom": lambda s, d: _lines(s, d).select("c", "s"),
    "HasBrand": lambda s, d: read(s, d, "part").select(*_long(("p_partkey", "p")), F.col("p_brand").alias("b")),
    "HasType": lambda s, d: read(s, d, "part").select(*_long(("p_partkey", "p")), F.col("p_type").alias("t")),
    "HasSize": lambda s, d: read(s, d, "part").select(*_long(("p_partkey", "p"), ("p_size", "z"))),
    "Did": lambda s, d: read(s, d, "events").select(*_long(("user_id", "u")), F.col("event_type").alias("t")),
    "NextTurn": lambda s, d: read(s, d, "conversations").select(*_long(("conv_id", "k"), ("turn", "x"))).join(read(s, d, "conversations").select(*_long(("conv_id", "k")), (F.col("turn").cast("bigint") - 1).alias("x")), ["k", "x"]).select("k", "x", (F.col("x") + 1).alias("y")),
    "Role": lambda s, d: read(s, d, "conversations").select(*_long(("conv_id", "k"), ("turn", "x")), F.col("role").alias("r")),
    "OnHost": lambda s, d: read(s, d, "pages").select(*_long(("page_id", "g")), F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("h")),
    "PageLang": lambda s, d: read(s, d, "pages").select(*_long(("page_id", "g")), F.regexp_extract("url", "^[a-z]+://[^/]+/([^/]*)", 1).alias("l")),
    "LinksTo": lambda s, d: read(s, d, "pages").select(*_long(("page_id", "g")), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("t")),
    "DocFrom": lambda s, d: read(s, d, "documents").select(*_long(("doc_id", "d")), F.col("source").alias("s")),
    "DocLang": lambda s, d: read(s, d, "documents").select(*_long(("doc_id", "d")), F.col("lang").alias("l")),
    "HasLine": _doc_lines,
    "Mentions": mentions,
    "Quality": lambda s, d: read(s, d, "labels").select(*_long(("doc_id", "d"), ("quality", "q"))),
    "Toxic": lambda s, d: read(s, d, "labels").select(*_long(("doc_id", "d"), ("toxic", "x"))),
    "InBucket": _sign_buckets,
    "HasLabel": lambda s, d: read(s, d, "embeddings").select(*_long(("vec_id", "v"), ("label", "l"))),
}


def _edges(kind: str, forward: bool) -> Callable[..., DataFrame]:
    def make(s: SparkSession, d: str, rows: DataFrame | None = None) -> DataFrame:
        rows = handoffs(s, d) if rows is None else rows
        if kind != "any":
            rows = rows.where(F.col("event_type") == kind)
        if forward:
            rows = rows.where((F.col("u") < F.col("v")) & (F.col("v") - F.col("u") <= GAP))
        return rows.select("u", "v")

    return make


for _t in EVENT_TYPES:
    TABLES[f"Handoff_{_t}"] = _edges(_t, False)
    TABLES[f"Forward_{_t}"] = _edges(_t, True)
TABLES["Forward_any"] = _edges("any", True)


def facts(spark: SparkSession, sf_dir: str, preds: list[str]) -> dict[str, DataFrame]:
    """Predicates by name. Edges are all chosen from the hand-offs, which are written once if several ask for them: whoever reads
    these frames, once or many times, would sort the events anew."""
    preds = list(dict.fromkeys(preds))
    edges = [p for p in preds if p.startswith(("Handoff_", "Forward_"))]
    if len(edges) < 2:
        return {p: TABLES[p](spark, sf_dir) for p in preds}
    path = f"{work_dir(spark)}/treefix/{uuid.uuid4().hex}-handoffs"
    handoffs(spark, sf_dir).write.parquet(path)
    rows = spark.read.schema("event_type string, u bigint, v bigint").parquet(path)
    return {p: TABLES[p](spark, sf_dir, rows) if p in edges else TABLES[p](spark, sf_dir) for p in preds}


def from_source(spark: SparkSession, kind: str, **options) -> DataFrame:
    """Facts from a file source (parquet, csv, json, orc), a table or view, SQL text, or jdbc."""
    if kind in ("table", "view"):
        return spark.table(options["name"])
    if kind == "sql":
        return spark.sql(options["text"])
    path = options.pop("path", None)
    reader = spark.read.format(kind)
    if "schema" in options:
        reader = reader.schema(options.pop("schema"))
    reader = reader.options(**options)
    return reader.load(path) if path else reader.load()


def write_facts(df: DataFrame, kind: str, target: str, mode: str = "errorifexists", partition_by: list[str] | None = None, bucket: tuple[int, str] | None = None) -> None:
    """A predicate to files, a catalog table (bucketed if asked for) or a view."""
    if kind == "view":
        df.createOrReplaceTempView(target)
        return
    out = df.write.mode(mode)
    if partition_by:
        out = out.partitionBy(*partition_by)
    if kind == "table":
        (out.bucketBy(*bucket).sortBy(bucket[1]) if bucket else out).format("parquet").saveAsTable(target)
    else:
        out.format(kind).save(target)
