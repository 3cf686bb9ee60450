"""A corpus pipeline of five stages over ``documents``.

Each stage takes (spark, docs, sf_dir), works on all documents that the stage before kept and returns
the columns of ``documents``; the last returns packed pieces. Executors give their heaps back before each. Empty and null texts are clean and stay.
Rows with a null id are never merged with others. Extra columns pass through.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefix.llm import packing, secrets_cnn, shingle_sets, substring_dedup, toxicity
from treefix.llm.shared import free_name, lighten, release, ship, stage


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity reaches the threshold go."""
    lighten(spark)
    net = toxicity.train(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    name = free_name(docs.columns, "toxicity")
    return toxicity.score_toxicity(docs, net, score_col=name).where(F.col(name) < toxicity.THRESHOLD).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Near copies are found by op6's fingerprints, and by band keys where those don't reach; 5-word shingle sets of similarity 0.8 or more decide. Of each group of them the document with the smallest id stays (once, if rows repeat)."""
    lighten(spark)
    own = free_name(docs.columns, "own_id")
    found = shingle_sets.near_duplicates(docs).select(F.col("doc_id").alias(own), "component_id")
    gone = found.where(F.col(own).isNotNull() & (F.col(own) != F.col("component_id"))).select(own).distinct()
    kept = docs.join(gone, F.col("doc_id") == F.col(own), "left_anti")
    # a repeated row is a copy of the smallest id too
    repeated = kept.groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows")).where("doc_id IS NOT NULL AND rows > 1").select(F.col("doc_id").alias(own))
    several = kept.join(repeated, F.col("doc_id") == F.col(own), "left_semi").dropDuplicates(["doc_id"])
    return kept.join(repeated, F.col("doc_id") == F.col(own), "left_anti").unionByName(several)


def drop_repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words of sequences that occur more than once go; what stood between kept words stays."""
    lighten(spark)
    own, th, new = (free_name(docs.columns, f"cut_{n}") for n in ("id", "hash", "text"))
    cut = substring_dedup.remove_repeats(docs).where("n_removed > 0").select(F.col("doc_id").alias(own), F.col("th").alias(th), F.col("kept_text").alias(new)).dropDuplicates([own, th])
    joined = docs.join(cut, F.col("doc_id").eqNullSafe(F.col(own)) & (F.xxhash64("text") == F.col(th)), "left")
    text = F.when(F.col(th).isNotNull(), F.col(new)).otherwise(F.col("text")).alias("text")
    return joined.select(*[text if c == "text" else F.col(f"`{c}`") for c in docs.columns])


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are masked; every document stays."""
    lighten(spark)
    return secrets_cnn.mask_secrets(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all documents and their places in sequences."""
    lighten(spark)
    return packing.pack(docs)


STAGES = [("toxicity", drop_toxic), ("near_dedup", drop_near_copies), ("substring_dedup", drop_repeats), ("secrets", mask_secrets), ("packing", pack_sequences)]
#: The network, the near copies' components and the token ids are beyond SQL; stages are tested against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written as Parquet and read again."""
    ship(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), name)
        release(spark)
    return STAGES[-1][1](spark, docs, sf_dir)
