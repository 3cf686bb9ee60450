"""The query of each operator, with its contract's columns, and SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treefix.llm import block_neighbours, license_rules, metric_tree, packing, sampled_segments, secrets_cnn, simhash_pivots, substring_dedup, token_counts, toxicity
from treefix.llm.shared import ship


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    net = toxicity.train(docs, _table(spark, sf_dir, "labels"))
    held = docs.select("doc_id", F.col("text").cast("binary").alias("text"))
    scored = toxicity.score_toxicity(held, net, drop_text=True)
    return scored.select("doc_id", toxicity.is_held_out().alias("held_out"), "score", (F.col("score") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op2_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = substring_dedup.remove_repeats(_table(spark, sf_dir, "documents"), with_text=False)
    return found.select("doc_id", "n_words", "n_removed", "kept_sha256")


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_table(spark, sf_dir, "documents"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.context_totals(token_counts.length_histogram(_table(spark, sf_dir, "documents")))


def op5_sampled_segments(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents").select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("th"), "text")
    found = sampled_segments.decode_segmentations(sampled_segments.sample_segmentations(docs, ["doc_id", "th"]))
    digest = F.crc32(F.array_join(F.transform("ids", lambda i: i.cast("string")), ",").cast("binary")).alias("ids_crc32")
    return found.select("doc_id", "rank", F.size("ids").alias("n_pieces"), digest, "log_prob", "perturbed", "inclusion", (F.xxhash64("decoded") == F.col("th")).alias("round_trip"))


def op6_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash_pivots.near_duplicates(_table(spark, sf_dir, "documents"))


def op7_block_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _table(spark, sf_dir, "embeddings")
    return block_neighbours.nearest(rows.where("vec_id % 20 = 0"), rows)


def op8_metric_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _table(spark, sf_dir, "embeddings")
    return metric_tree.top_products(rows.where("vec_id % 20 = 0"), rows)


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets_cnn.scan_secrets(_table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans")


def op10_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_rules.detect_licenses(_table(spark, sf_dir, "documents")).drop("detections")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_toxicity": op1_toxicity,
    "op2_substring_dedup": op2_substring_dedup,
    "op3_packing": op3_packing,
    "op4_token_counts": op4_token_counts,
    "op5_sampled_segments": op5_sampled_segments,
    "op6_simhash_near_dedup": op6_simhash_near_dedup,
    "op7_block_neighbours": op7_block_neighbours,
    "op8_metric_tree": op8_metric_tree,
    "op9_secrets": op9_secrets,
    "op10_licenses": op10_licenses,
    "pipeline": pipeline,
}

_REPEATS = r"""
WITH words AS (SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '') AS w FROM documents),
starts AS (SELECT doc_id, w, unnest(range(1, greatest(len(w) - 33, 1))) AS i FROM words),
windows AS (SELECT doc_id, i, array_to_string(w[i : i + 34], ' ') AS g FROM starts),
twice AS (SELECT doc_id, i FROM windows WHERE g IN (SELECT g FROM windows GROUP BY g HAVING count(*) > 1)),
places AS (SELECT doc_id, unnest(range(1, len(w) + 1)) AS p, unnest(w) AS word FROM words),
gone AS (SELECT DISTINCT doc_id, unnest(range(i, i + 35)) AS p FROM twice),
left_over AS (SELECT p.doc_id, p.p, p.word FROM places p ANTI JOIN gone g ON p.doc_id = g.doc_id AND p.p = g.p),
kept AS (SELECT doc_id, count(*) AS n, string_agg(word, ' ' ORDER BY p) AS t FROM left_over GROUP BY doc_id)
SELECT words.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(len(w) - coalesce(n, 0) AS BIGINT) AS n_removed, sha256(coalesce(t, '')) AS kept_sha256
FROM words LEFT JOIN kept USING (doc_id)"""

_NEAREST = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND vec_id IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 {zero}),
pairs AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, {score} AS score FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.e) = len(c.e) WHERE q.vec_id % 20 = 0),
ranked AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS r FROM pairs)
SELECT query_id, CAST(r AS INTEGER) AS rank, vec_id, score FROM ranked WHERE r <= 20"""

ORACLE_SQL: dict[str, str] = {
    "op2_substring_dedup": _REPEATS,
    "op8_metric_tree": _NEAREST.format(zero="", score="CAST(list_dot_product(list_transform(q.e, lambda x: floor(64 * x)), list_transform(c.e, lambda x: floor(64 * x))) AS BIGINT)"),
}
