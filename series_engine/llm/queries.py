"""The thin query of each operator: (spark, sf_dir) -> DataFrame of digest columns."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import exact_dedup, langid, packing, pieces, pii, quality, simhash, substring_dedup, token_counts, urls
from .common import table, unsigned_hex


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tokens of every line of every document, each document encoded whole."""
    return token_counts.section_token_counts(table(spark, sf_dir, "documents")).withColumnRenamed("key", "doc_id")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_verdicts(table(spark, sf_dir, "documents"))


def op3_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = exact_dedup.duplicate_groups(table(spark, sf_dir, "documents"))
    return out.select(F.col("key").alias("doc_id"), F.col("keep").alias("keep_id"), "group_size", "kept", F.col("sha").alias("text_sha256"))


def op4_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.near_duplicates(table(spark, sf_dir, "documents"))
    return out.select(F.col("key").alias("doc_id"), unsigned_hex(F.col("fp")).alias("fingerprint"), F.col("component").alias("component_id"))


def op5_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return urls.url_verdicts(table(spark, sf_dir, "pages")).withColumnRenamed("key", "page_id")


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.find_personal_data(table(spark, sf_dir, "documents"))
    count = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select(F.col("key").alias("doc_id"), *map(count, pii.KINDS), F.sha2(pii.span_string(F.col("base")), 256).alias("base_sha256"), pii.span_string(F.col("spans")).alias("spans"))


def op7_sentence_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of every text and whether decoding gives it back."""
    return pieces.piece_digests(table(spark, sf_dir, "documents")).withColumnRenamed("key", "doc_id")


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held_out = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2
    model = langid.train(docs.where(~held_out & F.col("lang").isNotNull()))
    return langid.predict(docs.select("doc_id", "text", held_out.alias("held_out")), model, keep=("doc_id", "held_out"))


def op9_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.removal_digests(table(spark, sf_dir, "documents")).withColumnRenamed("key", "doc_id")


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents")).withColumnRenamed("key", "doc_id")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


QUERIES = {f.__name__: f for f in (op1_token_counts, op2_quality_rules, op3_exact_dedup, op4_simhash_dedup, op5_url_filter, op6_personal_data, op7_sentence_pieces, op8_language_id, op9_substring_dedup, op10_packing, pipeline)}
