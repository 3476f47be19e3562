"""Queries of the corpus operators: each applies its operator to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import binary_output, html_text, langid, licenses, line_dedup, minhash, mixing, packing, quality, vector_dedup
from .common import table


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = mixing.mix(table(spark, sf_dir, "documents").select("doc_id", "text", "source"))
    return out.select("doc_id", *[F.col(f"mix_{c}").alias(c) for c in ("size", "source_size", "target", "taken")])


def op2_token_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    path = binary_output.fresh_path(spark)
    binary_output.write(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"), 2, path)
    return binary_output.read_digests(spark, path)


def token_shard_lookup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Keyed access to the shards of ``op2_token_shards``: every document whose id is divisible by 20, by its key."""
    import public_tokenizers

    docs, path = table(spark, sf_dir, "documents"), binary_output.fresh_path(spark)
    binary_output.write(docs, public_tokenizers.path("word_bpe_49k.json"), 2, path)
    found = binary_output.lookup(spark, path, docs.select("doc_id").where("doc_id % 20 = 0"))
    return found.select("doc_id", F.size("ids").cast("long").alias("n_tokens"), "ids_crc32")


def op3_vector_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_dedup.near_duplicate_vectors(table(spark, sf_dir, "embeddings"))


def op4_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents"), width=3, percent=85)


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(table(spark, sf_dir, "documents"))


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))


def op7_html_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = quality.judge(table(spark, sf_dir, "documents").select("doc_id", "text", "lang"), table(spark, sf_dir, "labels"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.drop_repeated_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.col("tpl_lines").alias("n_lines"), F.col("tpl_dropped").alias("n_dropped"), F.length("text").cast("long").alias("n_chars_left"), F.md5("text").alias("text_md5"))


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = licenses.scan(table(spark, sf_dir, "documents"), "doc_id")
    return out.withColumn("licenses", F.array_join("licenses", ","))


QUERIES = {
    "op1_mix_sources": op1_mix_sources,
    "op2_token_shards": op2_token_shards,
    "token_shard_lookup": token_shard_lookup,
    "op3_vector_dedup": op3_vector_dedup,
    "op4_minhash_dedup": op4_minhash_dedup,
    "op5_language_id": op5_language_id,
    "op6_best_fit_packing": op6_best_fit_packing,
    "op7_html_main_text": op7_html_main_text,
    "op8_quality_rules": op8_quality_rules,
    "op9_line_dedup": op9_line_dedup,
    "op10_license_scan": op10_license_scan,
}
ORACLES = {"op1_mix_sources": mixing.SQL, "op8_quality_rules": quality.SQL, "op9_line_dedup": line_dedup.SQL, "op10_license_scan": licenses.SQL}
