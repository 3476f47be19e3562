"""From raw documents to packed sequences: quality rules, line dedup, near-duplicate removal, mixing, packing.

Every stage reads whole texts and all rows that its predecessor kept, and runs over a table written before.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from termgrid.llm import line_dedup, minhash, mixing, packing, quality
from termgrid.llm.common import broadcast_below, checkpoint_folder, checkpointed, table, unused, word_count

#: Strings whose ids a worker of the last stage keeps: beside what the stages before have left in its executor, memory is short.
KEPT = 150_000
#: Largest table of rejected rows that is broadcast.
REJECTED_ROWS = 1_000_000


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows of ``docs`` that the base rules and the certified cutoffs keep.

    Null and empty texts fail the base rules; a null id is judged like others; rows of one id are judged by their texts.
    """
    key = F.xxhash64("text")
    judged = quality.judge(docs.withColumn("row_key", key), table(spark, sf_dir, "labels"), keep=("row_key",))
    bad, bad_key = unused("bad_id", docs), unused("bad_key", docs)
    rejected = broadcast_below(checkpointed(judged.where("not kept").select(F.col("doc_id").alias(bad), F.col("row_key").alias(bad_key)).distinct()), REJECTED_ROWS)
    return docs.join(rejected, F.col("doc_id").eqNullSafe(F.col(bad)) & key.eqNullSafe(F.col(bad_key)), "left_anti")


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """``docs`` less repeated lines; a document that loses all its words goes.

    ``n_chars`` is counted again where lines went. Rows without text or id stay as they are.
    """
    dropped = F.col(line_dedup.count_names(docs)[1])
    out = line_dedup.drop_repeated_lines(docs).where((dropped == 0) | (word_count(F.col("text")) > 0))
    return out.select(*[F.when(dropped > 0, F.length("text").cast(docs.schema[c].dataType)).otherwise(F.col(c)).alias(c) if c == "n_chars" else F.col(c) for c in docs.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document of smallest id of each group that shares 0.8 of its five-word shingles; rows without id or words stay."""
    return minhash.one_of_each(docs, width=5, percent=80)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix takes it; repeated rows share one decision."""
    return mixing.mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 2048 tokens with their place in a sequence."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"), kept=KEPT)


STAGES = [("quality rules", quality_rules), ("line dedup", drop_lines), ("near duplicates", near_duplicates), ("source mix", mix), ("best-fit packing", pack)]

#: Sketches, tokens and packing have no SQL form; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; what a stage returns is written to the shared folder and read again by the next."""
    docs, folder = table(spark, sf_dir, "documents"), f"{checkpoint_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES[:-1]):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
    return STAGES[-1][1](spark, docs, sf_dir)
