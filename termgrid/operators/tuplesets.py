"""Tuple sets: the rows of a relation that hold exactly some of the keywords."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import Database
from ..functions.text import keyword_mask


def with_mask(df: DataFrame, keywords: Sequence[str]) -> DataFrame:
    """``df`` with ``kw_mask``; a table that was stored with it stays as it is."""
    return df if "kw_mask" in df.columns else df.withColumn("kw_mask", keyword_mask(F.col("terms"), keywords))


def tuple_set(df: DataFrame, keywords: Sequence[str], mask: int) -> DataFrame:
    """Rows whose keywords are exactly those of ``mask``; mask 0 is the free set."""
    return with_mask(df, keywords).where(F.col("kw_mask") == mask).drop("kw_mask")


def mask_histogram(db: Database, keywords: Sequence[str], relations: Sequence[str]) -> DataFrame:
    """``(relation, kw_mask, n)``: one scan of each relation, a few rows out."""
    parts = [with_mask(db.view(r), keywords).select(F.lit(r).alias("relation"), F.col("kw_mask").cast("long").alias("kw_mask")) for r in relations]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("relation", "kw_mask").agg(F.count("*").alias("n"))


class TaggedDatabase(Database):
    """A database whose relations were grouped by the keywords that their rows hold: a folder for each mask."""

    def __init__(self, db: Database, path: str, relations: Sequence[str]):
        super().__init__(db.spark, db.where, db.graph, db.tokenizer)
        self.path, self.tagged = path, frozenset(relations)

    def view(self, name: str, columns: Sequence[str] | None = None) -> DataFrame:
        if columns is not None or name not in self.tagged:
            return super().view(name, columns)
        schema = with_mask(super().view(name), ()).schema
        return self.spark.read.schema(schema).parquet(f"{self.path}/{name}")


def tag(db: Database, keywords: Sequence[str], relations: Sequence[str], path: str) -> TaggedDatabase:
    """Scans, tokenises and masks each relation once, into ``path``, partitioned by mask.

    Tuple sets of all networks of the query are then read folder by folder: a mask is a partition filter.
    """
    for name in relations:
        with_mask(db.view(name), keywords).write.partitionBy("kw_mask").parquet(f"{path}/{name}")
    return TaggedDatabase(db, path, relations)
