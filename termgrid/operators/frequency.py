"""Term frequencies from volumes, and the most frequent terms."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.text import without
from .volumes import Star, _nums, leaf_rows, leaf_volumes, probed, product, volume_records


def weighted_terms(records: DataFrame, emit: str = "each") -> DataFrame:
    """``(term, part)`` from ``(volume, terms)``: a row for each occurrence, or (``local``) for each distinct term of a tuple."""
    if emit == "each":
        return records.select(F.explode("terms").alias("term"), F.col("volume").alias("part"))
    distinct = records.select("terms", "volume", F.explode(F.array_distinct("terms")).alias("term"))
    return distinct.select("term", (F.col("volume") * F.size(F.filter("terms", lambda t: t == F.col("term")))).alias("part"))


def sum_terms(parts: DataFrame) -> DataFrame:
    """``(term, freq)``; sums are partial in each task before the shuffle by term."""
    return parts.groupBy("term").agg(F.sum("part").alias("freq"))


def star_frequencies(star: Star, drop: Sequence[str] = (), emit: str = "each") -> DataFrame:
    """``(term, freq)`` of a star by its volumes: each tuple's terms weigh as many results as it occurs in."""
    records = volume_records(star).select("volume", without(F.col("terms"), drop).alias("terms"))
    return sum_terms(weighted_terms(records, emit))


def star_frequencies_by_key(star: Star, drop: Sequence[str] = ()) -> DataFrame:
    """The same from term counts by key: leaf texts shrink to (key, term, count) before they meet the volumes."""
    clean = lambda df: df.withColumn("terms", without(F.col("terms"), drop))
    out = clean(probed(star, ["terms"])).select(F.explode("terms").alias("term"), product(_nums(star), star.number()).alias("part"))
    if star.leaves:
        counts = clean(leaf_rows(star)).select("leaf", "key", F.explode("terms").alias("term")).groupBy("leaf", "key", "term").agg(F.count("*").alias("n"))
        rows = counts.join(leaf_volumes(star), ["leaf", "key"])
        out = out.unionByName(rows.select("term", (F.col("n") * F.col("volume")).cast(star.number()).alias("part")))
    return sum_terms(out)


def total_frequencies(each: Sequence[DataFrame]) -> DataFrame:
    """Frequencies summed over networks; no result belongs to two of them."""
    out = each[0].select("term", F.col("freq").alias("part"))
    for df in each[1:]:
        out = out.unionByName(df.select("term", F.col("freq").alias("part")))
    return sum_terms(out)


def top_terms(freq: DataFrame, k: int, ties: str = "cut", by: Sequence[str] = ()) -> DataFrame:
    """The k most frequent terms with their rank, equal ones by term; ``ties="all"`` keeps all that equal the k-th.

    ``by``: a top k for each value of these columns.
    """
    order = [F.desc("freq"), F.asc("term")]
    if by or ties == "all":
        w = Window.partitionBy(*by).orderBy(F.desc("freq")) if ties == "all" else Window.partitionBy(*by).orderBy(*order)
        rank: Column = F.rank().over(w) if ties == "all" else F.row_number().over(w)
        # Spark limits each group to its first k rows in every task before the window's shuffle
        return freq.withColumn("rank", rank.cast("long")).where(F.col("rank") <= k)
    top = freq.orderBy(*order).limit(k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy(*order)).cast("long"))
