"""The methods that counting is compared with."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import without
from .cells import cell_frequencies
from .volumes import Star


def full_join(star: Star, hint: str | None = None) -> DataFrame:
    """Every result as ``(terms)``, joined leaf by leaf; ``hint`` is a join strategy."""
    out = star.root
    for i, (key, leaf) in enumerate(zip(star.keys, star.leaves)):
        side = leaf.rows.select(F.col("key").alias(f"_k{i}"), F.col("terms").alias(f"_t{i}"))
        out = out.join(side.hint(hint) if hint else side, F.col(key) == F.col(f"_k{i}"))
    return out.select(F.concat("terms", *[f"_t{i}" for i in range(len(star.leaves))]).alias("terms"))


def count_results(results: DataFrame, drop: Sequence[str] = ()) -> DataFrame:
    return results.select(F.explode(without(F.col("terms"), drop)).alias("term")).groupBy("term").agg(F.count("*").alias("freq"))


def straightforward(star: Star, drop: Sequence[str] = ()) -> DataFrame:
    """Join everything, then count."""
    return count_results(full_join(star), drop)


def binary_cascade(star: Star, drop: Sequence[str] = ()) -> DataFrame:
    """Two-way shuffled joins in a row, each result moved to the next."""
    return count_results(full_join(star, "merge"), drop)


def two_scans(star: Star, drop: Sequence[str] = ()) -> DataFrame:
    """The counting method of one machine: one task scans the leaves for their numbers, then the facts, then the leaves' texts."""
    return cell_frequencies(star, [1] * len(star.leaves), drop=drop, prune=False)


def precomputed(star: Star, path: str, drop: Sequence[str] = ()) -> DataFrame:
    """Count over results that were joined and stored beforehand in ``path``."""
    full_join(star).write.mode("overwrite").parquet(path)
    return count_results(star.root.sparkSession.read.parquet(path), drop)
