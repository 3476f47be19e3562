"""Skewed copies of the line items: some rows repeated, others removed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def copies(profile: str) -> Column:
    """Copies of a row: ``hot_corner`` crowds one corner of two axes, ``half_idle`` leaves one half of an axis empty."""
    s, p = F.col("l_suppkey"), F.col("l_partkey")
    if profile == "hot_corner":
        return F.when((s % 10 == 0) & (p % 10 == 0), 40).when((s % 2 == 1) & (p % 2 == 1), 0).otherwise(1)
    if profile == "half_idle":
        return F.when(s % 10 == 0, 10).when(s % 2 == 1, 0).otherwise(1)
    raise ValueError(profile)


def make_skewed(lineitem: DataFrame, profile: str) -> DataFrame:
    n = copies(profile)
    return lineitem.where(n > 0).withColumn("_copy", F.explode(F.sequence(F.lit(1), n))).drop("_copy")
