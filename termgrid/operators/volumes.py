"""Volumes: in how many joined results a tuple occurs, counted without joining."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass
class Leaf:
    """Rows ``(key, terms)``; ``unique`` if no key repeats."""

    rows: DataFrame
    unique: bool = False
    name: str = ""


@dataclass
class Star:
    """A root with a column for each leaf's key, and the leaves in that order."""

    root: DataFrame
    keys: list[str] = field(default_factory=list)
    leaves: list[Leaf] = field(default_factory=list)
    #: counts as DECIMAL(38, 0), where products may leave 64 bits
    wide: bool = False

    def number(self) -> str:
        return "decimal(38,0)" if self.wide else "bigint"


def product(columns: Sequence[Column], kind: str = "bigint") -> Column:
    """Product in the number type of the plan; for decimals the type is kept at each step."""
    return reduce(lambda a, b: (a * b).cast(kind), columns, F.lit(1).cast(kind))


def combine_leaf(leaf: Leaf) -> DataFrame:
    """``(key, term, n)``: rows of one key merged to one bag of counts; the term null holds the number of its rows.

    A hot key's bag is many rows, each a partial sum in every task: no row grows with the number of its tuples.
    """
    return combine_fact(leaf.rows.where("key is not null"), ["key"])


def combine_fact(root: DataFrame, keys: Sequence[str]) -> DataFrame:
    """``(keys, term, n)``: root rows of equal keys merged to counts of their terms; the term null holds their number."""
    words = F.explode(F.concat("terms", F.array(F.lit(None).cast("string"))))
    return root.select(*keys, words.alias("term")).groupBy(*keys, "term").agg(F.count("*").alias("n"))


def num_array(leaf: Leaf, kind: str = "bigint") -> DataFrame:
    """``(key, num)``: the text stays behind, so only keys are counted and moved."""
    keys = leaf.rows.where("key is not null")
    if leaf.unique:
        return keys.select("key", F.lit(1).cast(kind).alias("num"))
    return keys.groupBy("key").agg(F.count("*").cast(kind).alias("num"))


def probed(star: Star, columns: Sequence[str] = ()) -> DataFrame:
    """Root rows that every leaf matches, with ``num_1..num_d``; ``columns`` of the root stay beside the keys.

    Counts are joined by key: Spark broadcasts them where they are small and shuffles else.
    """
    out = star.root.select(*star.keys, *columns)
    for i, (key, leaf) in enumerate(zip(star.keys, star.leaves, strict=True), 1):
        out = out.join(num_array(leaf, star.number()).select(F.col("key").alias(f"_k{i}"), F.col("num").alias(f"num_{i}")), F.col(key) == F.col(f"_k{i}")).drop(f"_k{i}")
    return out


def _nums(star: Star, but: int = -1) -> list[Column]:
    return [F.col(f"num_{j + 1}") for j in range(len(star.leaves)) if j != but]


def fact_volumes(star: Star) -> DataFrame:
    """``(keys, m, volume)``: for each composite key its rows and the results in which one of them occurs."""
    return probed(star).groupBy(*star.keys).agg(F.count("*").alias("m"), F.first(product(_nums(star), star.number())).alias("volume"))


def leaf_volumes(star: Star, only: int | None = None) -> DataFrame:
    """``(leaf, key, volume)``: results in which one tuple of a leaf key occurs, all leaves in one pass over the root.

    For leaf i a root row counts as the product of the other leaves' numbers. Partial sums by key keep the shuffle at one
    row for each key and task. ``only``: one leaf, from 1.
    """
    rows = probed(star)
    parts = [(i, key) for i, key in enumerate(star.keys, 1) if only in (None, i)]
    each = F.array(*[F.struct(F.lit(i).alias("leaf"), F.col(key).alias("key"), product(_nums(star, i - 1), star.number()).alias("part")) for i, key in parts])
    return rows.select(F.inline(each)).groupBy("leaf", "key").agg(F.sum("part").alias("volume"))


def leaf_rows(star: Star, columns: Sequence[str] = ("terms",)) -> DataFrame:
    """``(leaf, key, columns)`` of all leaves in one table, so that one join meets one table of volumes."""
    parts = [leaf.rows.select(F.lit(i).alias("leaf"), "key", *columns) for i, leaf in enumerate(star.leaves, 1)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def volume_records(star: Star) -> DataFrame:
    """``(node, key, volume, terms)`` of every tuple that occurs in a result; node 0 is the root (its key is null).

    The root is probed twice, whatever the number of leaves: for its own terms, and for all leaves' volumes.
    """
    root = probed(star, ["terms"]).select(F.lit(0).alias("node"), F.lit(None).cast("string").alias("key"), product(_nums(star), star.number()).alias("volume"), "terms")
    if not star.leaves:
        return root
    rows = leaf_rows(star).join(leaf_volumes(star), ["leaf", "key"])
    return root.unionByName(rows.select(F.col("leaf").alias("node"), F.col("key").cast("string").alias("key"), "volume", "terms"))


def result_count(star: Star) -> DataFrame:
    """The number of results of the network, without a result."""
    return probed(star).agg(F.coalesce(F.sum(product(_nums(star), star.number())), F.lit(0)).alias("n_results"))
