"""Networks of any shape: two sweeps of counts over the tree, or joins until a star is left."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..catalog import Database
from ..functions.text import without
from ..plans.networks import Node
from .frequency import sum_terms
from .tuplesets import tuple_set
from .volumes import Leaf, Star, product


@dataclass
class Branch:
    """A tuple set with rows ``(columns, terms)`` and its children as (own column, their column, branch)."""

    rows: DataFrame
    children: list[tuple[str, str, Branch]] = field(default_factory=list)
    name: str = ""
    unique: tuple[str, ...] = ()


def compile_tree(db: Database, keywords: Sequence[str], node: Node, tuples: bool = False) -> Branch:
    """A network as unresolved plans: exact tuple sets hung on each other.

    ``tuples``: rows carry the name of their relation and their keys, as an array of one string.
    """
    rows = tuple_set(db.view(node.relation), keywords, node.mask)
    if tuples:
        rows = rows.withColumn("tuples", F.array(F.concat_ws(":", F.lit(node.relation), *[F.col(k).cast("string") for k in db.graph.relations[node.relation].keys])))
    return Branch(rows, [(c.on[0], c.on[1], compile_tree(db, keywords, c, tuples)) for c in node.children], node.relation, db.graph.relations[node.relation].unique)


def _upward(b: Branch) -> tuple[DataFrame, list]:
    """Rows of ``b`` with, for each child, the number of results below that match; rows without one are gone."""
    df, below = b.rows, []
    for i, (own, other, child) in enumerate(b.children):
        rows, lower = _upward(child)
        below.append((rows, lower))
        n = product([F.col(f"n{j}") for j in range(len(child.children))])
        counts = rows.select(F.col(other).alias("k"), n.alias("n")).groupBy("k").agg(F.sum("n").alias(f"n{i}")).withColumnRenamed("k", f"k{i}")
        df = df.join(counts, F.col(own) == F.col(f"k{i}")).drop(f"k{i}")
    return df, below


def tree_records(b: Branch) -> DataFrame:
    """``(node, volume, terms)``: counts go up from the leaves, contexts come down from the root; only keys and counts move."""
    out: list[DataFrame] = []

    def downward(b: Branch, rows: DataFrame, below: list, name: str) -> None:
        ns = [F.col(f"n{i}") for i in range(len(b.children))]
        out.append(rows.select(F.lit(name).alias("node"), product([F.col("context"), *ns]).alias("volume"), "terms"))
        for i, ((own, other, child), (lower, deeper)) in enumerate(zip(b.children, below)):
            part = product([F.col("context"), *[n for j, n in enumerate(ns) if j != i]])
            context = rows.select(F.col(own).alias("k"), part.alias("c")).groupBy("k").agg(F.sum("c").alias("context"))
            downward(child, lower.join(context, F.col(other) == F.col("k")).drop("k"), deeper, f"{name}.{i}")

    rows, below = _upward(b)
    downward(b, rows.withColumn("context", F.lit(1).cast("bigint")), below, "0")
    all_ = out[0]
    for df in out[1:]:
        all_ = all_.unionByName(df)
    return all_


def tree_frequencies(b: Branch, drop: Sequence[str] = ()) -> DataFrame:
    return sum_terms(tree_records(b).select(F.explode(without(F.col("terms"), drop)).alias("term"), F.col("volume").alias("part")))


def joined(b: Branch) -> DataFrame:
    """The branch and all below it as joined rows with one bag: its own columns and ``terms`` (and ``tuples``)."""
    df = b.rows
    bags = [c for c in ("terms", "tuples") if c in df.columns]
    for own, other, child in b.children:
        below = joined(child).select(F.col(other).alias("_k"), *[F.col(c).alias(f"_{c}") for c in bags])
        df = df.join(below, F.col(own) == F.col("_k")).withColumns({c: F.concat(c, f"_{c}") for c in bags}).drop("_k", *[f"_{c}" for c in bags])
    return df


def starify(b: Branch) -> Star:
    """A star: children of the root with children of their own are joined with these, leaf by leaf."""
    keys, leaves = [], []
    for own, other, child in b.children:
        alias = f"key_{len(keys) + 1}"
        keys.append((alias, own))
        rows = joined(child)
        # a join with unique parents keeps the child's key unique
        whole = other in child.unique and all(o in c.unique for _, o, c in child.children)
        leaves.append(Leaf(rows.select(F.col(other).alias("key"), "terms"), whole, child.name))
    root = b.rows.select(*[F.col(own).alias(a) for a, own in keys], "terms")
    return Star(root, [a for a, _ in keys], leaves)


def joined_size(left: DataFrame, right: DataFrame, own: str, other: str, exact: bool = False) -> DataFrame:
    """``(n,)``: the estimated rows of an equi-join: the rows of both sides over the larger number of distinct keys (estimated, or ``exact``)."""
    side = lambda df, c, x: df.agg(F.count(c).alias(f"n{x}"), F.countDistinct(c).alias(f"v{x}") if exact else F.approx_count_distinct(c).alias(f"v{x}"))
    return side(left, own, "a").crossJoin(side(right, other, "b")).select((F.col("na") * F.col("nb") / F.greatest("va", "vb", F.lit(1))).alias("n"))


def choose_merges(sizes: dict[tuple[str, str], float]) -> list[tuple[str, str]]:
    """The order in which pairs of relations are joined: the smallest estimated result first, equal ones by name."""
    return sorted(sizes, key=lambda p: (sizes[p], p))
