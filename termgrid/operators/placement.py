"""Uneven cells: sampled costs and the placement of cells on slots."""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .grid import fact_cell, leaf_cells
from .volumes import Leaf, Star

# ---- samples ---------------------------------------------------------------------------------------------------------


def sample_simple(df: DataFrame, fraction: float, seed: int = 7) -> DataFrame:
    return df.sample(False, fraction, seed)


def sample_hash(df: DataFrame, column: str, m: int, below: int, prime: int = 7919) -> DataFrame:
    """A sample that any engine repeats: rows with ``key * prime mod m < below``; the fraction is ``below / m``."""
    return df.where(F.pmod(F.col(column) * prime, F.lit(m)) < below)


def sample_stratified(df: DataFrame, column: str, fractions: dict, seed: int = 7) -> DataFrame:
    return df.sampleBy(column, fractions, seed)


def sample_systematic(df: DataFrame, order: Sequence[str], step: int, start: int = 0, by: Sequence[str] = ()) -> DataFrame:
    """Every ``step``-th row in order; ``by`` numbers rows apart for each value, else one task numbers all."""
    n = F.row_number().over(Window.partitionBy(*by).orderBy(*order)) - 1
    return df.withColumn("_n", n).where(F.col("_n") % step == start).drop("_n")


def sampled(star: Star, m: int, below: int) -> Star:
    """The star over hash samples of its root (by the first key) and leaves."""
    return Star(sample_hash(star.root, star.keys[0], m, below), star.keys, [Leaf(sample_hash(x.rows, "key", m, below), x.unique, x.name) for x in star.leaves])


# ---- costs -----------------------------------------------------------------------------------------------------------


def plain_cost(facts: Column, leaves: Sequence[Column], joins: Column) -> Column:
    """The cost of a cell: facts and leaf rows that it gets, and results that it makes."""
    out = facts + joins
    for x in leaves:
        out = out + x
    return out


def cell_costs(star: Star, shares: Sequence[int], fraction: float = 1.0, kind: str = "xxhash", cost: Callable = plain_cost) -> DataFrame:
    """``(cell, fact_est, leaf_est_1.., join_est, cost)`` of every cell that has facts.

    Rows are counted on (samples of) the tables and scaled. Results are estimated as facts times, for each leaf, rows for
    each distinct key of the slice, as if keys were uniform.
    """
    up = 1.0 / fraction
    out = star.root.groupBy(fact_cell(star.keys, shares, kind).alias("cell")).agg((F.count("*") * F.lit(up)).alias("fact_est"))
    per_key = []
    for i, leaf in enumerate(star.leaves):
        slices = leaf.rows.where("key is not null").select("key", F.element_at(leaf_cells(F.col("key"), i, shares, kind), 1).alias("first"))
        # a slice is named by its first cell; it is as good as one row for each bucket of the axis
        sums = slices.groupBy("first").agg((F.count("*") * F.lit(up)).alias(f"leaf_est_{i + 1}"), F.countDistinct("key").alias("v"))
        after = math.prod(shares[i + 1 :])
        first = (F.floor(F.col("cell") / after) % shares[i] * after).cast("int")
        sums = sums.withColumnRenamed("first", "_f").withColumn(f"per_{i + 1}", F.col(f"leaf_est_{i + 1}") / (F.col("v") * F.lit(up))).drop("v")
        out = out.join(sums, first == F.col("_f"), "left").drop("_f").na.fill(0.0, [f"leaf_est_{i + 1}", f"per_{i + 1}"])
        per_key.append(F.col(f"per_{i + 1}"))
    joins = F.col("fact_est")
    for p in per_key:
        joins = joins * p
    leaves = [F.col(f"leaf_est_{i + 1}") for i in range(len(star.leaves))]
    out = out.withColumn("join_est", joins)
    return out.withColumn("cost", cost(F.col("fact_est"), leaves, F.col("join_est"))).select("cell", "fact_est", *[f"leaf_est_{i + 1}" for i in range(len(star.leaves))], "join_est", "cost")


def useful_leaf_rows(star: Star, axis: int, shares: Sequence[int], kind: str = "xxhash") -> DataFrame:
    """Copies of a leaf for cells that have facts only."""
    occupied = star.root.select(fact_cell(star.keys, shares, kind).alias("cell")).distinct()
    copies = star.leaves[axis].rows.select(F.explode(leaf_cells(F.col("key"), axis, shares, kind)).alias("cell"), "key")
    return copies.join(occupied, "cell", "left_semi")


def prune_dangling(star: Star) -> DataFrame:
    """Root rows that every leaf matches; semi-joins on keys only."""
    out = star.root
    for key, leaf in zip(star.keys, star.leaves):
        out = out.join(leaf.rows.select(F.col("key").alias("_k")), F.col(key) == F.col("_k"), "left_semi")
    return out


# ---- placement -------------------------------------------------------------------------------------------------------


def place_greedy(costs: dict[int, float], slots: int) -> dict[int, int]:
    """Costliest cell first, each on the slot with the least load so far."""
    heap = [(0.0, s) for s in range(slots)]
    out = {}
    for cell, cost in sorted(costs.items(), key=lambda x: (-x[1], x[0])):
        load, slot = heapq.heappop(heap)
        out[cell] = slot
        heapq.heappush(heap, (load + cost, slot))
    return out


def place_one_each(costs: dict[int, float], slots: int) -> dict[int, int]:
    return {cell: cell for cell in costs}


def place_round_robin(costs: dict[int, float], slots: int) -> dict[int, int]:
    return {cell: cell % slots for cell in costs}


def place_by_facts(costs: DataFrame, slots: int) -> dict[int, int]:
    """Greedy on fact rows alone."""
    return place_greedy({r.cell: r.fact_est for r in costs.select("cell", "fact_est").collect()}, slots)


def costs_of(costs: DataFrame) -> dict[int, float]:
    """Costs on the driver: one row for each cell, of which there are as many as the shares say."""
    return {r.cell: float(r.cost) for r in costs.select("cell", "cost").collect()}


def slot_loads(star: Star, shares: Sequence[int], slots: dict[int, int], kind: str = "xxhash") -> DataFrame:
    """``(slot, facts, copies, records)``: what each slot gets, leaf rows once for each slot."""
    from .grid import slot_map

    place = slot_map(slots)
    facts = star.root.select(place[fact_cell(star.keys, shares, kind)].alias("slot")).groupBy("slot").agg(F.count("*").alias("facts"))
    parts = None
    for i, leaf in enumerate(star.leaves):
        to = F.array_distinct(F.filter(F.transform(leaf_cells(F.col("key"), i, shares, kind), lambda c: place[c]), lambda s: s.isNotNull()))
        own = leaf.rows.where("key is not null").select(F.explode(to).alias("slot"))
        parts = own if parts is None else parts.unionByName(own)
    copies = parts.groupBy("slot").agg(F.count("*").alias("copies"))
    out = facts.join(copies, "slot", "full_outer").na.fill(0, ["facts", "copies"])
    return out.withColumn("records", F.col("facts") + F.col("copies"))


def salt_hot_keys(star: Star, axis: int, threshold: int, salts: int) -> Star:
    """Facts of keys with more than ``threshold`` of them spread over ``salts`` copies of the leaf key.

    All keys become strings, those of this axis with their salt; counts don't change, as each fact meets one copy.
    """
    key = star.keys[axis]
    hot = star.root.groupBy(key).agg(F.count("*").alias("n")).where(F.col("n") > threshold).select(F.col(key).alias("_h"))
    facts = star.root.join(hot, F.col(key) == F.col("_h"), "left")
    salt = F.when(F.col("_h").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64(*star.keys, "terms"), F.lit(salts))).cast("int")
    root = facts.withColumn("_s", salt).select(*[(F.concat_ws("#", F.col(k).cast("string"), F.col("_s").cast("string")) if k == key else F.col(k).cast("string")).alias(k) for k in star.keys], "terms")
    leaf = star.leaves[axis]
    rows = leaf.rows.join(hot, F.col("key") == F.col("_h"), "left")
    copies = F.when(F.col("_h").isNull(), F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.lit(salts - 1)))
    rows = rows.select("key", "terms", F.explode(copies).alias("_s")).select(F.concat_ws("#", F.col("key").cast("string"), F.col("_s").cast("string")).alias("key"), "terms")
    leaves = [Leaf(x.rows.withColumn("key", F.col("key").cast("string")), x.unique, x.name) for x in star.leaves]
    return Star(root, star.keys, [*leaves[:axis], Leaf(rows, leaf.unique, leaf.name), *leaves[axis + 1 :]], star.wide)
