"""The replicating grid: shares of its axes, cells of facts and leaf copies, counting in cells."""

from __future__ import annotations

import itertools
import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .frequency import sum_terms
from .volumes import Star, leaf_rows, num_array, product

# ---- shares and cost -------------------------------------------------------------------------------------------------


def star_cost(facts: float, leaves: Sequence[float], shares: Sequence[float]) -> float:
    """Rows sent: each fact once, each leaf row to all cells of its slice."""
    k = math.prod(shares)
    return facts + sum(n * k / a for n, a in zip(leaves, shares, strict=True))


def star_shares(leaves: Sequence[float], cells: int, mode: str = "proportional") -> list[float]:
    """Real shares with the product ``cells``: proportional to leaf sizes (the least cost), or equal."""
    d = len(leaves)
    if mode == "equal":
        return [cells ** (1 / d)] * d
    mean = math.prod(max(n, 1) for n in leaves) ** (1 / d)
    return [max(n, 1) / mean * cells ** (1 / d) for n in leaves]


def clamped_shares(leaves: Sequence[float], cells: int) -> list[float]:
    """Least-cost shares of at least 1: shares below are fixed at 1, the others solved again."""
    fixed: set[int] = set()
    while True:
        free = [i for i in range(len(leaves)) if i not in fixed]
        if not free:
            return [1.0] * len(leaves)
        got = dict(zip(free, star_shares([leaves[i] for i in free], cells)))
        low = {i for i in free if got[i] < 1}
        if not low:
            return [got.get(i, 1.0) for i in range(len(leaves))]
        fixed |= low


def integer_shares(leaves: Sequence[float], cells: int, rounding: str = "search", mode: str = "proportional") -> list[int]:
    """Whole shares: real ones rounded down (at least 1), or the cheapest vector that uses the most cells it can.

    The search ranks vectors with product <= cells by the load of a cell, then by rows sent.
    """
    if rounding == "floor":
        return [max(1, math.floor(a + 1e-9)) for a in star_shares(leaves, cells, mode)]
    best = None
    for head in itertools.product(*[range(1, cells + 1)] * (len(leaves) - 1)):
        used = math.prod(head)
        if used > cells:
            continue
        shares = [*head, cells // used]
        key = (-math.prod(shares), star_cost(0, leaves, shares), shares)
        if best is None or key < best:
            best = key
    return list(best[2])


def triangle_cost(r: float, s: float, t: float, shares: Sequence[float]) -> float:
    """Rows sent for R(A,B), S(B,C), T(A,C) on a grid a * b * c: each is copied along the axis it lacks."""
    a, b, c = shares
    return r * c + s * a + t * b


def triangle_shares(r: float, s: float, t: float, cells: float) -> tuple[float, float, float]:
    """Shares that make the three terms of the cost equal, each (cells * r * s * t) ** (1/3)."""
    each = (cells * r * s * t) ** (1 / 3)
    return each / s, each / t, each / r


def max_cell_load(per_axis: int, buckets: int, used: int, axes: int = 3) -> float:
    """Results of the hottest cell if ``used`` of ``buckets`` on each axis hold all n keys of every axis."""
    return (per_axis / min(used, buckets)) ** axes


# ---- buckets and cells -----------------------------------------------------------------------------------------------


def bucket(key: Column, share: int, kind: str = "xxhash") -> Column:
    """Bucket of a key: ``xxhash`` (default), ``mod`` of an integer key, or ``hash`` with the sign bit masked."""
    if kind == "mod":
        return F.pmod(key, F.lit(share)).cast("int")
    if kind == "hash":
        return F.pmod(F.hash(key).bitwiseAND(0x7FFFFFFF), F.lit(share)).cast("int")
    return F.pmod(F.xxhash64(key), F.lit(share)).cast("int")


def numbered_buckets(keys: DataFrame, key: str, share: int) -> DataFrame:
    """``(key, number, bucket)``: distinct keys numbered from 1 in order, then modulo.

    For small key sets: numbering needs one sorted task. ``bucket`` needs none.
    """
    n = F.row_number().over(Window.orderBy(key)).cast("long")
    return keys.select(key).distinct().withColumn("number", n).withColumn("bucket", (F.col("number") % share).cast("int"))


def fact_cell(keys: Sequence[str], shares: Sequence[int], kind: str = "xxhash") -> Column:
    """The one cell of a fact: its buckets as the digits of a number in mixed radix."""
    cell = F.lit(0)
    for k, a in zip(keys, shares, strict=True):
        cell = cell * a + bucket(F.col(k), a, kind)
    return cell.cast("int")


def leaf_cells(key: Column, axis: int, shares: Sequence[int], kind: str = "xxhash") -> Column:
    """Array of the cells of a leaf key's slice: all that have its bucket on its axis."""
    after = math.prod(shares[axis + 1 :])
    others = [outer * shares[axis] * after + inner for outer in range(math.prod(shares[:axis])) for inner in range(after)]
    return F.transform(F.array(*[F.lit(o) for o in others]), lambda o: (o + bucket(key, shares[axis], kind) * after).cast("int"))


def fact_cells(star: Star, shares: Sequence[int], kind: str = "xxhash") -> DataFrame:
    """``(cell, n)`` facts in each cell that has any."""
    return star.root.groupBy(fact_cell(star.keys, shares, kind).alias("cell")).agg(F.count("*").alias("n"))


def leaf_copies(star: Star, shares: Sequence[int], kind: str = "xxhash", columns: Sequence[str] = ()) -> DataFrame:
    """``(leaf, cell, key, columns)``: every leaf row in every cell of its slice."""
    parts = [leaf.rows.select(F.lit(i + 1).alias("leaf"), F.explode(leaf_cells(F.col("key"), i, shares, kind)).alias("cell"), F.col("key"), *columns) for i, leaf in enumerate(star.leaves)]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# ---- counting on the grid --------------------------------------------------------------------------------------------


def slot_map(cells: dict[int, int]) -> Column:
    """Cell -> slot as a literal map; the number of cells is a parameter, not data."""
    return F.create_map(*[F.lit(x) for kv in sorted(cells.items()) for x in kv])


def grid_frequencies(star: Star, shares: Sequence[int], slots: dict[int, int] | None = None, kind: str = "xxhash", prune: bool = True, dedupe: bool = True, drop: Sequence[str] = ()) -> DataFrame:
    """``(term, freq)`` with the slots of a grid as a further join key.

    Facts get the slot of their cell; the numbers of leaf keys are copied to the slots of their slice, once for each slot if
    ``dedupe``, and meet the facts there by ordinary joins on (slot, key). ``prune`` sends no copy to cells without facts.
    The parts of a volume are summed over slots before the leaf texts meet them, by one join without slots: texts are never
    copied. ``cells.cell_frequencies`` counts inside the slots instead.
    """
    from ..functions.text import without

    cells = math.prod(shares)
    slots = slots or {c: c for c in range(cells)}
    place = slot_map(slots)
    facts = star.root.select(*star.keys, "terms", fact_cell(star.keys, shares, kind).alias("cell"))
    occupied = facts.select("cell").distinct()
    probe = facts.withColumn("slot", place[F.col("cell")])
    if dedupe is False:
        probe = probe.withColumn("slot", F.col("cell"))
    number = star.number()
    nums = []
    for i, (key, leaf) in enumerate(zip(star.keys, star.leaves), 1):
        copies = num_array(leaf, number).withColumnRenamed("num", f"num_{i}")
        copies = copies.select(F.explode(leaf_cells(F.col("key"), i - 1, shares, kind)).alias("cell"), "key", f"num_{i}")
        if prune:
            copies = copies.join(occupied, "cell", "left_semi")
        copies = copies.withColumn("slot", place[F.col("cell")] if dedupe else F.col("cell")).select("slot", F.col("key").alias(f"_k{i}"), f"num_{i}").dropDuplicates(["slot", f"_k{i}"])
        nums.append(copies)
        probe = probe.join(copies.withColumnRenamed("slot", f"_s{i}"), (F.col("slot") == F.col(f"_s{i}")) & (F.col(key) == F.col(f"_k{i}"))).drop(f"_s{i}", f"_k{i}")
    ns = [F.col(f"num_{i + 1}") for i in range(len(star.leaves))]
    out = probe.select(F.explode(without(F.col("terms"), drop)).alias("term"), product(ns, number).alias("part"))
    each = F.array(*[F.struct(F.lit(i + 1).alias("leaf"), F.col(key).alias("key"), product([n for j, n in enumerate(ns) if j != i], number).alias("part")) for i, key in enumerate(star.keys)])
    local = probe.select("slot", F.inline(each)).groupBy("slot", "leaf", "key").agg(F.sum("part").alias("volume"))
    volumes = local.groupBy("leaf", "key").agg(F.sum("volume").alias("volume"))
    rows = leaf_rows(star).join(volumes, ["leaf", "key"])
    out = out.unionByName(rows.select(F.explode(without(F.col("terms"), drop)).alias("term"), F.col("volume").alias("part")))
    return sum_terms(out)


def grid_triangle_join(r: DataFrame, s: DataFrame, t: DataFrame, shares: Sequence[int], kind: str = "xxhash") -> DataFrame:
    """R(a,b) join S(b,c) join T(a,c) in one round: each row is copied along the axis it lacks, cells join alone."""
    na, nb, nc = shares

    def cell(x: Column, y: Column, z: Column) -> Column:
        return ((x * nb + y) * nc + z).cast("int")

    ab, bb, cb = (lambda x: bucket(x, na, kind)), (lambda x: bucket(x, nb, kind)), (lambda x: bucket(x, nc, kind))
    rc = r.select("a", "b", F.explode(F.sequence(F.lit(0), F.lit(nc - 1))).alias("z")).withColumn("cell", cell(ab(F.col("a")), bb(F.col("b")), F.col("z")))
    sc = s.select("b", "c", F.explode(F.sequence(F.lit(0), F.lit(na - 1))).alias("z")).withColumn("cell", cell(F.col("z"), bb(F.col("b")), cb(F.col("c"))))
    tc = t.select("a", "c", F.explode(F.sequence(F.lit(0), F.lit(nb - 1))).alias("z")).withColumn("cell", cell(ab(F.col("a")), F.col("z"), cb(F.col("c"))))
    return rc.drop("z").join(sc.drop("z"), ["cell", "b"]).join(tc.drop("z"), ["cell", "a", "c"]).select("a", "b", "c")
