"""Counting inside the slots of a grid: build from leaf rows, probe with facts, emit weighted terms, in one pass."""

from __future__ import annotations

import math
from collections.abc import Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.text import without
from ..shipping import shipped
from .frequency import sum_terms
from .grid import fact_cell, leaf_cells, slot_map
from .volumes import Star

#: Terms that a slot sums up before it passes their sums on.
HELD_TERMS = 1 << 20


def dealt(star: Star, shares: Sequence[int], slots: dict[int, int] | None = None, drop: Sequence[str] = (), kind: str = "xxhash", prune: bool = True) -> DataFrame:
    """``(slot, tag, k1..kd, terms)``: facts in the slot of their cell, leaf rows once in each slot that has a cell of their slice.

    ``tag`` is the number of the leaf, from 0, and the number of leaves for facts, so leaf rows sort before facts. With
    ``prune`` no copy goes to a cell without facts: occupied cells are a table of at most as many rows as the grid has cells.
    """
    d = len(star.leaves)
    slots = slots or {c: c for c in range(math.prod(shares))}
    place = slot_map(slots)
    keys = [f"k{i + 1}" for i in range(d)]
    whole = ("tinyint", "smallint", "int", "bigint")
    kind_of = "long" if all(t in whole for _, t in [*star.root.select(*star.keys).dtypes, *[x.rows.select("key").dtypes[0] for x in star.leaves]]) else "string"
    facts = star.root.where(" and ".join(f"{k} is not null" for k in star.keys))
    facts = facts.withColumn("_cell", fact_cell(star.keys, shares, kind))
    out = facts.select(place[F.col("_cell")].alias("slot"), F.lit(d).alias("tag"), *[F.col(k).cast(kind_of).alias(n) for k, n in zip(star.keys, keys)], "terms")
    occupied = F.broadcast(facts.select(F.col("_cell").alias("cell")).distinct().agg(F.collect_set("cell").alias("_occupied"))) if prune else None
    for i, leaf in enumerate(star.leaves):
        rows = leaf.rows.where("key is not null")
        cells = leaf_cells(F.col("key"), i, shares, kind)
        if prune:
            rows = rows.crossJoin(occupied)
            cells = F.array_intersect(cells, F.col("_occupied"))
        rows = rows.withColumn("_slot", F.explode(F.array_distinct(F.transform(cells, lambda c: place[c]))))
        out = out.unionByName(rows.select(F.col("_slot").alias("slot"), F.lit(i).alias("tag"), *[(F.col("key").cast(kind_of) if j == i else F.lit(None).cast(kind_of)).alias(n) for j, n in enumerate(keys)], "terms"))
    return out.withColumn("terms", without(F.col("terms"), drop))


class _Slot:
    """The state of one slot: leaf keys with their numbers and texts, volumes so far, sums of terms."""

    def __init__(self, d: int):
        self.d, self.rows, self.sums = d, [[] for _ in range(d)], {}
        self.keys: list[np.ndarray] | None = None

    def leaf(self, i: int, part: pa.RecordBatch) -> None:
        self.rows[i].append((part.column(2 + i).to_numpy(zero_copy_only=False), part.column(2 + self.d)))

    def _build(self) -> None:
        self.keys, self.nums, self.inverse, self.volumes = [], [], [], []
        for rows in self.rows:
            every = np.concatenate([k for k, _ in rows]) if rows else np.zeros(0, np.int64)
            keys, inverse, nums = np.unique(every, return_inverse=True, return_counts=True)
            self.keys.append(keys)
            self.nums.append(nums)
            self.inverse.append(inverse)
            self.volumes.append(np.zeros(len(keys), np.int64))

    def facts(self, part: pa.RecordBatch) -> None:
        if self.keys is None:
            self._build()
        n = part.num_rows
        fits, at = np.ones(n, bool), []
        for i in range(self.d):
            k = part.column(2 + i).to_numpy(zero_copy_only=False)
            x = np.searchsorted(self.keys[i], k)
            x[x == len(self.keys[i])] = 0
            fits &= self.keys[i][x] == k if len(self.keys[i]) else False
            at.append(x)
        if not fits.any():
            return
        nums = [self.nums[i][at[i][fits]] for i in range(self.d)]
        for i in range(self.d):
            others = np.ones(int(fits.sum()), np.int64)
            for j in range(self.d):
                others = others * nums[j] if j != i else others
            np.add.at(self.volumes[i], at[i][fits], others)
        product = nums[0].astype(np.int64)
        for x in nums[1:]:
            product = product * x
        weight = np.zeros(n, np.int64)
        weight[fits] = product
        self._add(part.column(2 + self.d), weight)

    def _add(self, terms: pa.Array, weight: np.ndarray) -> None:
        """Adds each row's weight to the sums of its terms."""
        sizes = np.diff(terms.offsets.to_numpy())
        words = terms.flatten().dictionary_encode()
        sums = np.zeros(len(words.dictionary), np.int64)
        np.add.at(sums, words.indices.to_numpy(), np.repeat(weight, sizes))
        some = np.flatnonzero(sums)
        for term, x in zip(words.dictionary.take(pa.array(some)).to_pylist(), sums[some].tolist()):
            self.sums[term] = self.sums.get(term, 0) + x

    def taken(self) -> pa.RecordBatch:
        out = pa.RecordBatch.from_arrays([pa.array(list(self.sums), pa.string()), pa.array(list(self.sums.values()), pa.int64())], ["term", "part"])
        self.sums = {}
        return out

    def close(self) -> pa.RecordBatch:
        """Leaf texts weigh the volumes that this slot's facts gave their keys."""
        if self.keys is not None:
            for i, rows in enumerate(self.rows):
                volume, start = self.volumes[i][self.inverse[i]], 0
                for keys, terms in rows:
                    self._add(terms, volume[start : start + len(keys)])
                    start += len(keys)
        return self.taken()


def _counted(d: int):
    """Over rows sorted by slot and tag: ``(term, part)``; only a slot's leaf rows are held, facts pass through."""

    def run(batches):
        slot, state = None, None
        for batch in batches:
            if not batch.num_rows:
                continue
            marks = np.stack([batch.column(0).to_numpy(), batch.column(1).to_numpy()], 1)
            edges = [0, *(np.flatnonzero((marks[1:] != marks[:-1]).any(1)) + 1).tolist(), len(marks)]
            for a, b in zip(edges, edges[1:]):
                if state is None or marks[a][0] != slot:
                    if state is not None:
                        yield state.close()
                    slot, state = marks[a][0], _Slot(d)
                part = batch.slice(a, b - a)
                state.facts(part) if marks[a][1] == d else state.leaf(int(marks[a][1]), part)
                if len(state.sums) > HELD_TERMS:
                    yield state.taken()
        if state is not None:
            yield state.close()

    return run


def cell_frequencies(star: Star, shares: Sequence[int], slots: dict[int, int] | None = None, drop: Sequence[str] = (), kind: str = "xxhash", prune: bool = True) -> DataFrame:
    """``(term, freq)`` counted slot by slot: one shuffle by slot, then each slot alone, then sums by term.

    A slot gets its leaf rows first and keeps them (number and text of each key); facts stream past, each adding its terms
    and its part of the volumes; at the end the leaf texts are weighed. As each fact is in one slot, the sums over slots
    are the answer. A task holds the leaf rows of one slot, so the shares must be so fine that these fit. Keys that are
    not whole numbers are compared as strings; sums are 64-bit. Rows with null keys join nothing. Without leaves every root row counts once.
    """
    if star.wide:
        raise ValueError("slots count in 64 bits; use star_frequencies for wide counts")
    if not star.leaves:
        return sum_terms(star.root.select(F.explode(without(F.col("terms"), drop)).alias("term"), F.lit(1).cast("bigint").alias("part")))
    rows = dealt(star, shares, slots, drop, kind, prune)
    n = len(set((slots or {c: c for c in range(math.prod(shares))}).values()))
    # as many partitions as slots: two slots may share a task, which then takes one after the other
    rows = shipped(rows).repartition(n, "slot").sortWithinPartitions("slot", "tag")
    return sum_terms(rows.mapInArrow(_counted(len(star.leaves)), "term string, part bigint"))
