"""The experiments: times by job, shuffled bytes, growth, one machine against many, even and uneven placement."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import workloads
from .catalog import Database
from .functions.text import without
from .operators import baselines, cells, frequency, measures, skew, trees, tuplesets, volumes
from .queries.grids import SKEW_BATCHES, SKEW_GRIDS, skew_placement, skewed_star
from .queries.search import CHAIN_KW, MIX_KW, STAR_KW, SUPPLIER_KW
from .sources import shared_folder

SHAPES = {"star": (workloads.star, STAR_KW), "chain": (workloads.chain, CHAIN_KW), "mix": (workloads.mix, MIX_KW)}


def seconds(plan: DataFrame) -> float:
    began = time.perf_counter()
    plan.write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - began, 3)


def measured(spark: SparkSession, plan: DataFrame) -> tuple[float, int]:
    """Seconds of a plan and the bytes that it writes to shuffles."""
    before = measures.shuffle_bytes(spark)
    took = seconds(plan)
    return took, measures.shuffle_bytes(spark) - before


def star_for(db: Database, shape: str) -> tuple[volumes.Star, list[str]]:
    make, keywords = SHAPES[shape]
    return trees.starify(trees.compile_tree(db, keywords, make())), keywords


def job_split(db: Database, shape: str = "star") -> dict[str, float]:
    """Seconds of the first job (volumes, written) and of the second (term sums over them)."""
    star, keywords = star_for(db, shape)
    sums: Callable = lambda df: frequency.sum_terms(frequency.weighted_terms(df.select("volume", without(F.col("terms"), keywords).alias("terms"))))
    first, second = measures.stage_split(db.spark, volumes.volume_records(star), sums, shared_folder(db.spark))
    return {"volumes": round(first, 3), "frequencies": round(second, 3)}


def shuffle_share(db: Database, shape: str, input_bytes: int) -> dict[str, float]:
    """Time of the shape's first batch, and its shuffled bytes over those of the tables."""
    took, moved = measured(db.spark, workloads.batch_frequencies(db, shape, workloads.batch(shape, 0)))
    return {"seconds": took, "shuffle_mb": round(moved / 1e6, 3), "share_of_input": round(moved / max(1, input_bytes), 4)}


def one_machine(db: Database, join: bool = True) -> dict[str, float]:
    """The star with many results a key in one task, in the slots of a grid, by volumes, and (``join``) by joining everything."""
    star = trees.starify(trees.compile_tree(db, SUPPLIER_KW, workloads.supplier_root()))
    out = {"one_task": seconds(baselines.two_scans(star, SUPPLIER_KW)), "slots": seconds(cells.cell_frequencies(star, [4, 2], drop=SUPPLIER_KW))}
    out["volumes"] = seconds(frequency.star_frequencies(star, SUPPLIER_KW))
    return out | ({"full_join": seconds(baselines.straightforward(star, SUPPLIER_KW))} if join else {})


def searched_skew(db: Database, batch: str, shape: str, grid_cells: int, profile: str = "half_idle") -> dict[str, float]:
    """One query of a batch on skewed line items, counted in 8 slots from 8 or 27 cells; and the load of the slots."""
    number = {"Q1": 0, "Q4": 0, "Q5": 1}[batch]
    keywords = workloads.batch(shape, number)[0][1]
    make, _ = SHAPES[shape]
    star = trees.starify(trees.compile_tree(db, keywords, make()))
    facts = skew.make_skewed(db.table("lineitem"), profile)
    rows = tuplesets.tuple_set(_lines(db, facts), keywords, 0)
    star.root = rows.select(*[F.col({"part": "l_partkey", "supplier": "l_suppkey"}.get(x.name, "l_orderkey")).alias(k) for k, x in zip(star.keys, star.leaves)], "terms")
    shares = SKEW_GRIDS[shape][grid_cells]
    slots = skew_placement(skewed_star(db, shape, profile), shape, grid_cells)
    took, moved = measured(db.spark, cells.cell_frequencies(star, shares, slots, keywords, "mod"))
    return {"seconds": took, "shuffle_bytes": moved}


def _lines(db: Database, facts: DataFrame) -> DataFrame:
    return Database(db.spark, {"lineitem": facts}, db.graph, db.tokenizer).view("lineitem")


def uneven(db: Database) -> dict:
    """For each batch of the skew experiment: time, shuffled bytes and hottest slot with 8 and with 27 cells, and the change."""
    from .queries.grids import QUERIES

    loads = {(r.batch, r.cells): r for r in QUERIES["skew_experiment"](db.spark, db.where).collect()}
    out = {}
    for batch, shape in SKEW_BATCHES:
        for n in (8, 27):
            out[f"{batch}_{n}"] = searched_skew(db, batch, shape, n) | {"max_records": loads[batch, n].max_records, "max_over_mean": round(loads[batch, n].ratio, 3), "records": loads[batch, n].records}
        a, b = out[f"{batch}_8"], out[f"{batch}_27"]
        out[f"{batch}_change"] = {k: round(b[k] / a[k] - 1, 4) for k in ("seconds", "shuffle_bytes", "max_records", "records")}
    return out
