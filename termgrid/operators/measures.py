"""What the experiments measure: times, rows moved, loads, errors."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .grid import leaf_copies, star_cost
from .volumes import Star


def batch_time(plans: Sequence[Callable[[], DataFrame]], reps: int = 1) -> float:
    """Mean seconds for a plan of the batch, to a sink that stores nothing."""
    began = time.perf_counter()
    for _ in range(reps):
        for plan in plans:
            plan().write.format("noop").mode("overwrite").save()
    return (time.perf_counter() - began) / (reps * max(1, len(plans)))


def stage_split(spark: SparkSession, volumes: DataFrame, terms: Callable[[DataFrame], DataFrame], path: str) -> tuple[float, float]:
    """Seconds of the first job (volumes, written to ``path``) and of the second (term sums over them)."""
    began = time.perf_counter()
    volumes.write.mode("overwrite").parquet(path)
    half = time.perf_counter()
    terms(spark.read.parquet(path)).write.format("noop").mode("overwrite").save()
    return half - began, time.perf_counter() - half


def phase_bound(map_: float, shuffle: float, sort: float, reduce: float) -> float:
    """Least time of a job whose shuffle runs beside its map phase."""
    return max(map_, shuffle) + sort + reduce


def replication_factors(shares: Sequence[int]) -> list[int]:
    """Copies of a row of each leaf."""
    k = 1
    for a in shares:
        k *= a
    return [k // a for a in shares]


def comm_cost(star: Star, shares: Sequence[int], facts: int, leaves: Sequence[int], kind: str = "xxhash") -> DataFrame:
    """``(predicted, actual)`` rows sent: by the formula, and counted after copying."""
    copies = leaf_copies(star, shares, kind).agg(F.count("*").alias("c"))
    return copies.crossJoin(star.root.agg(F.count("*").alias("f"))).select(F.lit(float(star_cost(facts, leaves, shares))).alias("predicted"), (F.col("c") + F.col("f")).alias("actual"))


def slot_load(loads: DataFrame, slots: int) -> DataFrame:
    """``(max_records, mean_records, ratio, idle)`` of a table of slot loads; slots without rows count as idle."""
    return loads.agg(F.max("records").alias("max_records"), (F.sum("records") / slots).alias("mean_records"), (F.lit(slots) - F.sum((F.col("facts") > 0).cast("long"))).alias("idle")).withColumn("ratio", F.col("max_records") / F.col("mean_records"))


def cost_error(estimated: DataFrame, true: DataFrame) -> DataFrame:
    """``(cell, est, truth, rel_error, q_error)`` for each cell of either table."""
    e = estimated.select("cell", F.col("cost").alias("est"))
    t = true.select("cell", F.col("cost").alias("truth"))
    out = e.join(t, "cell", "full_outer").na.fill(0.0, ["est", "truth"])
    q = F.when((F.col("est") > 0) & (F.col("truth") > 0), F.greatest(F.col("est") / F.col("truth"), F.col("truth") / F.col("est")))
    return out.withColumn("rel_error", F.when(F.col("truth") > 0, F.abs(F.col("est") - F.col("truth")) / F.col("truth"))).withColumn("q_error", q)


def gain(before: float, after: float) -> float:
    """Relative saving; negative for growth."""
    return (before - after) / before


def mismatches(a: DataFrame, b: DataFrame, key: str = "term", value: str = "freq") -> DataFrame:
    """Keys on which two answers differ."""
    x = a.select(F.col(key), F.col(value).cast("decimal(38,0)").alias("va"))
    y = b.select(F.col(key), F.col(value).cast("decimal(38,0)").alias("vb"))
    return x.join(y, key, "full_outer").where(~F.col("va").eqNullSafe(F.col("vb")))


def shuffle_bytes(spark: SparkSession) -> int:
    """Bytes written to shuffles so far, by all stages in the status store."""
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None)
    return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))


def ledger(star: Star, shares: Sequence[int], drop: Sequence[str], kind: str = "xxhash") -> DataFrame:
    """``(step, rows_before, rows_after)`` for each reduction: combining, keyword and cell pruning, dangling facts."""
    from ..functions.text import without
    from .placement import prune_dangling, useful_leaf_rows

    def pair(step: str, before: DataFrame, after: DataFrame) -> DataFrame:
        return before.agg(F.count("*").alias("rows_before")).crossJoin(after.agg(F.count("*").alias("rows_after"))).select(F.lit(step).alias("step"), "rows_before", "rows_after")

    words = star.root.select(F.explode("terms").alias("t"))
    out = pair("combine facts", star.root, star.root.groupBy(*star.keys).agg(F.count("*").alias("m")))
    for i, leaf in enumerate(star.leaves):
        words = words.unionByName(leaf.rows.select(F.explode("terms").alias("t")))
        out = out.unionByName(pair(f"combine leaf {i + 1}", leaf.rows, leaf.rows.groupBy("key").agg(F.count("*").alias("n"))))
        every = Star(star.root, star.keys, star.leaves)
        out = out.unionByName(pair(f"prune cells of leaf {i + 1}", leaf_copies(every, shares, kind).where(F.col("leaf") == i + 1), useful_leaf_rows(star, i, shares, kind)))
    out = out.unionByName(pair("drop keywords", words, words.where(~F.col("t").isin(list(drop)))))
    return out.unionByName(pair("dangling facts", star.root, prune_dangling(star)))
