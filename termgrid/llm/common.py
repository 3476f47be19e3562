"""Pieces that several corpus operators share."""

from __future__ import annotations

import tempfile

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word is a run of characters other than space and U+0009 to U+000D (fixed values).
SPACES = " \t\n\x0b\x0c\r"
SPACE_RUN = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def words(text: Column) -> Column:
    """Array of the words of ``text``; null and blank texts give an empty array."""
    body = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACES))
    return F.when(body == "", F.array().cast("array<string>")).otherwise(F.split(body, SPACE_RUN))


def word_count(text: Column) -> Column:
    return F.size(words(text)).cast("long")


def unused(name: str, *frames: DataFrame) -> str:
    """``name``, with underscores before it for as long as one of the frames has a column of that name."""
    taken = {c.lower() for df in frames for c in df.columns}
    while name.lower() in taken:
        name = "_" + name
    return name


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder for intermediate tables; a temporary one stands in only for a session of one machine, as in tests."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None:
            if not sc.master.startswith("local"):
                raise ValueError("spark.checkpoint.dir must name a folder that all executors reach")
            folder = tempfile.mkdtemp(prefix="tg-checkpoint-")
        sc.setCheckpointDir(folder)
    return sc.getCheckpointDir()


def checkpointed(df: DataFrame) -> DataFrame:
    """``df`` computed once and kept in the shared checkpoint folder, so that lost executors cost no recomputation."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def broadcast_below(df: DataFrame, rows: int) -> DataFrame:
    """``df`` marked for broadcast if it has at most ``rows`` rows, else as it is (a shuffled join then serves).

    Pass a checkpointed table: it is counted here.
    """
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


#: Edges that one task of a round takes at least, and the least number of tasks.
EDGE_ROWS, EDGE_TASKS = 50_000, 16


def components(edges: DataFrame, a: str = "src", b: str = "dst", rounds: int = 60) -> DataFrame:
    """``(node, component)`` for each node on an edge; component = smallest node reachable.

    Alternates joining every larger neighbour to a node's minimum with joining every node's neighbours to its smaller
    minimum, until nothing changes. The number of rows never exceeds that of the edges, whatever the shape of the graph.
    Each shuffle writes files for every task before it, so a round has as many tasks as its edges need.
    """
    e = checkpointed(edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct())

    def star(pairs: DataFrame, both: bool) -> DataFrame:
        # hubs have many neighbours: the minimum is a partial aggregate and the join back can be split by AQE
        sides = pairs.unionByName(pairs.select(F.col("v").alias("u"), F.col("u").alias("v"))) if both else pairs
        low = sides.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        joined = sides.join(low, "u")
        if both:
            out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        else:
            out = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v")))
        return out.where("u <> v").coalesce(tasks).distinct().coalesce(tasks)

    def mark(pairs: DataFrame) -> tuple:
        return tuple(pairs.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())

    last = mark(e)
    for _ in range(rounds):
        if not last[0]:
            break
        tasks = max(EDGE_TASKS, -(-last[0] // EDGE_ROWS))
        e = checkpointed(star(star(e.coalesce(tasks), True), False))
        now = mark(e)
        if now == last:
            break
        last = now
    else:
        raise RuntimeError("components did not settle")
    # every node now hangs on its root
    return e.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
