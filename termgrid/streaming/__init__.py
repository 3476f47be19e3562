"""Structured Streaming twins: counts add over portions of the facts, so facts may arrive bit by bit."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..catalog import Database
from ..functions.text import tokenize
from ..shipping import shipped


def event_stream(db: Database, files: int = 1) -> DataFrame:
    """The events as a stream of files, their time as an event time."""
    where = f"{db.where}/events.parquet"
    schema = db.table("events").schema
    reader = db.spark.readStream.schema(schema).option("maxFilesPerTrigger", files)
    # a single file is read through its folder
    folder, _, name = where.rpartition("/")
    return reader.option("pathGlobFilter", name).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, mode: str, checkpoint: str, schema: StructType | None = None) -> DataFrame:
    """The stream's result after all that is there now, from Parquet beside the checkpoint; rows stay on the executors.

    Each micro-batch writes a folder of its own, so a batch that runs again after a failure replaces itself. In complete
    mode the last folder is the answer; else all folders, with their number as ``batch`` in update mode.
    """
    spark, out = stream.sparkSession, f"{checkpoint}-out"
    schema = StructType([StructField(f.name, f.dataType, True) for f in (schema or stream.schema).fields])

    def keep(rows: DataFrame, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{out}/batch={number}")

    spark.createDataFrame([], schema).write.mode("overwrite").parquet(f"{out}/batch=-1")
    stream.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    got = spark.read.schema(StructType([*schema.fields, StructField("batch", LongType())])).parquet(out)
    if mode == "complete":
        last = got.agg(F.max("batch").alias("_last"))
        got = got.join(F.broadcast(last), F.col("batch") == F.col("_last")).drop("_last")
    return got if mode == "update" else got.drop("batch")


def streamed_terms(facts: DataFrame, leaf: DataFrame, key: str) -> DataFrame:
    """``(term, freq)`` kept up to date: streaming facts with terms, joined to the static counts of one leaf ``(key, num)``."""
    joined = facts.join(leaf.select(F.col("key").alias("_k"), "num"), F.col(key) == F.col("_k"))
    return joined.select(F.explode("terms").alias("term"), "num").groupBy("term").agg(F.sum("num").alias("freq"))


def windowed_terms(events: DataFrame, width: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """``(start, term, freq)`` by tumbling or sliding windows of ``ts``; with ``late`` a watermark bounds the state."""
    if late:
        events = events.withWatermark("ts", late)
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    terms = events.select("ts", F.explode(tokenize(F.col("event_type"))).alias("term"))
    return terms.groupBy(w.alias("w"), "term").agg(F.count("*").alias("freq")).select(F.col("w.start").alias("start"), "term", "freq")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event id once within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def merge_counts(batch: DataFrame, path: str, spark: SparkSession) -> None:
    """``foreachBatch`` sink: adds a batch's term sums as a further portion; readers sum the portions."""
    batch.groupBy("term").agg(F.sum("freq").alias("freq")).write.mode("append").parquet(path)


def leaf_delta(facts: DataFrame, nums: list[DataFrame], keys: list[str], delta: DataFrame, axis: int) -> DataFrame:
    """``(keys.., volume)`` that new rows of one leaf add: the new counts times the old counts of the others."""
    out = facts
    for i, (key, num) in enumerate(zip(keys, nums)):
        side = (delta if i == axis else num).select(F.col("key").alias(f"_k{i}"), F.col("num").alias(f"_n{i}"))
        out = out.join(side, F.col(key) == F.col(f"_k{i}")).drop(f"_k{i}")
    volume = F.lit(1).cast("bigint")
    for i in range(len(keys)):
        volume = volume * F.col(f"_n{i}")
    return out.select(*keys, volume.alias("volume"))


def kept_top(events: DataFrame, k: int, width: str = "1 day") -> DataFrame:
    """``(start, term, freq, rank)`` in update mode: for each window with new events its k most frequent terms.

    The state of a window is its counts by term, of which there are as many as event types; equal counts rank by term.
    """
    terms = shipped(events).select(F.window("ts", width).getField("start").alias("start"), F.explode(tokenize(F.col("event_type"))).alias("term"))

    def update(key, frames, state):
        counts = dict(zip(*state.get)) if state.exists else {}
        for frame in frames:
            for term, n in frame["term"].value_counts().items():
                counts[term] = counts.get(term, 0) + int(n)
        state.update((list(counts), list(counts.values())))
        best = sorted(counts.items(), key=lambda x: (-x[1], x[0]))[:k]
        yield pd.DataFrame({"start": [key[0]] * len(best), "term": [t for t, _ in best], "freq": [n for _, n in best], "rank": range(1, len(best) + 1)})

    return terms.groupBy("start").applyInPandasWithState(update, "start timestamp, term string, freq bigint, rank bigint", "terms array<string>, counts array<bigint>", "update", "NoTimeout")
