"""Readers, writers and in-memory fixtures."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

FORMATS = ("parquet", "json", "csv", "text", "orc")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A table from files; formats without a schema of their own need one, so that no pass over the data guesses it."""
    if fmt not in FORMATS:
        raise ValueError(fmt)
    if fmt in ("json", "csv") and schema is None:
        raise ValueError("a schema is needed")
    reader = spark.read.options(**options)
    return (reader.schema(schema) if schema else reader).format(fmt).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    writer = df.write.mode(mode).format(fmt)
    (writer.partitionBy(*by) if by else writer).save(path)


def write_by_term(freq: DataFrame, path: str, buckets: int = 16) -> None:
    """Term frequencies in folders by a hash of the term, so that one term's folder can be read alone."""
    from pyspark.sql import functions as F

    write(freq.withColumn("bucket", F.pmod(F.xxhash64("term"), F.lit(buckets)).cast("int")), path, by=("bucket",))


def save_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by its join key: later joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def running_example(spark: SparkSession) -> dict[str, DataFrame]:
    """The worked example: three leaves with repeated keys and a root whose last row dangles (fixed values)."""
    leaf = lambda rows: spark.createDataFrame(rows, "key string, terms array<string>")
    return {
        "S": leaf([("a1", []), ("a1", []), ("a2", ["w1", "w2", "w3"]), ("a2", ["w2"]), ("a2", ["w3"]), ("a4", ["w4"]), ("a3", [])]),
        "T": leaf([("b2", []), ("b3", ["w2"]), ("b3", ["w1", "w3"]), ("b4", ["w3"])]),
        "P": leaf([("c1", ["w1", "w1"]), ("c1", ["w1", "w2"]), ("c2", ["w2", "w4"]), ("c2", ["w2", "w3"])]),
        "R": spark.createDataFrame(
            [("a2", "b4", "c1", ["w2", "w3"]), ("a4", "b3", "c1", ["w3"]), ("a1", "b2", "c2", ["w1", "w2"]), ("a1", "b4", "c1", []), ("a5", "b2", "c2", [])],
            "A string, B string, C string, terms array<string>",
        ),
    }


def shared_folder(spark: SparkSession) -> str:
    """A fresh folder that all executors reach, below the session's checkpoint folder."""
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors reach")
        base = tempfile.mkdtemp(prefix="tg-")
    return f"{base}/tg-{uuid.uuid4().hex}"
