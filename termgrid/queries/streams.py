"""Streaming queries and their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import streaming
from ..functions.text import tokenize
from ..operators import tuplesets
from . import search, sql
from ..sources import shared_folder

QUERIES: dict = {}
ORACLES: dict = {}


def query(oracle: str | None = None):
    def add(f):
        search.query(oracle, f.__name__)(f)
        QUERIES[f.__name__] = search.QUERIES.pop(f.__name__)
        if oracle:
            ORACLES[f.__name__] = search.ORACLES.pop(f.__name__)
        return f

    return add


@query(f"select term, sum(num)::bigint as freq from (select unnest({sql.tokens('event_type')}) as term, num from events join (select c_custkey as k, 1 as num from {sql.tuple_set('customer', ['building'], 1)}) on user_id = k) x group by term")
def stream_event_terms(db):
    leaf = tuplesets.tuple_set(db.view("customer"), ["building"], 1).select(F.col("c_custkey").alias("key"), F.lit(1).cast("bigint").alias("num"))
    facts = streaming.event_stream(db).select("user_id", tokenize(F.col("event_type")).alias("terms"))
    return streaming.drained(streaming.streamed_terms(facts, leaf, "user_id"), "complete", shared_folder(db.spark))


@query("select time_bucket(interval 1 day, ts) as start, event_type as term, count(*)::bigint as freq from events group by all")
def tumbling_terms(db):
    return streaming.windowed_terms(db.table("events"), "1 day").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select start, event_type as term, count(*)::bigint as freq from (select event_type, unnest([time_bucket(interval 1 day, ts), time_bucket(interval 1 day, ts) + interval 12 hour, time_bucket(interval 1 day, ts) - interval 12 hour]) as start, ts from events) x where start <= ts and ts < start + interval 1 day group by all")
def sliding_terms(db):
    return streaming.windowed_terms(db.table("events"), "1 day", "12 hours").withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select user_id, count(*)::bigint as n_sessions from (select user_id, ts, coalesce(ts - lag(ts) over (partition by user_id order by ts) >= interval 6 hour, true) as fresh from events) x where fresh group by user_id")
def session_counts(db):
    s = db.table("events").groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"))
    return s.groupBy("user_id").agg(F.count("*").alias("n_sessions"))


@query("select start, term, freq from (select time_bucket(interval 1 day, ts) as start, event_type as term, count(*)::bigint as freq from events group by all) x where start + interval 1 day <= (select max(ts) from events) - interval 1 hour")
def stream_watermark(db):
    """Days that the watermark has passed, each once; the days after it are still open."""
    out = streaming.drained(streaming.windowed_terms(streaming.event_stream(db), "1 day", late="1 hour"), "append", shared_folder(db.spark))
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@query("select count(distinct event_id)::bigint as n from events")
def stream_dedup(db):
    return streaming.drained(streaming.deduplicated(streaming.event_stream(db).select("event_id", "ts")), "append", shared_folder(db.spark)).agg(F.count("*").alias("n"))


@query("select start, term, freq, row_number() over (partition by start order by freq desc, term)::bigint as rank from (select time_bucket(interval 1 day, ts) as start, event_type as term, count(*)::bigint as freq from events group by all) x qualify rank <= 3")
def stream_topk_state(db):
    """The three most frequent terms of each day, from counts kept as state of the day; the last update of a day holds."""
    kept = streaming.drained(streaming.kept_top(streaming.event_stream(db), 3), "update", shared_folder(db.spark))
    last = kept.groupBy(F.col("start").alias("_s")).agg(F.max("batch").alias("_b"))
    kept = kept.join(last, (F.col("start") == F.col("_s")) & (F.col("batch") == F.col("_b")))
    return kept.select(F.col("start").cast("timestamp_ntz").alias("start"), "term", "freq", "rank")


@query("select l_partkey as k1, l_suppkey as k2, (n2 * 1)::bigint as volume from lineitem join (select p_partkey as a, 1 as n1 from part) x on l_partkey = a join (select user_id as b, count(*) as n2 from events group by 1) y on l_suppkey = b")
def leaf_delta_volumes(db):
    """What new rows of one leaf add to the volumes: the events as new rows of the second leaf, by their user as key."""
    facts = db.table("lineitem").select(F.col("l_partkey").alias("k1"), F.col("l_suppkey").alias("k2"))
    parts = db.table("part").select(F.col("p_partkey").alias("key"), F.lit(1).cast("bigint").alias("num"))
    fresh = db.table("events").groupBy(F.col("user_id").alias("key")).agg(F.count("*").alias("num"))
    return streaming.leaf_delta(facts, [parts, fresh], ["k1", "k2"], fresh, 1)


@query(f"select term, count(*)::bigint as freq from (select unnest({sql.tokens('event_type')}) as term from events) x group by term")
def stream_foreach_batch(db):
    path, spark = shared_folder(db.spark), db.spark
    counts = streaming.event_stream(db).select(F.explode(tokenize(F.col("event_type"))).alias("term"), F.lit(1).cast("bigint").alias("freq"))
    q = counts.writeStream.foreachBatch(lambda b, _: streaming.merge_counts(b, path, spark)).option("checkpointLocation", shared_folder(spark)).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.parquet(path).groupBy("term").agg(F.sum("freq").alias("freq"))
