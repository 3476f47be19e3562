"""Mixing sources to target weights with a cap on epochs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import broadcast_below, checkpointed, unused, word_count

WEIGHTS = (5, 2, 1)
BUDGET = 1.5
EPOCHS = 2
SEED = 17
#: A source's documents are dealt to so many buckets by hash; the bucket where its fractional epoch ends is sampled.
BUCKETS = 1024
FINE = 1 << 22
#: Largest table of sources that is broadcast.
SOURCE_ROWS = 200_000


def source_targets(sized: DataFrame, weights=WEIGHTS, budget: float = BUDGET, epochs: float = EPOCHS) -> DataFrame:
    """``(source, source_size, weight, target)`` from rows ``(source, size)``.

    Water-filling in one pass: rank the sources by the level at which each reaches its cap. If the first j are clamped,
    the level of the rest is (budget - their caps) / (weights of the rest); the highest level that none of the rest
    exceeds is where the repeated clamping and resharing ends. Sources without words get the target 0.
    """
    order = Window.orderBy(F.asc_nulls_last("source"))
    by_level = Window.orderBy("full_at", F.asc_nulls_last("source")).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    ring = F.array(*[F.lit(float(w)) for w in weights])
    return (
        sized.groupBy("source").agg(F.sum("size").alias("source_size"))
        .withColumn("weight", F.element_at(ring, (F.row_number().over(order) - 1) % len(weights) + 1))
        .withColumn("cap", F.col("source_size") * F.lit(float(epochs)))
        .withColumn("full_at", F.col("cap") / F.col("weight"))
        .withColumn("left", F.sum("source_size").over(every) * F.lit(float(budget)) - F.coalesce(F.sum("cap").over(by_level), F.lit(0.0)))
        .withColumn("rest", F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(by_level), F.lit(0.0)))
        .withColumn("level", F.max(F.when(F.col("left") / F.col("rest") <= F.col("full_at"), F.col("left") / F.col("rest"))).over(every))
        .select("source", "source_size", "weight", F.least("cap", F.coalesce(F.col("weight") * F.col("level"), F.col("cap"))).alias("target"))
    )


def _draw(key: Column, seed: int) -> Column:
    """32 bits from the seed and the key, the same on each run."""
    return F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), key.cast("string"))), 1, 8), 16, 10).cast("long")


def mix(docs: DataFrame, size: Column | None = None, weights=WEIGHTS, budget: float = BUDGET, epochs: float = EPOCHS, seed: int = SEED) -> DataFrame:
    """``docs`` with ``size``, ``source_size``, ``target``, ``repeats`` and ``taken`` = size * repeats (named ``mix_*``).

    Each document is taken ``floor(target / source_size)`` times, and once more if it falls in the source's fractional
    epoch: documents are ordered by a seeded hash in buckets, whole buckets are taken while they fit, and the bucket where
    the target lies is sampled by the hash's other bits. A source so misses its target by less than one bucket (or one
    document, where a bucket holds one). Null sources form a source of their own; a null ``doc_id`` draws like an empty
    one; null, empty and blank texts have size 0 and are repeated like others of their source; repeated rows share one
    decision. All columns of ``docs`` stay as they are; ``mix_names`` tells the names of the new ones.
    """
    size = word_count(F.col("text")) if size is None else size
    draw = _draw(F.col("doc_id"), seed)
    slim = checkpointed(docs.select("source", size.alias("size"), F.floor(draw / FINE).cast("int").alias("bucket")).groupBy("source", "bucket").agg(F.sum("size").alias("size")))
    so_far = Window.partitionBy("source").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    goals = checkpointed(source_targets(slim, weights, budget, epochs)).withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
    goals = goals.withColumn("more", F.col("target") - F.col("whole") * F.col("source_size"))
    ends = (
        slim.withColumn("before", F.coalesce(F.sum("size").over(so_far), F.lit(0)))
        .join(broadcast_below(goals.select(F.col("source").alias("s"), "more"), SOURCE_ROWS), F.col("source").eqNullSafe(F.col("s")))
        .where((F.col("before") <= F.col("more")) & (F.col("more") < F.col("before") + F.col("size")))
        .select("s", F.col("bucket").alias("end_bucket"), ((F.col("more") - F.col("before")) / F.col("size")).alias("end_share"))
    )
    names = mix_names(docs)
    key, whole, end_bucket, end_share = (unused(c, docs) for c in ("mix_key", "mix_whole", "mix_end_bucket", "mix_end_share"))
    plan = checkpointed(
        goals.join(ends, F.col("source").eqNullSafe(F.col("s")), "left")
        .select(F.col("source").alias(key), F.col("source_size").alias(names["source_size"]), F.col("target").alias(names["target"]), F.col("whole").alias(whole), F.coalesce("end_bucket", F.lit(0)).alias(end_bucket), F.coalesce("end_share", F.lit(0.0)).alias(end_share))
    )
    bucket, fine = F.floor(draw / FINE), (draw % FINE) / F.lit(float(FINE))
    extra = (bucket < F.col(end_bucket)) | ((bucket == F.col(end_bucket)) & (fine < F.col(end_share)))
    return (
        docs.withColumn(names["size"], size)
        .join(broadcast_below(plan, SOURCE_ROWS), F.col("source").eqNullSafe(F.col(key)))
        .withColumn(names["repeats"], F.col(whole) + extra.cast("long"))
        .withColumn(names["taken"], F.col(names["repeats"]) * F.col(names["size"]))
        .select(*docs.columns, *names.values())
    )


def mix_names(docs: DataFrame) -> dict[str, str]:
    """Names of the columns that ``mix`` adds: ``mix_*``, with underscores before them where ``docs`` has such a column."""
    return {c: unused(f"mix_{c}", docs) for c in ("size", "source_size", "target", "repeats", "taken")}


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each row of ``docs`` as often as it is taken, with the columns of ``docs``, whatever their names."""
    repeats, turn = mix_names(docs)["repeats"], unused("mix_turn", docs)
    out = mix(docs, **options).where(F.col(repeats) > 0)
    return out.withColumn(turn, F.explode(F.sequence(F.lit(1), F.col(repeats).cast("int")))).select(*docs.columns)


#: DuckDB twin of the query.
SQL = r"""
with d as (select doc_id, source, case when text is null then 0 else len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) end::bigint as size,
    ('0x' || substr(md5('17:' || doc_id::varchar), 1, 8))::bigint as draw from documents),
s as (select source, sum(size)::bigint as source_size, ([5.0, 2.0, 1.0])[((row_number() over (order by source asc nulls last) - 1) % 3 + 1)::int]::double as weight from d group by source),
c as (select *, source_size * 2.0::double as cap, source_size * 2.0::double / weight as full_at from s),
l as (select *, (sum(source_size) over ())::double * 1.5 - coalesce(sum(cap) over w, 0) as remaining,
    sum(weight) over () - coalesce(sum(weight) over w, 0) as rest from c
    window w as (order by full_at, source asc nulls last rows between unbounded preceding and 1 preceding)),
g as (select source, source_size, least(cap, coalesce(weight * max(case when remaining / rest <= full_at then remaining / rest end) over (), cap)) as target from l),
h as (select *, case when source_size > 0 then floor(target / source_size) else 0 end::bigint as whole from g),
m as (select *, target - whole * source_size as more from h),
b as (select source, draw // 4194304 as bucket, sum(size)::bigint as size from d group by all),
a as (select *, coalesce(sum(size) over (partition by source order by bucket rows between unbounded preceding and 1 preceding), 0)::bigint as prior from b),
e as (select a.source, bucket as end_bucket, (more - prior) / a.size as end_share from a join m on a.source is not distinct from m.source where prior <= more and more < prior + a.size)
select d.doc_id, d.size, m.source_size, m.target,
  d.size * (whole + case when draw // 4194304 < coalesce(end_bucket, 0) or (draw // 4194304 = coalesce(end_bucket, 0) and (draw % 4194304) / 4194304.0::double < coalesce(end_share, 0)) then 1 else 0 end) as taken
from d join m on d.source is not distinct from m.source left join e on d.source is not distinct from e.source
"""
