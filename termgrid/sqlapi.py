"""The counting plan as SQL text, and SQL functions for tokens and masks."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession

from .catalog import Database


def register(spark: SparkSession) -> None:
    """SQL functions ``tg_tokens(text)`` and ``tg_has(terms, word)`` for this session."""
    spark.sql(r"create or replace temporary function tg_tokens(t string) returns array<string> return filter(split(lower(coalesce(t, '')), r'[^\p{L}\p{N}_#]+'), x -> x <> '')")
    spark.sql("create or replace temporary function tg_has(t array<string>, w string) returns boolean return array_contains(t, w)")


def star_text(keywords: Sequence[str]) -> str:
    """The counting plan for line items with parts, suppliers and orders as one statement."""
    def exact(i: int | None) -> str:
        return " and ".join(f"{'' if j == i else 'not '}array_contains(terms, '{w}')" for j, w in enumerate(keywords))

    words = ", ".join(f"'{w}'" for w in keywords)
    return f"""
with p as (select p_partkey as k, terms from tg_part where {exact(0)}),
 s as (select s_suppkey as k, terms from tg_supplier where {exact(1)}),
 o as (select o_orderkey as k, terms from tg_orders where {exact(2)}),
 f as (select l_partkey, l_suppkey, l_orderkey, terms, pn, sn, o_n from (select * from tg_lineitem where {exact(None)}) l
  join (select k as pk, count(*) as pn from p group by k) on l_partkey = pk
  join (select k as sk, count(*) as sn from s group by k) on l_suppkey = sk
  join (select k as ok, count(*) as o_n from o group by k) on l_orderkey = ok),
 parts as (
  select explode(terms) as term, pn * sn * o_n as part from f
  union all select explode(terms), v from p join (select l_partkey as k, sum(sn * o_n) as v from f group by 1) using (k)
  union all select explode(terms), v from s join (select l_suppkey as k, sum(pn * o_n) as v from f group by 1) using (k)
  union all select explode(terms), v from o join (select l_orderkey as k, sum(pn * sn) as v from f group by 1) using (k))
select term, sum(part) as freq from parts where term not in ({words}) group by term"""


def star_sql(db: Database, keywords: Sequence[str]) -> DataFrame:
    """``(term, freq)`` of the star by SQL over temporary views of the relations."""
    if any("'" in w for w in keywords):
        raise ValueError("keywords hold no quotes")
    for r in ("part", "supplier", "orders", "lineitem"):
        db.view(r).createOrReplaceTempView(f"tg_{r}")
    return db.spark.sql(star_text(keywords))
