"""Queries of the relational operators and functions that users of the search need."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .. import session, sqlapi, workloads
from ..functions.text import term_counts, tokenize
from ..operators import baselines, frequency, measures, volumes
from ..operators.cells import cell_frequencies
from ..sources import read, write
from . import search, sql
from .search import MULTI, MULTI_KW, STAR_FREQ, STAR_KW, shared_folder, star_of

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


def _star(db):
    return frequency.star_frequencies(star_of(db), STAR_KW)


# ---- scans, projections, filters, joins ------------------------------------------------------------------------------


@query("select p_partkey, p_name, p_size from part where p_size > 20")
def scan_parquet(db):
    return db.table("part").where("p_size > 20").select("p_partkey", "p_name", "p_size")


@query("select l_orderkey, l_quantity from lineitem where l_quantity >= 45")
def scan_projection(db):
    return db.table("lineitem").where("l_quantity >= 45").select("l_orderkey", "l_quantity")


@query("select o_orderkey, concat_ws(' ', o_orderstatus, o_orderpriority) as text from orders")
def project_text(db):
    return db.table("orders").select("o_orderkey", F.concat_ws(" ", "o_orderstatus", "o_orderpriority").alias("text"))


@query(f"select p_partkey from {sql.view('part')} where list_contains(terms, 'red')")
def filter_keyword(db):
    return db.view("part").where(F.array_contains("terms", "red")).select("p_partkey")


@query("select count(*)::bigint as n from lineitem where l_shipdate >= timestamp '1996-01-01' and l_shipdate < timestamp '1997-01-01'")
def filter_date_range(db):
    return db.table("lineitem").where("l_shipdate >= timestamp_ntz '1996-01-01' and l_shipdate < timestamp_ntz '1997-01-01'").agg(F.count("*").alias("n"))


_JOIN = "select p_brand, count(*)::bigint as n, sum(l_quantity) as quantity from lineitem join part on l_partkey = p_partkey group by p_brand"


def _joined(db, hint):
    part = db.table("part").select("p_partkey", "p_brand").hint(hint)
    return db.table("lineitem").join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@query(_JOIN)
def join_broadcast(db):
    return _joined(db, "broadcast")


@query(_JOIN)
def join_shuffle_hash(db):
    return _joined(db, "shuffle_hash")


@query(_JOIN)
def join_sort_merge(db):
    return _joined(db, "merge")


@query("select count(*)::bigint as n from part where p_partkey in (select l_partkey from lineitem where l_quantity > 49)")
def semi_join_leaf(db):
    return db.table("part").join(db.table("lineitem").where("l_quantity > 49"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").agg(F.count("*").alias("n"))


@query("select count(*)::bigint as n from orders where o_orderkey not in (select l_orderkey from lineitem)")
def anti_join_dangling(db):
    return db.table("orders").join(db.table("lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti").agg(F.count("*").alias("n"))


@query("select count(*)::bigint as n from orders a join orders b on a.o_custkey = b.o_custkey and a.o_orderkey < b.o_orderkey")
def theta_same_relation(db):
    a, b = (db.table("orders").select(F.col("o_custkey").alias(f"c{x}"), F.col("o_orderkey").alias(f"k{x}")) for x in "ab")
    return a.join(b, (F.col("ca") == F.col("cb")) & (F.col("ka") < F.col("kb"))).agg(F.count("*").alias("n"))


@query("select s_suppkey, cell::int as cell from supplier, range(8) r(cell) where cell % 2 = s_suppkey % 2")
def replicate_cross(db):
    # copies along an axis: a sequence in the row, no join
    cells = F.filter(F.sequence(F.lit(0), F.lit(7)), lambda c: c % 2 == F.col("s_suppkey") % 2)
    return db.table("supplier").select("s_suppkey", F.explode(cells).alias("cell"))


@query("select band, count(*)::bigint as n from part join (values ('small', 1, 10), ('middle', 11, 30), ('large', 31, 100)) b(band, lo, hi) on p_size between lo and hi group by band")
def range_join_size_band(db):
    bands = F.broadcast(db.spark.createDataFrame([("small", 1, 10), ("middle", 11, 30), ("large", 31, 100)], "band string, lo int, hi int"))
    return db.table("part").join(bands, F.col("p_size").between(F.col("lo"), F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@query("select e.event_id, max(v.ts) as last_view from events e left join events v on v.user_id = e.user_id and v.event_type = 'view' and v.ts < e.ts where e.event_type = 'purchase' group by e.event_id")
def asof_events(db):
    """The latest earlier view of the same user, by a running window instead of a range join."""
    e = db.table("events").select("event_id", "user_id", "event_type", "ts")
    seen = F.last(F.when(F.col("event_type") == "view", F.col("ts")), True).over(Window.partitionBy("user_id").orderBy("ts").rowsBetween(Window.unboundedPreceding, -1))
    return e.withColumn("last_view", seen).where("event_type = 'purchase'").select("event_id", "last_view")


@query("select count(*)::bigint as n from events a join events b on a.user_id = b.user_id and a.event_type = 'click' and b.event_type = 'purchase' and b.ts > a.ts and b.ts <= a.ts + interval 1 hour")
def interval_join_events(db):
    e = db.table("events")
    a = e.where("event_type = 'click'").select(F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'purchase'").select(F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    return a.join(b, (F.col("ua") == F.col("ub")) & (F.col("tb") > F.col("ta")) & (F.col("tb") <= F.col("ta") + F.expr("interval 1 hour"))).agg(F.count("*").alias("n"))


@query("select coalesce(a.term, b.term) as term, a.freq as freq_a, b.freq as freq_b from (" + STAR_FREQ + ") a full join (" + sql.frequencies([workloads.chain()], ["america", "building"]) + ") b on a.term = b.term")
def full_outer_compare(db):
    a = _star(db).withColumnRenamed("freq", "freq_a")
    b = frequency.star_frequencies(star_of(db, workloads.chain(), ["america", "building"]), ["america", "building"]).withColumnRenamed("freq", "freq_b")
    return a.join(b, "term", "full_outer")


# ---- aggregation -----------------------------------------------------------------------------------------------------


@query("select l_returnflag, l_linestatus, count(*)::bigint as n, sum(l_quantity) as quantity from lineitem group by all")
def agg_partial_final(db):
    return db.table("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


@query("select count(distinct l_suppkey)::bigint as suppliers, count(distinct l_partkey)::bigint as parts from lineitem")
def distinct_keys(db):
    return db.table("lineitem").agg(F.countDistinct("l_suppkey").alias("suppliers"), F.countDistinct("l_partkey").alias("parts"))


@query()
def approx_distinct_keys(db):
    return db.table("lineitem").agg(F.approx_count_distinct("l_suppkey", 0.02).alias("suppliers"), F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query()
def approx_top_terms(db):
    terms = db.view("documents").select(F.explode("terms").alias("term"))
    return terms.agg(F.expr("approx_top_k(term, 10, 20000)").alias("top")).select(F.inline("top")).withColumnRenamed("item", "term")


@query("select cn_id, term, sum(freq)::bigint as freq from (" + " union all ".join(f"select {i}::int as cn_id, term, freq from ({sql.frequencies([n], MULTI_KW)}) f" for i, n in enumerate(MULTI)) + ") x group by rollup (cn_id, term)")
def freq_rollup_cn_term(db):
    parts = [session.network_frequencies(db, MULTI_KW, n).select(F.lit(i).alias("cn_id"), "term", "freq") for i, n in enumerate(MULTI)]
    return parts[0].unionByName(parts[1]).rollup("cn_id", "term").agg(F.sum("freq").alias("freq"))


@query("select source, lang, count(*)::bigint as n, sum(n_chars)::bigint as chars from documents group by cube (source, lang)")
def freq_cube_source_lang(db):
    return db.table("documents").cube("source", "lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("select source, lang, count(*)::bigint as n from documents group by grouping sets ((source), (lang), ())")
def freq_grouping_sets(db):
    db.table("documents").createOrReplaceTempView("tg_documents")
    return db.spark.sql("select source, lang, count(*) as n from tg_documents group by grouping sets ((source), (lang), ())")


@query("select l_suppkey % 8 as slot, sum((l_returnflag = 'A')::int)::bigint as \"A\", sum((l_returnflag = 'N')::int)::bigint as \"N\", sum((l_returnflag = 'R')::int)::bigint as \"R\" from lineitem group by 1")
def pivot_slot_measure(db):
    return db.table("lineitem").withColumn("slot", F.col("l_suppkey") % 8).groupBy("slot").pivot("l_returnflag", ["A", "N", "R"]).agg(F.count("l_orderkey")).na.fill(0)


# ---- windows, order, sets --------------------------------------------------------------------------------------------


@query(sql.batch(workloads.batch("star", 0), workloads.star))
def batch_topk_rank(db):
    return workloads.batch_top(db, "star", 0)


@query(f"select term, freq, sum(freq) over (order by freq desc, term rows unbounded preceding)::bigint as running from ({STAR_FREQ}) f")
def cumulative_freq_share(db):
    return running_sum(_star(db), "freq", "term").select("term", "freq", "running")


def running_sum(df, value: str, key: str):
    """``df`` with the running sum of ``value`` from the largest on, equal ones by ``key``.

    Rows are summed by value first; the few distinct values are summed up in one task, and rows of one value in parts by
    the first characters of the key, so that no task orders all rows.
    """
    df = df.withColumn("_head", F.substring(key, 1, 2))
    parts = df.groupBy(value, "_head").agg(F.count("*").alias("_n"))
    levels = parts.groupBy(value).agg(F.sum("_n").alias("_n"))
    before = lambda *order: Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    levels = levels.select(F.col(value).alias("_v"), F.coalesce(F.sum(F.col(value) * F.col("_n")).over(before(F.desc(value))), F.lit(0)).alias("_above"))
    inner = Window.partitionBy(value).orderBy("_head").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select(F.col(value).alias("_p"), F.col("_head").alias("_h"), F.coalesce(F.sum("_n").over(inner), F.lit(0)).alias("_same"))
    rank = F.row_number().over(Window.partitionBy(value, "_head").orderBy(key))
    out = df.withColumn("_rank", rank).join(parts, (F.col(value) == F.col("_p")) & F.col("_head").eqNullSafe(F.col("_h"))).join(levels, F.col(value) == F.col("_v"))
    return out.withColumn("running", F.col("_above") + F.col(value) * (F.col("_same") + F.col("_rank"))).drop("_head", "_p", "_h", "_v", "_above", "_same", "_rank")


@query("select slot, n, ntile(4) over (order by n, slot)::int as quartile from (select l_suppkey % 16 as slot, count(*)::bigint as n from lineitem group by 1) x")
def ntile_slot_load(db):
    loads = db.table("lineitem").groupBy((F.col("l_suppkey") % 16).alias("slot")).agg(F.count("*").alias("n"))
    return loads.withColumn("quartile", F.ntile(4).over(Window.orderBy("n", "slot")))


@query("select event_id, lag(event_type) over w as before, lead(event_type) over w as following from events window w as (partition by user_id order by ts, event_id)")
def lag_events(db):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return db.table("events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("following"))


@query("select o_orderkey, count(*) over (partition by o_custkey order by epoch(o_orderdate)::bigint range between 2592000 preceding and current row)::bigint as n from orders")
def range_frame_orders(db):
    at = F.unix_timestamp(F.col("o_orderdate").cast("timestamp"))
    return db.table("orders").select("o_orderkey", F.count("*").over(Window.partitionBy("o_custkey").orderBy(at).rangeBetween(-2592000, 0)).alias("n"))


@query("select o_orderkey, percent_rank() over w as pr, cume_dist() over w as cd, first_value(o_orderkey) over w as first_order from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def distribution_windows(db):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return db.table("orders").select("o_orderkey", F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"), F.first("o_orderkey").over(w).alias("first_order"))


@query(f"select term, freq from ({STAR_FREQ}) f order by freq desc, term")
def global_sort_terms(db):
    return _star(db).orderBy(F.desc("freq"), "term")


@query(f"select term, freq from ({STAR_FREQ}) f order by freq desc, term limit 5 offset 5")
def limit_offset_terms(db):
    return _star(db).orderBy(F.desc("freq"), "term").offset(5).limit(5)


_A, _B = (f"select term from ({sql.frequencies([n], MULTI_KW)}) f" for n in MULTI)


def _terms(db, i):
    return session.network_frequencies(db, MULTI_KW, MULTI[i]).select("term")


@query(f"select term, count(*)::bigint as n from ({_A} union all {_B}) x group by term")
def union_cn_terms(db):
    return _terms(db, 0).unionByName(_terms(db, 1)).groupBy("term").agg(F.count("*").alias("n"))


@query(f"{_A} intersect {_B}")
def intersect_terms(db):
    return _terms(db, 0).intersect(_terms(db, 1))


@query(f"{_A} except {_B}")
def except_terms(db):
    return _terms(db, 0).subtract(_terms(db, 1))


_WORDS, _ITEMS = (f"select unnest({sql.tokens('text')}) as term from {t}" for t in ("documents", "benchmark"))


def _words(db, name):
    return db.table(name).select(F.explode(tokenize(F.col("text"))).alias("term"))


@query(f"{_WORDS} except all {_ITEMS}")
def except_all_terms(db):
    return _words(db, "documents").exceptAll(_words(db, "benchmark"))


@query(f"{_WORDS} intersect all {_ITEMS}")
def intersect_all_terms(db):
    return _words(db, "documents").intersectAll(_words(db, "benchmark"))


# ---- functions -------------------------------------------------------------------------------------------------------


@query("select p_partkey, upper(p_name) as up, length(p_name)::int as n, replace(p_name, ' ', '-') as dashed, substr(p_name, 1, 3) as head, trim(p_brand) as brand, levenshtein(p_name, p_type)::int as dist, translate(p_name, 'aeiou', '12345') as digits from part")
def string_fns(db):
    c = F.col("p_name")
    return db.table("part").select("p_partkey", F.upper(c).alias("up"), F.length(c).alias("n"), F.regexp_replace(c, " ", "-").alias("dashed"), F.substring(c, 1, 3).alias("head"), F.trim("p_brand").alias("brand"), F.levenshtein(c, F.col("p_type")).alias("dist"), F.translate(c, "aeiou", "12345").alias("digits"))


@query(f"select page_id, len({sql.tokens(chr(114) + 'egexp_replace(regexp_replace(html, ' + chr(39) + '(?s)<(script|style).*?</(script|style)>' + chr(39) + ', ' + chr(39) + ' ' + chr(39) + ', ' + chr(39) + 'g' + chr(39) + '), ' + chr(39) + '<[^>]*>' + chr(39) + ', ' + chr(39) + ' ' + chr(39) + ', ' + chr(39) + 'g' + chr(39) + ')')})::bigint as n_tokens from pages")
def pages_strip_html(db):
    plain = F.regexp_replace(F.regexp_replace("html", r"(?s)<(script|style).*?</(script|style)>", " "), "<[^>]*>", " ")
    return db.table("pages").select("page_id", F.size(tokenize(plain)).cast("bigint").alias("n_tokens"))


@query("select year(o_orderdate)::int as y, month(o_orderdate)::int as m, count(*)::bigint as n, min(date_diff('day', date '1992-01-01', o_orderdate::date))::int as first_day from orders group by 1, 2")
def date_fns(db):
    d = F.col("o_orderdate")
    return db.table("orders").groupBy(F.year(d).alias("y"), F.month(d).alias("m")).agg(F.count("*").alias("n"), F.min(F.datediff(F.to_date(d), F.lit("1992-01-01").cast("date"))).alias("first_day"))


@query("select s_suppkey, round(cbrt(s_suppkey + 1), 6) as root, floor(pow(s_suppkey, 0.5))::bigint as half, greatest(s_suppkey, 7)::bigint as at_least, round(log2(s_suppkey + 1), 6) as bits from supplier")
def math_shares(db):
    k = F.col("s_suppkey")
    return db.table("supplier").select("s_suppkey", F.round(F.cbrt(k + 1), 6).alias("root"), F.floor(F.pow(k.cast("double"), F.lit(0.5))).alias("half"), F.greatest(k, F.lit(7)).alias("at_least"), F.round(F.log2(k + 1), 6).alias("bits"))


@query("select s_suppkey, (s_suppkey & 6)::bigint as masked, bit_count(s_suppkey)::int as ones, (s_suppkey << 2)::bigint as shifted from supplier")
def bit_masks(db):
    k = F.col("s_suppkey")
    return db.table("supplier").select("s_suppkey", k.bitwiseAND(6).alias("masked"), F.bit_count(k).alias("ones"), F.shiftleft(k, 2).alias("shifted"))


@query(f"select p_partkey, array_to_string(list_sort(list_distinct(terms)), ' ') as words, len(terms)::int as n, list_contains(terms, 'red') as red from {sql.view('part')}")
def array_fns(db):
    return db.view("part").select("p_partkey", F.array_join(F.array_sort(F.array_distinct("terms")), " ").alias("words"), F.size("terms").alias("n"), F.array_contains("terms", "red").alias("red"))


@query(f"select doc_id, term, count(*)::bigint as n from (select doc_id, unnest({sql.tokens('text')}) as term from documents) x group by all")
def map_term_counts(db):
    return db.view("documents").select("doc_id", F.explode(term_counts(F.col("terms"))).alias("term", "n"))


@query("select event_id, json_extract(props, '$.k')::bigint as k from events")
def json_props(db):
    return db.table("events").select("event_id", F.from_json("props", "k bigint").getField("k").alias("k"))


@query("select sum(coalesce(nullif(p_size, 10), 0))::bigint as total, count(nullif(p_size, 10))::bigint as n, sum(case when p_size > 25 then 1 else 0 end)::bigint as large from part")
def null_safety(db):
    return db.table("part").agg(F.sum(F.coalesce(F.nullif(F.col("p_size"), F.lit(10)), F.lit(0))).alias("total"), F.count(F.nullif(F.col("p_size"), F.lit(10))).alias("n"), F.sum(F.when(F.col("p_size") > 25, 1).otherwise(0)).alias("large"))


@query("select c_custkey from customer c where exists (select 1 from orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 400000)")
def exists_subquery(db):
    for t in ("customer", "orders"):
        db.table(t).createOrReplaceTempView(f"tg_{t}")
    return db.spark.sql("select c_custkey from tg_customer c where exists (select 1 from tg_orders o where o.o_custkey = c.c_custkey and o.o_totalprice > 400000)")


@query("select s_suppkey, l_orderkey, l_extendedprice from (select l_suppkey as s_suppkey, l_orderkey, l_extendedprice, row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_linenumber) as r from lineitem) where r <= 2")
def lateral_topk(db):
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return db.table("lineitem").withColumn("r", F.row_number().over(w)).where("r <= 2").select(F.col("l_suppkey").alias("s_suppkey"), "l_orderkey", "l_extendedprice")


# ---- sinks, user functions, SQL --------------------------------------------------------------------------------------


@query("select leaf, key, volume from (" + search.ORACLES["leaf_volumes_star"] + ") v")
def roundtrip_parquet_volumes(db):
    path = shared_folder(db.spark)
    write(volumes.leaf_volumes(star_of(db, workloads.order_root(), search.ORDER_KW)), path)
    return read(db.spark, path)


@query("select r_regionkey, r_name from region")
def roundtrip_json_csv(db):
    a, b = shared_folder(db.spark), shared_folder(db.spark)
    write(db.table("region").select("r_regionkey", "r_name"), a, "json")
    write(read(db.spark, a, "json", "r_regionkey int, r_name string"), b, "csv")
    return read(db.spark, b, "csv", "r_regionkey int, r_name string")


@query(f"select term, count(*)::bigint as n from (select unnest({sql.tokens('text')}) as term from documents) x group by term")
def arrow_udf_tokens(db):
    """A tokenizer of the user's own, as an Arrow-batched function."""
    @F.pandas_udf(T.ArrayType(T.StringType()))
    def words(text: pd.Series) -> pd.Series:
        import re

        cut = re.compile(r"[^\w#]+")
        return text.fillna("").map(lambda t: [x for x in cut.split(t.lower()) if x])

    return db.table("documents").select(F.explode(words("text")).alias("term")).groupBy("term").agg(F.count("*").alias("n"))


@query("select s_suppkey, cell::int as cell from supplier, range(8) r(cell) where cell % 2 = s_suppkey % 2")
def udtf_cell_copies(db):
    class Copies:
        def eval(self, bucket: int, share: int, cells: int):
            for c in range(bucket, cells, share):
                yield (c,)

    copies = F.udtf(Copies, returnType="cell int")
    db.spark.udtf.register("tg_copies", copies)
    db.table("supplier").createOrReplaceTempView("tg_supplier")
    return db.spark.sql("select s_suppkey, cell from tg_supplier, lateral tg_copies(cast(s_suppkey % 2 as int), 2, 8)")


@query(f"select p_brand, term, count(*)::bigint as n from (select p_brand, unnest({sql.tokens('p_name')}) as term from part) x group by all")
def udaf_bag_merge(db):
    """Bags of terms merged to one bag of counts by a grouped function of the user's own."""
    @F.pandas_udf(T.MapType(T.StringType(), T.LongType()))
    def merged(term: pd.Series, n: pd.Series) -> dict:
        return n.groupby(term).sum().to_dict()

    # counts by (brand, term, task) first: the function gets a bag of counts from each task, not the texts
    rows = db.table("part").select("p_brand", F.explode(tokenize(F.col("p_name"))).alias("term"))
    parts = rows.groupBy("p_brand", "term", F.spark_partition_id()).agg(F.count("*").alias("n"))
    return parts.groupBy("p_brand").agg(merged("term", "n").alias("bag")).select("p_brand", F.explode("bag").alias("term", "n"))


@query(STAR_FREQ)
def arrow_kernel_star_term_freq(db):
    """The star counted cell by cell in Arrow kernels: leaf rows are built up, facts probe them, volumes are emitted."""
    return cell_frequencies(star_of(db), [2, 2, 2], drop=STAR_KW)


@query("select count(*)::bigint as n_words from (select unnest(string_split_regex(trim(text, ' \t\n\r'), '\\s+')) as t from documents where text <> '')")
def mapinarrow_tokens(db):
    import pyarrow as pa

    def count(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len((t or "").split()) for t in b.column(0).to_pylist()], pa.int64())], ["n"])

    return db.table("documents").select("text").mapInArrow(count, "n bigint").agg(F.sum("n").alias("n_words"))


@query("select p_partkey, p_name from part")
def sort_within_partitions(db):
    return db.table("part").select("p_partkey", "p_name").repartition(4, "p_partkey").sortWithinPartitions("p_name")


@query(f"select term, count(*)::bigint as n from (select unnest({sql.tokens('text')}) as term from documents) x group by term")
def wordcount_documents(db):
    """Map, combine, reduce: the aggregate's partial side is the combiner."""
    return map_combine_reduce(db.view("documents"), lambda df: df.select(F.explode("terms").alias("term")), ["term"], F.count("*").alias("n"))


def map_combine_reduce(df, mapper, keys, *aggregates):
    return mapper(df).groupBy(*keys).agg(*aggregates)


@query(STAR_FREQ)
def sql_star_term_freq(db):
    return sqlapi.star_sql(db, STAR_KW)


@query("select 0::bigint as n_differences")
def topk_measure_recall(db):
    """An approximate top k against the exact one: terms of the exact top 10 that are missing."""
    exact = frequency.top_terms(db.view("documents").select(F.explode("terms").alias("term")).groupBy("term").agg(F.count("*").alias("freq")), 10)
    approx = db.view("documents").select(F.explode("terms").alias("term")).agg(F.expr("approx_top_k(term, 10, 50000)").alias("top")).select(F.inline("top"))
    return exact.join(approx.select(F.col("item").alias("term")), "term", "left_anti").agg(F.count("*").alias("n_differences"))


__all__ = ["baselines", "measures"]
