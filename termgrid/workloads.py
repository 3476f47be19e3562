"""The experiments' query shapes and batches on the order tables."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .catalog import Database
from .operators.frequency import sum_terms, top_terms
from .operators.volumes import product
from .plans.networks import Node

PART, SUPPLIER, ORDERS, CUSTOMER = ("l_partkey", "p_partkey"), ("l_suppkey", "s_suppkey"), ("l_orderkey", "o_orderkey"), ("o_custkey", "c_custkey")


def star(part: int = 1, supplier: int = 2, orders: int = 4) -> Node:
    return Node("lineitem", 0, None, (Node("part", part, PART), Node("supplier", supplier, SUPPLIER), Node("orders", orders, ORDERS)))


def chain(supplier: int = 1, customer: int = 2) -> Node:
    return Node("lineitem", 0, None, (Node("supplier", supplier, SUPPLIER), Node("orders", 0, ORDERS, (Node("customer", customer, CUSTOMER),))))


def mix(part: int = 1, supplier: int = 2, customer: int = 4) -> Node:
    return Node("lineitem", 0, None, (Node("part", part, PART), Node("supplier", supplier, SUPPLIER), Node("orders", 0, ORDERS, (Node("customer", customer, CUSTOMER),))))


def two_orders() -> Node:
    """Two orders of one customer, each with one keyword."""
    return Node("customer", 0, None, (Node("orders", 1, ("c_custkey", "o_custkey")), Node("orders", 2, ("c_custkey", "o_custkey"))))


def order_root() -> Node:
    return Node("orders", 0, None, (Node("lineitem", 1, ("o_orderkey", "l_orderkey")), Node("lineitem", 2, ("o_orderkey", "l_orderkey")), Node("customer", 4, CUSTOMER)))


def supplier_root() -> Node:
    """Two line items of one supplier."""
    return Node("supplier", 0, None, (Node("lineitem", 1, ("s_suppkey", "l_suppkey")), Node("lineitem", 2, ("s_suppkey", "l_suppkey"))))


def event_pair() -> Node:
    return Node("events", 1, None, (Node("customer", 2, ("user_id", "c_custkey")),))


#: Words of the text views, by relation (fixed values of the given tables).
PART_WORDS = ("red", "old", "blue", "cold", "hot", "new", "widget", "bolt", "gear", "plate")
REGION_WORDS = ("america", "asia", "europe", "africa", "america", "europe", "asia", "africa", "america", "europe")
PRIORITY_WORDS = ("urgent", "high", "low", "urgent", "high", "low", "urgent", "high", "low", "urgent")
SEGMENT_WORDS = ("building", "machinery", "automobile", "household", "furniture", "building", "machinery", "automobile", "household", "furniture")


def batch(shape: str, number: int) -> list[tuple[int, list[str]]]:
    """Ten queries (qid, keywords), one keyword from the texts of each outer relation; batches turn the word lists."""
    turn = lambda words, by: [words[(i + by) % len(words)] for i in range(10)]
    parts, regions = turn(PART_WORDS, number), turn(REGION_WORDS, 3 * number)
    priorities, segments = turn(PRIORITY_WORDS, 2 * number), turn(SEGMENT_WORDS, number)
    rows = {"star": (parts, regions, priorities), "chain": (regions, segments), "mix": (parts, regions, segments)}[shape]
    return [(i, [r[i] for r in rows]) for i in range(10)]


#: For each shape the relations that hold its keywords, in their order.
HOLDERS = {"star": ("part", "supplier", "orders"), "chain": ("supplier", "customer"), "mix": ("part", "supplier", "customer")}


def _batch_facts(db: Database, shape: str, queries: Sequence[tuple[int, list[str]]]) -> tuple[DataFrame, list]:
    """Facts ``(qid, keys, terms, n0..)`` that every leaf of a query matches, and the leaves as (key, rows).

    Tuple sets get the query id as a column: a row is in the set of each query whose keyword it holds and whose others it
    lacks. Counting is then by (query, key), so tables are scanned once for the batch. The batch itself is a handful of
    literals.
    """
    holders = HOLDERS[shape]
    n = len(holders)
    b = F.broadcast(db.spark.createDataFrame([(q, *kw) for q, kw in queries], "qid int, " + ", ".join(f"kw{i} string" for i in range(n))))

    def member(rows: DataFrame, holds: int | None) -> DataFrame:
        has = [F.array_contains("terms", F.col(f"kw{i}")) for i in range(n)]
        cond = F.lit(True)
        for i in range(n):
            cond = cond & (has[i] if i == holds else ~has[i])
        gone = F.array(*[F.col(f"kw{i}") for i in range(n)])
        return rows.join(b, cond).withColumn("terms", F.filter("terms", lambda t: ~F.array_contains(gone, t))).drop(*[f"kw{i}" for i in range(n)])

    leaves = []
    for i, name in enumerate(holders):
        if name == "customer":
            # customers are joined into their orders first, query by query
            c = member(db.view("customer"), i).select(F.col("qid").alias("cq"), F.col("c_custkey").alias("ck"), F.col("terms").alias("ct"))
            o = db.view("orders").join(c, F.col("o_custkey") == F.col("ck"))
            o = o.join(b.withColumnRenamed("qid", "bq"), F.col("cq") == F.col("bq"))
            free = ~F.arrays_overlap("terms", F.array(*[F.col(f"kw{j}") for j in range(n)]))
            leaves.append(("l_orderkey", o.where(free).select("cq", F.col("o_orderkey").alias("key"), F.concat("terms", "ct").alias("terms")).withColumnRenamed("cq", "qid")))
        else:
            own = {"part": ("l_partkey", "p_partkey"), "supplier": ("l_suppkey", "s_suppkey"), "orders": ("l_orderkey", "o_orderkey")}[name]
            leaves.append((own[0], member(db.view(name), i).select("qid", F.col(own[1]).alias("key"), "terms")))
    facts = db.view("lineitem").select(*[k for k, _ in leaves], "terms")
    for i, (key, rows) in enumerate(leaves):
        nums = rows.groupBy("qid", "key").agg(F.count("*").alias(f"n{i}")).withColumnRenamed("qid", f"q{i}").withColumnRenamed("key", f"k{i}")
        on = F.col(key) == F.col(f"k{i}")
        facts = facts.join(nums, on if i == 0 else on & (F.col("q0") == F.col(f"q{i}")))
    facts = facts.join(b, F.col("q0") == F.col("qid")).where(~F.arrays_overlap("terms", F.array(*[F.col(f"kw{j}") for j in range(n)])))
    facts = facts.select("qid", *[k for k, _ in leaves], "terms", *[f"n{i}" for i in range(n)])
    return facts, leaves


def batch_result_counts(db: Database, shape: str, queries: Sequence[tuple[int, list[str]]]) -> DataFrame:
    """``(qid, n_results)`` of all queries of a batch in one plan, without a result; 0 for queries that have none."""
    facts, leaves = _batch_facts(db, shape, queries)
    counts = facts.groupBy("qid").agg(F.sum(product([F.col(f"n{i}") for i in range(len(leaves))])).alias("n"))
    every = db.spark.createDataFrame([(q,) for q, _ in queries], "qid int")
    return every.join(counts, "qid", "left").select("qid", F.coalesce("n", F.lit(0)).cast("bigint").alias("n_results"))


def batch_frequencies(db: Database, shape: str, queries: Sequence[tuple[int, list[str]]]) -> DataFrame:
    """``(qid, term, freq)`` of all queries of a batch in one plan."""
    facts, leaves = _batch_facts(db, shape, queries)
    n = len(leaves)
    out = facts.select("qid", F.explode("terms").alias("term"), product([F.col(f"n{i}") for i in range(n)]).alias("part"))
    each, all_rows = [], None
    for i, (key, rows) in enumerate(leaves):
        others = product([F.col(f"n{j}") for j in range(n) if j != i])
        each.append(F.struct(F.lit(i).alias("leaf"), F.col(key).alias("key"), others.alias("part")))
        tagged = rows.select("qid", F.lit(i).alias("leaf"), "key", "terms")
        all_rows = tagged if all_rows is None else all_rows.unionByName(tagged)
    volumes = facts.select("qid", F.inline(F.array(*each))).groupBy("qid", "leaf", "key").agg(F.sum("part").alias("part"))
    out = out.unionByName(all_rows.join(volumes, ["qid", "leaf", "key"]).select("qid", F.explode("terms").alias("term"), "part"))
    return out.groupBy("qid", "term").agg(F.sum("part").alias("freq"))


def batch_top(db: Database, shape: str, number: int, k: int = 10) -> DataFrame:
    return top_terms(batch_frequencies(db, shape, batch(shape, number)), k, by=("qid",))


def generated_batch(db: Database, shape: str, n: int = 10, seed: int = 1) -> list[list[str]]:
    """``n`` queries of a shape, made as the experiments make them: join the relations and take one word of each bag.

    The words of one query come from one joined result, each from the texts of its relation only, so each query has a
    result. Line items are taken in the order of a seeded hash; only these few meet the other relations, and reach the driver.
    """
    node = {"star": star, "chain": chain, "mix": mix}[shape]()
    facts = db.view("lineitem").select("l_partkey", "l_suppkey", "l_orderkey", "terms").dropna()
    rows = F.broadcast(facts.withColumn("at", F.xxhash64(F.lit(seed), "l_orderkey", "l_partkey", "l_suppkey")).orderBy("at", "l_orderkey", "l_partkey", "l_suppkey").limit(8 * n).withColumnRenamed("terms", "t_lineitem"))
    names = ["lineitem"]

    def hang(rows: DataFrame, x: Node) -> DataFrame:
        for c in x.children:
            rows = rows.join(db.view(c.relation).withColumnRenamed("terms", f"t_{c.relation}"), F.col(c.on[0]) == F.col(c.on[1]))
            names.append(c.relation)
            rows = hang(rows, c)
        return rows

    rows = hang(rows, node)
    picks = []
    for h in HOLDERS[shape]:
        others = F.flatten(F.array(*[F.col(f"t_{x}") for x in names if x != h]))
        own = F.array_except(F.col(f"t_{h}"), others)
        picks.append(F.get(own, F.pmod(F.xxhash64(F.lit(seed), "at", F.lit(h)), F.greatest(F.size(own), F.lit(1))).cast("int")).alias(h))
    made = rows.select("at", "l_orderkey", "l_partkey", "l_suppkey", *picks).dropna().dropDuplicates(list(HOLDERS[shape]))
    return [[r[h] for h in HOLDERS[shape]] for r in made.orderBy("at", *HOLDERS[shape]).limit(n).collect()]


def workload_bags(db: Database) -> DataFrame:
    """``(relation, term, n)``: the distinct terms of each outer relation with their rows."""
    out = None
    for r in ("part", "supplier", "orders", "customer"):
        words = db.view(r).select(F.lit(r).alias("relation"), F.explode(F.array_distinct("terms")).alias("term"))
        out = words if out is None else out.unionByName(words)
    return out.groupBy("relation", "term").agg(F.count("*").alias("n"))


def frequencies(db: Database, node: Node, keywords: Sequence[str]) -> DataFrame:
    from .operators.trees import compile_tree, tree_frequencies

    return tree_frequencies(compile_tree(db, keywords, node), keywords)


__all__ = ["batch", "batch_frequencies", "batch_result_counts", "batch_top", "chain", "event_pair", "frequencies", "generated_batch", "mix", "order_root", "star", "sum_terms", "supplier_root", "two_orders", "workload_bags"]
