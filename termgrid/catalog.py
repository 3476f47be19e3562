"""Relations, their text views and the schema graph."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.text import text_of, tokenize


@dataclass(frozen=True)
class Relation:
    """A relation to search: its keys, the attributes that make its text, and how its rows are read.

    ``unique`` names the keys that no two rows share: counts of these need no aggregation. ``merge`` lists small parents
    that are flattened into the text beforehand: (table, own column, their column).
    """

    name: str
    keys: tuple[str, ...]
    text: tuple[str, ...]
    unique: tuple[str, ...] = ()
    table: str = ""
    merge: tuple[tuple[str, str, str], ...] = ()
    where: str = ""

    def source(self) -> str:
        return self.table or self.name


@dataclass(frozen=True)
class ForeignKey:
    """Rows of ``child`` refer to rows of ``parent``; several child columns may refer to one parent."""

    child: str
    column: str
    parent: str
    key: str


@dataclass
class SchemaGraph:
    relations: dict[str, Relation] = field(default_factory=dict)
    edges: list[ForeignKey] = field(default_factory=list)

    def add(self, relation: Relation) -> SchemaGraph:
        self.relations[relation.name] = relation
        return self

    def add_fk(self, child: str, column: str, parent: str, key: str) -> SchemaGraph:
        """An edge; a relation can't refer to itself."""
        if child == parent:
            raise ValueError(f"{child} refers to itself")
        for name, col in ((child, column), (parent, key)):
            if col not in self.relations[name].keys:
                raise ValueError(f"{col} is no key of {name}")
        self.edges.append(ForeignKey(child, column, parent, key))
        return self

    def around(self, name: str) -> list[tuple[str, str, str, ForeignKey]]:
        """Neighbours as (own column, other relation, other column, edge)."""
        out = [(e.column, e.parent, e.key, e) for e in self.edges if e.child == name]
        return out + [(e.key, e.child, e.column, e) for e in self.edges if e.parent == name]


def orders_schema() -> SchemaGraph:
    """The order tables: line items refer to parts, suppliers and orders, orders to customers."""
    g = SchemaGraph()
    g.add(Relation("part", ("p_partkey",), ("p_name", "p_brand", "p_type"), ("p_partkey",)))
    g.add(Relation("supplier", ("s_suppkey",), ("s_name", "n_name", "r_name"), ("s_suppkey",), merge=(("nation", "s_nationkey", "n_nationkey"), ("region", "n_regionkey", "r_regionkey"))))
    g.add(Relation("orders", ("o_orderkey", "o_custkey"), ("o_orderstatus", "o_orderpriority"), ("o_orderkey",)))
    g.add(Relation("customer", ("c_custkey",), ("c_name", "c_mktsegment"), ("c_custkey",)))
    g.add(Relation("lineitem", ("l_orderkey", "l_partkey", "l_suppkey"), ("l_returnflag", "l_linestatus")))
    g.add(Relation("events", ("user_id",), ("event_type",)))
    g.add(Relation("documents", ("doc_id",), ("text",), ("doc_id",)))
    g.add_fk("lineitem", "l_partkey", "part", "p_partkey").add_fk("lineitem", "l_suppkey", "supplier", "s_suppkey")
    g.add_fk("lineitem", "l_orderkey", "orders", "o_orderkey").add_fk("orders", "o_custkey", "customer", "c_custkey")
    g.add_fk("events", "user_id", "customer", "c_custkey")
    return g


def references(db: Database) -> DataFrame:
    """``(child, fk, parent, pk, n_rows, n_linked)``: each edge of the schema graph, the rows of its child and those that find a parent."""
    def of(e: ForeignKey) -> DataFrame:
        rows = db.table(e.child).groupBy(F.col(e.column).alias("own")).agg(F.count("*").alias("n"))
        keys = db.table(e.parent).select(F.col(e.key).alias("key")).distinct()
        linked = F.sum(F.when(F.col("key").isNotNull(), F.col("n")).otherwise(0))
        names = [F.lit(x).alias(c) for x, c in ((e.child, "child"), (e.column, "fk"), (e.parent, "parent"), (e.key, "pk"))]
        return rows.join(keys, F.col("own") == F.col("key"), "left").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_rows"), F.coalesce(linked, F.lit(0)).alias("n_linked")).select(*names, "n_rows", "n_linked")

    return reduce(DataFrame.unionByName, [of(e) for e in db.graph.edges])


class Database:
    """A schema graph over a folder of Parquet tables, or over given DataFrames."""

    def __init__(self, spark: SparkSession, where: str | dict[str, DataFrame], graph: SchemaGraph | None = None, tokenizer: str | Callable = "alnum"):
        self.spark, self.where, self.graph, self.tokenizer = spark, where, graph or orders_schema(), tokenizer

    def table(self, name: str) -> DataFrame:
        return self.where[name] if isinstance(self.where, dict) else self.spark.read.parquet(f"{self.where}/{name}.parquet")

    def view(self, name: str, columns: Sequence[str] | None = None) -> DataFrame:
        """Keys and the bag of terms of a relation; only the columns in use are read."""
        r = self.graph.relations[name]
        df = self.table(r.source())
        if r.where:
            df = df.where(r.where)
        for parent, own, key in r.merge:
            # parents of fixed size in this schema; Spark broadcasts what its statistics show to be small
            df = df.join(self.table(parent), F.col(own) == F.col(key))
        return df.select(*r.keys, tokenize(text_of(columns or r.text), self.tokenizer).alias("terms"))
