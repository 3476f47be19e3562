"""Queries of the grid: shares, cells, costs, placement, skew."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import workloads
from ..catalog import Database
from ..operators import baselines, frequency, grid, measures, placement, skew
from ..operators.trees import compile_tree, starify
from ..operators.volumes import Leaf, Star
from . import search, sql
from .search import ORDER_KW, STAR_FREQ, STAR_KW, star_of

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


SHARES, FINE = [2, 2, 2], [3, 3, 3]
#: Hash sample of the queries: rows with key * 7919 mod 100 < 10.
M, BELOW = 100, 10


def bare_star(db: Database, profile: str | None = None) -> Star:
    """All line items with parts, suppliers and orders, without keywords: the load of the distribution experiments."""
    facts = db.table("lineitem").select("l_partkey", "l_suppkey", "l_orderkey")
    if profile:
        facts = skew.make_skewed(facts, profile)
    bag = F.array().cast("array<string>").alias("terms")
    leaf = lambda t, k: Leaf(db.table(t).select(F.col(k).alias("key"), bag), True, t)
    return Star(facts.select("*", bag), ["l_partkey", "l_suppkey", "l_orderkey"], [leaf("part", "p_partkey"), leaf("supplier", "s_suppkey"), leaf("orders", "o_orderkey")])


AXES = (("part", "p_partkey", "l_partkey"), ("supplier", "s_suppkey", "l_suppkey"), ("orders", "o_orderkey", "l_orderkey"))
SKEWED = {
    "hot_corner": "(select l.* from lineitem l, range(case when l_suppkey % 10 = 0 and l_partkey % 10 = 0 then 40 when l_suppkey % 2 = 1 and l_partkey % 2 = 1 then 0 else 1 end) r)",
    "half_idle": "(select l.* from lineitem l, range(case when l_suppkey % 10 = 0 then 10 when l_suppkey % 2 = 1 then 0 else 1 end) r)",
}
SKEWED = {k: v.replace(", range(", ", lateral (select unnest(range(").replace(" end) r)", " end))) r)") for k, v in SKEWED.items()}


def cell_sql(shares, key=("l_partkey", "l_suppkey", "l_orderkey")) -> str:
    a, b, c = shares
    return f"(({key[0]} % {a}) * {b * c} + ({key[1]} % {b}) * {c} + {key[2]} % {c})::int"


def copies_sql(shares) -> str:
    """(leaf, cell, key) of all copies."""
    a, b, c = shares
    grid_ = f"(select x * {b * c} + y * {c} + z as cell, x, y, z from range({a}) r1(x), range({b}) r2(y), range({c}) r3(z))"
    return " union all ".join(f"select {i + 1}::int as leaf, g.cell::int as cell, {k} as key from {t}, {grid_} g where {k} % {s} = g.{v}" for i, ((t, k, _), s, v) in enumerate(zip(AXES, shares, "xyz")))


# ---- the triangle ----------------------------------------------------------------------------------------------------

def triangle(db: Database) -> tuple[DataFrame, DataFrame, DataFrame]:
    """The pairs of part and supplier, supplier and order, part and order of all line items."""
    pairs = db.table("lineitem").select(F.col("l_partkey").alias("a"), F.col("l_suppkey").alias("b"), F.col("l_orderkey").alias("c"))
    return tuple(pairs.select(*p).where(f"{p[0]} is not null and {p[1]} is not null").distinct() for p in ("ab", "bc", "ac"))


@query("with l as (select l_partkey as a, l_suppkey as b, l_orderkey as c from lineitem) select a, b, c from (select distinct a, c from l) t join (select distinct b, c from l) s using (c) join (select distinct a, b from l) r using (a, b)")
def triangle_grid_join(db):
    # orders have few suppliers, suppliers many parts: the join over orders comes first, so the roles of a and c are turned
    r, s, t = triangle(db)
    turned = grid.grid_triangle_join(t.select(F.col("a"), F.col("c").alias("b")), s.select(F.col("c").alias("b"), F.col("b").alias("c")), r.select("a", F.col("b").alias("c")), [2, 2, 2])
    return turned.select("a", F.col("c").alias("b"), F.col("b").alias("c"))


@query("with l as (select l_partkey as a, l_suppkey as b, l_orderkey as c from lineitem), n as (select (select count(*) from (select distinct a, b from l where a is not null and b is not null) x) as r, (select count(*) from (select distinct b, c from l where b is not null and c is not null) y) as s, (select count(*) from (select distinct a, c from l where a is not null and c is not null) z) as t) select v.a::int as a, v.b::int as b, v.c::int as c, (n.r * v.c + n.s * v.a + n.t * v.b)::bigint as cost from n, (values (1, 1, 8), (1, 2, 4), (2, 2, 2), (4, 2, 1), (8, 1, 1)) v(a, b, c)")
def triangle_cost_table(db):
    r, s, t = triangle(db)
    n = r.agg(F.count("*").alias("r")).crossJoin(s.agg(F.count("*").alias("s"))).crossJoin(t.agg(F.count("*").alias("t")))
    v = db.spark.createDataFrame([(1, 1, 8), (1, 2, 4), (2, 2, 2), (4, 2, 1), (8, 1, 1)], "a int, b int, c int")
    return n.crossJoin(v).select("a", "b", "c", (F.col("r") * F.col("c") + F.col("s") * F.col("a") + F.col("t") * F.col("b")).alias("cost"))


# ---- shares, cells, copies -------------------------------------------------------------------------------------------


@query("select a::int as a, b::int as b, c::int as c, (f + s * b * c + t * a * c + p * a * b)::bigint as cost from (select count(*) as f from lineitem) x, (select count(*) as s from part) s, (select count(*) as t from supplier) t, (select count(*) as p from orders) p, (values (1, 1, 8), (1, 2, 4), (2, 2, 2), (2, 1, 4), (8, 1, 1)) v(a, b, c)")
def star_cost_table(db):
    n = db.table("lineitem").agg(F.count("*").alias("f"))
    for t, c in (("part", "s"), ("supplier", "t"), ("orders", "p")):
        n = n.crossJoin(db.table(t).agg(F.count("*").alias(c)))
    v = db.spark.createDataFrame([(1, 1, 8), (1, 2, 4), (2, 2, 2), (2, 1, 4), (8, 1, 1)], "a int, b int, c int")
    return n.crossJoin(v).select("a", "b", "c", F.expr("f + s * b * c + t * a * c + p * a * b").alias("cost"))


@query("select s_suppkey as key, row_number() over (order by s_suppkey)::bigint as number, (row_number() over (order by s_suppkey) % 2)::int as bucket from supplier")
def bucket_numbering(db):
    return grid.numbered_buckets(db.table("supplier").select(F.col("s_suppkey").alias("key")), "key", 2)


@query("select (o_orderkey % 3)::int as bucket, count(*)::bigint as n from orders group by 1")
def bucket_hash_mod(db):
    return db.table("orders").groupBy(grid.bucket(F.col("o_orderkey"), 3, "mod").alias("bucket")).agg(F.count("*").alias("n"))


@query(f"select {cell_sql(SHARES)} as cell, count(*)::bigint as n from lineitem group by 1")
def cell_fact_counts(db):
    return grid.fact_cells(bare_star(db), SHARES, "mod")


@query(f"select leaf, cell, count(*)::bigint as n from ({copies_sql(SHARES)}) c group by all")
def cell_leaf_counts(db):
    return grid.leaf_copies(bare_star(db), SHARES, "mod").groupBy("leaf", "cell").agg(F.count("*").alias("n"))


@query(STAR_FREQ)
def grid_star_term_freq(db):
    return grid.grid_frequencies(star_of(db), SHARES, drop=STAR_KW)


@query(sql.frequencies([workloads.order_root()], ORDER_KW))
def grid_order_root_freq(db):
    return grid.grid_frequencies(star_of(db, workloads.order_root(), ORDER_KW), [2, 2, 2], drop=ORDER_KW)


@query(STAR_FREQ)
def grid_no_prune_no_dedupe(db):
    return grid.grid_frequencies(star_of(db), SHARES, prune=False, dedupe=False, drop=STAR_KW)


# ---- uneven cells ----------------------------------------------------------------------------------------------------


@query(f"select {cell_sql(FINE)} as cell, count(*)::bigint as n from {SKEWED['hot_corner']} l group by 1")
def uneven_grid_counts(db):
    return grid.fact_cells(bare_star(db, "hot_corner"), FINE, "mod")


def cost_sql(shares, facts: str, sampled: bool) -> str:
    up = f"{M / BELOW}::double" if sampled else "1.0::double"
    keep = lambda k: f" where ({k} * 7919) % {M} < {BELOW}" if sampled else ""
    a, b, c = shares
    digits = f"(cell // {b * c}) % {a}", f"(cell // {c}) % {b}", f"cell % {c}"
    ctes, joins, prod, total = "", "", "fact_est", ""
    for i, ((t, k, _), s, d) in enumerate(zip(AXES, shares, digits), 1):
        ctes += f", l{i} as (select {k} % {s} as b, count(*) * {up} as leaf_est, count(*) * {up} / (count(distinct {k}) * {up}) as per from {t}{keep(k)} group by 1)"
        joins += f" left join l{i} on l{i}.b = {d}"
        prod += f" * coalesce(l{i}.per, 0)"
        total += f" + coalesce(l{i}.leaf_est, 0)"
    return f"with f as (select {cell_sql(shares)} as cell, count(*) * {up} as fact_est from {facts} l{keep('l_partkey')} group by 1){ctes} select cell, fact_est, {prod} as join_est, fact_est + {prod}{total} as cost from f{joins}"


@query(cost_sql(SHARES, "lineitem", False))
def cell_cost_exact(db):
    return placement.cell_costs(bare_star(db), SHARES, kind="mod").select("cell", "fact_est", "join_est", "cost")


@query(cost_sql(SHARES, "lineitem", True))
def cell_cost_sampled(db):
    return placement.cell_costs(placement.sampled(bare_star(db), M, BELOW), SHARES, BELOW / M, "mod").select("cell", "fact_est", "join_est", "cost")


@query(f"select cell, e.cost as est, t.cost as truth, abs(e.cost - t.cost) / t.cost as rel_error from ({cost_sql(SHARES, 'lineitem', True)}) e full join ({cost_sql(SHARES, 'lineitem', False)}) t using (cell)")
def cell_cost_error(db):
    est = placement.cell_costs(placement.sampled(bare_star(db), M, BELOW), SHARES, BELOW / M, "mod")
    return measures.cost_error(est, placement.cell_costs(bare_star(db), SHARES, kind="mod")).select("cell", "est", "truth", "rel_error")


@query(f"select count(*)::bigint as n, sum(o_orderkey)::bigint as keys from orders where (o_orderkey * 7919) % {M} < {BELOW}")
def sample_hash_counts(db):
    return placement.sample_hash(db.table("orders"), "o_orderkey", M, BELOW).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("keys"))


@query()
def sample_simple_counts(db):
    return placement.sample_simple(db.table("orders"), 0.1).agg(F.count("*").alias("n"))


@query()
def sample_stratified(db):
    return placement.sample_stratified(db.table("orders"), "o_orderstatus", {"O": 0.1, "F": 0.2, "P": 0.3}).groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("select o_orderkey from (select o_orderkey, row_number() over (order by o_orderkey) - 1 as n from orders) where n % 50 = 0")
def sample_systematic(db):
    return placement.sample_systematic(db.table("orders"), ["o_orderkey"], 50).select("o_orderkey")


@query(f"select count(*)::bigint as n_copies from ({copies_sql(SHARES)}) c where leaf = 1 and cell in (select {cell_sql(SHARES)} from {SKEWED['half_idle']} l)")
def pruned_cells(db):
    return placement.useful_leaf_rows(bare_star(db, "half_idle"), 0, SHARES, "mod").agg(F.count("*").alias("n_copies"))


@query(f"select count(*)::bigint as n from {sql.tuple_set('lineitem', STAR_KW, 0)} l where l_partkey in (select p_partkey from {sql.tuple_set('part', STAR_KW, 1)}) and l_suppkey in (select s_suppkey from {sql.tuple_set('supplier', STAR_KW, 2)}) and l_orderkey in (select o_orderkey from {sql.tuple_set('orders', STAR_KW, 4)})")
def dangling_fact_prune(db):
    return placement.prune_dangling(star_of(db)).agg(F.count("*").alias("n"))


def _placed(db: Database, how, profile: str = "hot_corner", shares=FINE, slots: int = 8) -> DataFrame:
    costs = placement.costs_of(placement.cell_costs(bare_star(db, profile), shares, kind="mod"))
    return placement.slot_loads(bare_star(db, profile), shares, how(costs, slots), "mod")


@query()
def placement_greedy(db):
    return _placed(db, placement.place_greedy)


@query()
def placement_fact_rows(db):
    star = bare_star(db, "hot_corner")
    return placement.slot_loads(star, FINE, placement.place_by_facts(placement.cell_costs(star, FINE, kind="mod"), 8), "mod")


def loads_sql(shares, facts: str, slot: str) -> str:
    return f"""with f as (select {cell_sql(shares)} as cell, count(*) as n from {facts} l group by 1),
  s as (select {slot} as slot, sum(n) as facts from f group by 1),
  c as (select slot, count(*) as copies from (select distinct leaf, key, {slot} as slot from ({copies_sql(shares)}) x where cell in (select cell from f)) y group by 1)
  select slot::int as slot, coalesce(facts, 0)::bigint as facts, coalesce(copies, 0)::bigint as copies, (coalesce(facts, 0) + coalesce(copies, 0))::bigint as records from s full join c using (slot)"""


def greedy_sql(shares, facts: str, cost: str, slots: int = 8) -> str:
    """Loads after greedy placement: a recursive query takes the costliest cell to the first slot of least load."""
    zeros = ", ".join(["0.0::double"] * slots)
    costs = f"select cell, {cost} as cost, row_number() over (order by {cost} desc, cell) as i from ({cost_sql(shares, facts, False)}) q"
    steps = f"""cc as ({costs}),
  gg as (select 0::bigint as i, [{zeros}] as loads, -1 as cell, -1::bigint as slot union all
    select cc.i, list_transform(gg.loads, lambda x, k: case when k = list_position(gg.loads, list_min(gg.loads)) then x + cc.cost else x end), cc.cell, list_position(gg.loads, list_min(gg.loads)) - 1 from gg join cc on cc.i = gg.i + 1),
  mm as (select map_from_entries(list((cell, slot))) as slot_of from gg where cell >= 0)"""
    return "with recursive " + steps + ", " + loads_sql(shares, facts, "(select slot_of from mm)[cell]").removeprefix("with ")


ORACLES["placement_greedy"] = greedy_sql(FINE, SKEWED["hot_corner"], "cost")
ORACLES["placement_fact_rows"] = greedy_sql(FINE, SKEWED["hot_corner"], "fact_est")


@query(loads_sql(SHARES, SKEWED["hot_corner"], "cell"))
def placement_one_each(db):
    return _placed(db, placement.place_one_each, shares=SHARES)


@query(loads_sql(FINE, SKEWED["hot_corner"], "cell % 8"))
def placement_round_robin(db):
    return _placed(db, placement.place_round_robin)


@query(loads_sql(SHARES, "lineitem", "cell % 4"))
def slot_leaf_copies(db):
    star = bare_star(db)
    return placement.slot_loads(star, SHARES, {c: c % 4 for c in range(8)}, "mod")


@query(f"select (select count(*) from ({copies_sql(SHARES)}) c)::bigint as cell_copies, (select count(*) from (select distinct leaf, key, cell % 4 from ({copies_sql(SHARES)}) c))::bigint as slot_copies")
def slot_dedupe_saving(db):
    copies = grid.leaf_copies(bare_star(db), SHARES, "mod")
    return copies.agg(F.count("*").alias("cell_copies")).crossJoin(copies.select("leaf", "key", F.col("cell") % 4).distinct().agg(F.count("*").alias("slot_copies")))


@query("select 0::bigint as n_differences")
def theorem_cell_union(db):
    star = star_of(db, workloads.order_root(), ORDER_KW)
    other = {c: (c * 5 + 3) % 3 for c in range(12)}
    return measures.mismatches(grid.grid_frequencies(star, [3, 2, 2], other), grid.grid_frequencies(star, [3, 2, 2])).agg(F.count("*").alias("n_differences"))


@query(STAR_FREQ)
def salted_star_term_freq(db):
    return frequency.star_frequencies_by_key(placement.salt_hot_keys(star_of(db), 1, 10, 4), STAR_KW)


# ---- skew experiment -------------------------------------------------------------------------------------------------


@query(loads_sql(SHARES, SKEWED["half_idle"], "cell"))
def skew_no_adjust_loads(db):
    return _placed(db, placement.place_one_each, "half_idle", SHARES)


@query(greedy_sql(FINE, SKEWED["half_idle"], "cost"))
def skew_adjust_loads(db):
    return _placed(db, placement.place_greedy, "half_idle", FINE)


def skewed_star(db: Database, shape: str, profile: str = "half_idle") -> Star:
    """The load of a batch on skewed line items: their keys with the leaves of its shape, orders merged with customers in chains."""
    star = bare_star(db, profile)
    keep = [0, 1, 2] if shape == "star" else [1, 2]
    leaves = [star.leaves[i] for i in keep]
    if shape == "chain":
        merged = db.table("orders").join(db.table("customer").select("c_custkey"), F.col("o_custkey") == F.col("c_custkey"))
        leaves[1] = Leaf(merged.select(F.col("o_orderkey").alias("key"), F.array().cast("array<string>").alias("terms")), True, "orders")
    return Star(star.root, [star.keys[i] for i in keep], leaves)


#: Batches of the skew experiment with their shapes, and the grids of 8 and of 27 cells for each shape.
SKEW_BATCHES = (("Q1", "star"), ("Q4", "chain"), ("Q5", "chain"))
SKEW_GRIDS = {"star": {8: [2, 2, 2], 27: [3, 3, 3]}, "chain": {8: [2, 4], 27: [3, 9]}}


def skew_placement(star: Star, shape: str, cells: int, fraction: float = 0.1) -> dict[int, int]:
    """Cells on 8 slots: one each for 8 cells; else greedy by costs that are estimated on a simple random sample."""
    if cells == 8:
        return {c: c for c in range(8)}
    some = Star(placement.sample_simple(star.root, fraction), star.keys, [Leaf(placement.sample_simple(x.rows, fraction), x.unique, x.name) for x in star.leaves])
    costs = placement.costs_of(placement.cell_costs(some, SKEW_GRIDS[shape][cells], fraction, "mod"))
    # cells that the sample missed come last, at no cost
    return placement.place_greedy({c: costs.get(c, 0.0) for c in range(cells)}, 8)


@query()
def skew_experiment(db):
    """Loads of 8 slots with 8 and with 27 cells, for the batches of the skew experiment on one skewed table."""
    out = None
    for shape in ("star", "chain"):
        star = skewed_star(db, shape)
        for cells, shares in SKEW_GRIDS[shape].items():
            loads = placement.slot_loads(star, shares, skew_placement(star, shape, cells), "mod")
            row = measures.slot_load(loads, 8).crossJoin(loads.agg(F.sum("records").alias("records"), F.sum("facts").alias("facts")))
            batches = F.explode(F.array(*[F.lit(b) for b, s in SKEW_BATCHES if s == shape])).alias("batch")
            row = row.select(batches, F.lit(cells).alias("cells"), "max_records", "mean_records", "ratio", "idle", "records", "facts")
            out = row if out is None else out.unionByName(row)
    return out


@query()
def placement_simple_sample(db):
    """Greedy placement of 27 cells by costs estimated on a simple random sample of a tenth; the loads are those of all rows."""
    star = bare_star(db, "hot_corner")
    return placement.slot_loads(star, FINE, skew_placement(star, "star", 27), "mod")


def results_cost(facts, leaves, joins):
    """Another cost of a cell: its results count twice, leaf rows half, as they are sent but once probed."""
    out = facts + 2 * joins
    for x in leaves:
        out = out + x / 2
    return out


@query(f"select cell, fact_est + 2 * join_est + (cost - fact_est - join_est) / 2 as cost from ({cost_sql(SHARES, 'lineitem', False)}) q")
def cell_cost_plugged(db):
    return placement.cell_costs(bare_star(db), SHARES, kind="mod", cost=results_cost).select("cell", "cost")


@query(f"select (select count(*) from ({copies_sql(SHARES)}) c)::bigint as copies_8, (select count(*) from ({copies_sql(FINE)}) c)::bigint as copies_27, (select count(*) from {SKEWED['hot_corner']} l)::bigint as facts")
def skew_shuffle_growth(db):
    star = bare_star(db, "hot_corner")
    n = lambda shares, name: grid.leaf_copies(star, shares, "mod").agg(F.count("*").alias(name))
    return n(SHARES, "copies_8").crossJoin(n(FINE, "copies_27")).crossJoin(star.root.agg(F.count("*").alias("facts")))


@query(f"select slot, records from ({loads_sql(SHARES, 'lineitem', 'cell')}) l")
def grid_slot_records(db):
    return placement.slot_loads(bare_star(db), SHARES, {c: c for c in range(8)}, "mod").select("slot", "records")


@query(f"select max(records) as max_records, (sum(records) / 8)::double as mean_records, (8 - sum((facts > 0)::int))::bigint as idle from ({loads_sql(SHARES, SKEWED['half_idle'], 'cell')}) l")
def grid_imbalance(db):
    costs = placement.costs_of(placement.cell_costs(bare_star(db, "half_idle"), SHARES, kind="mod"))
    return measures.slot_load(placement.slot_loads(bare_star(db, "half_idle"), SHARES, placement.place_one_each(costs, 8), "mod"), 8).select("max_records", F.col("mean_records").cast("double").alias("mean_records"), "idle")


@query(f"select leaf, factor, count(*)::bigint as n_rows from (select leaf, key, count(*)::int as factor from ({copies_sql(SHARES)}) c group by all) k group by all")
def leaf_replication_factor(db):
    """Rows of each leaf by the number of their copies."""
    copies = grid.leaf_copies(bare_star(db), SHARES, "mod").groupBy("leaf", "key").agg(F.count("*").cast("int").alias("factor"))
    return copies.groupBy("leaf", "factor").agg(F.count("*").alias("n_rows"))


@query(f"select ((select count(*) from lineitem) + 4 * ((select count(*) from part) + (select count(*) from supplier) + (select count(*) from orders)))::double as predicted, ((select count(*) from ({copies_sql(SHARES)}) c) + (select count(*) from lineitem))::bigint as actual")
def comm_cost_predicted_vs_actual(db):
    n = lambda t: db.table(t).count()
    return measures.comm_cost(bare_star(db), SHARES, n("lineitem"), [n("part"), n("supplier"), n("orders")], "mod")


@query("select 0::bigint as n_differences")
def exactness_grid(db):
    star = starify(compile_tree(db, STAR_KW, workloads.star()))
    return measures.mismatches(grid.grid_frequencies(star, FINE, {c: c % 8 for c in range(27)}, drop=STAR_KW), baselines.straightforward(star, STAR_KW)).agg(F.count("*").alias("n_differences"))


def _ledger_sql() -> str:
    lines = sql.tuple_set("lineitem", STAR_KW, 0)
    sets = [sql.tuple_set(t, STAR_KW, 1 << i) for i, (t, _, _) in enumerate(AXES)]
    row = lambda step, before, after: f"select '{step}' as step, ({before})::bigint as rows_before, ({after})::bigint as rows_after"
    n = lambda rows: f"select count(*) from {rows} x"
    out = [row("combine facts", n(lines), f"select count(*) from (select distinct l_partkey, l_suppkey, l_orderkey from {lines}) x")]
    a, b, c = SHARES
    grid_ = f"(select x * {b * c} + y * {c} + z as cell, x, y, z from range({a}) r1(x), range({b}) r2(y), range({c}) r3(z))"
    for i, ((_, k, _), rows, v) in enumerate(zip(AXES, sets, "xyz"), 1):
        copies = f"(select g.cell from {rows} t, {grid_} g where {k} % {SHARES[i - 1]} = g.{v})"
        out.append(row(f"combine leaf {i}", n(rows), f"select count(distinct {k}) from {rows} x"))
        out.append(row(f"prune cells of leaf {i}", n(copies), f"select count(*) from {copies} x where cell in (select {cell_sql(SHARES)} from {lines} l)"))
    words = "(select unnest(terms) as t from (" + " union all ".join(f"select terms from {x} y" for x in (lines, *sets)) + ") z)"
    out.append(row("drop keywords", n(words), f"select count(*) from {words} x where t not in ({', '.join(repr(w) for w in STAR_KW)})"))
    keep = " and ".join(f"{f} in (select {k} from {rows} y)" for (_, k, f), rows in zip(AXES, sets))
    out.append(row("dangling facts", n(lines), f"select count(*) from {lines} x where {keep}"))
    return " union all ".join(out)


@query(_ledger_sql())
def reduction_ledger(db):
    return measures.ledger(star_of(db), SHARES, STAR_KW, "mod")
