"""Queries of the search itself: tuple sets, networks, volumes, frequencies, baselines, workloads."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import session, workloads
from ..catalog import Database, Relation, orders_schema, references
from ..functions.text import count_in, text_of, tokenize, without
from ..operators import baselines, frequency, measures, trees, tuplesets, volumes
from ..operators.cells import cell_frequencies
from ..plans.networks import Node
from ..sources import shared_folder
from . import sql

QUERIES: dict = {}
ORACLES: dict = {}

STAR_KW, CHAIN_KW, MIX_KW = ["red", "america", "urgent"], ["america", "building"], ["red", "america", "building"]
MULTI_KW = ["medium", "america"]
#: The two networks of the ambiguous query: one keyword is both a part type and an order priority.
MULTI = [
    Node("lineitem", 0, None, (Node("part", 1, workloads.PART), Node("supplier", 2, workloads.SUPPLIER))),
    Node("lineitem", 0, None, (Node("orders", 1, workloads.ORDERS), Node("supplier", 2, workloads.SUPPLIER))),
]


def query(oracle: str | None = None, name: str | None = None):
    """Registers a function of a Database under its name."""

    def add(f):
        @functools.wraps(f)
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            return f(Database(spark, sf_dir))

        QUERIES[name or f.__name__] = run
        if oracle:
            ORACLES[name or f.__name__] = oracle
        return f

    return add


def star_of(db: Database, node: Node | None = None, keywords=STAR_KW) -> volumes.Star:
    return trees.starify(trees.compile_tree(db, keywords, node or workloads.star()))


STAR_FREQ = sql.frequencies([workloads.star()], STAR_KW)
CHAIN_FREQ = sql.frequencies([workloads.chain()], CHAIN_KW)
MIX_FREQ = sql.frequencies([workloads.mix()], MIX_KW)

# ---- problem level ---------------------------------------------------------------------------------------------------


@query(sql.top(sql.frequencies([workloads.star()], STAR_KW), 10))
def cot_star_topk(db):
    return session.cooccurring_terms(db, STAR_KW, 10, 4)


@query(sql.top(sql.frequencies([workloads.star()], STAR_KW), 10))
def cot_star_topk_stored(db):
    """The same from tuple sets that are stored by mask, so that each relation is scanned once for all networks."""
    return session.cooccurring_terms(db, STAR_KW, 10, 4, store=shared_folder(db.spark))


@query(sql.top(sql.frequencies(MULTI, MULTI_KW), 10))
def cot_multi_cn(db):
    return session.cooccurring_terms(db, MULTI_KW, 10, 3, store=shared_folder(db.spark))


# networks are numbered by size and name: that of orders comes before that of parts
@query(" union all ".join(f"select {i}::int as cn_id, count(*)::bigint as n_results from ({sql.results(n, MULTI_KW)}) r" for i, n in enumerate(MULTI[::-1])))
def ks_results_count(db):
    return session.keyword_results(db, MULTI_KW, 3).groupBy("cn_id").agg(F.count("*").alias("n_results"))


@query(" union all ".join(f"select {i}::int as cn_id, array_to_string(tuples, ' ') as tuples from ({sql.result_tuples(n, MULTI_KW)}) r" for i, n in enumerate(MULTI[::-1])))
def ks_results(db):
    """Every result of the query, named by its rows."""
    return session.keyword_results(db, MULTI_KW, 3).select("cn_id", F.array_join("tuples", " ").alias("tuples"))


@query(f"select term, count(*)::bigint as n_results from ({sql.results(workloads.star(), STAR_KW)}) r, (select term from ({sql.top(STAR_FREQ, 4)}) t) w where list_contains(terms, term) group by term")
def expanded_query_results(db):
    """Feedback: the query with each of its four most frequent terms added, and the results that are then left."""
    words = session.expand_query(STAR_KW, session.cooccurring_terms(db, STAR_KW, 4, 4), 4)
    return session.refine_counts(session.keyword_results(db, STAR_KW, 4), words[len(STAR_KW):])


@query(" union all ".join(f"select {i}::int as cn_id, term, freq from ({sql.frequencies([n], MULTI_KW)}) f" for i, n in enumerate(MULTI)))
def cn_freq_breakdown(db):
    parts = [session.network_frequencies(db, MULTI_KW, n).select(F.lit(i).alias("cn_id"), "term", "freq") for i, n in enumerate(MULTI)]
    return parts[0].unionByName(parts[1])


@query(f"select doc_id, len(list_filter({sql.tokens('text')}, lambda t: t = 'the'))::bigint as n from documents")
def count_in_result(db):
    return db.view("documents").select("doc_id", count_in(F.col("terms"), "the").alias("n"))


@query("select 0::bigint as n_differences")
def keyword_prune_early_vs_late(db):
    late = frequency.star_frequencies(star_of(db)).where(~F.col("term").isin(STAR_KW))
    return measures.mismatches(frequency.star_frequencies(star_of(db), STAR_KW), late).agg(F.count("*").alias("n_differences"))


@query(f"select t as term, count(*)::bigint as n_results from ({sql.results(workloads.star(), STAR_KW)}) r, (values ('o'), ('f'), ('promo'), ('nation_11')) v(t) where list_contains(terms, t) group by t")
def refine_counts(db):
    return session.refine_counts(trees.joined(trees.compile_tree(db, STAR_KW, workloads.star())), ["o", "f", "promo", "nation_11"])


# ---- tuple sets ------------------------------------------------------------------------------------------------------


@query(f"select p_partkey, array_to_string(terms, ' ') as terms from {sql.view('part')}")
def text_view_part(db):
    return db.view("part").select("p_partkey", F.array_join("terms", " ").alias("terms"))


@query(f"select count(*)::bigint as n_tokens, count(distinct t)::bigint as n_distinct, sum(length(t))::bigint as n_chars from (select unnest({sql.tokens('text')}) as t from documents)")
def tokenize_documents(db):
    t = db.view("documents").select(F.explode("terms").alias("t"))
    counts = t.groupBy("t").agg(F.count("*").alias("n"))  # distinct terms once, instead of a distinct count beside plain sums
    return counts.agg(F.sum("n").alias("n_tokens"), F.count("*").alias("n_distinct"), F.sum(F.col("n") * F.length("t")).alias("n_chars"))


STOP = ("the", "of", "and", "de", "la", "der", "die", "und", "que", "le")


@query(f"select doc_id, len(list_filter({sql.tokens('text')}, lambda t: t not in {STOP}))::bigint as n from documents")
def stopword_filter(db):
    return db.view("documents").select("doc_id", F.size(without(F.col("terms"), STOP)).cast("bigint").alias("n"))


def _mask_sql(relations, keywords) -> str:
    mask = " + ".join(f"list_contains(terms, '{w}')::bigint * {1 << i}" for i, w in enumerate(keywords))
    return " union all ".join(f"select '{r}' as relation, ({mask})::bigint as kw_mask, count(*)::bigint as n from {sql.view(r)} group by all" for r in relations)


@query(_mask_sql(["part"], MULTI_KW + ["red"]).replace("'part' as relation, ", ""))
def kw_mask_hist(db):
    return tuplesets.with_mask(db.view("part"), MULTI_KW + ["red"]).groupBy("kw_mask").agg(F.count("*").alias("n"))


@query(_mask_sql(session.RELATIONS, STAR_KW))
def tuple_set_sizes(db):
    return tuplesets.mask_histogram(db, STAR_KW, session.RELATIONS)


# ---- networks --------------------------------------------------------------------------------------------------------


@query(" union all ".join(f"select '{e.child}' as child, '{e.column}' as fk, '{e.parent}' as parent, '{e.key}' as pk, count(*)::bigint as n_rows, (count(*) filter (where {e.column} in (select {e.key} from {e.parent})))::bigint as n_linked from {e.child}" for e in orders_schema().edges))
def schema_graph_edges(db):
    return references(db)


@query()
def cn_list(db):
    from ..plans.networks import canonical, classify

    rows = [(i, canonical(t), classify(t)[0], t.size()) for i, t in enumerate(session.networks(db, STAR_KW, 5))]
    return db.spark.createDataFrame(rows, "cn_id int, network string, shape string, size int")


@query(sql.frequencies([workloads.two_orders()], ["urgent", "low"]))
def cn_two_orders_one_customer(db):
    return frequency.star_frequencies(star_of(db, workloads.two_orders(), ["urgent", "low"]), ["urgent", "low"])


@query("select 0::bigint as n_shared")
def cn_disjointness(db):
    """Results of different networks over the same relations: the exact tuple sets share no row, so no result is in two."""
    ids = []
    for i, node in enumerate(session.networks(db, MULTI_KW, 3)):
        rows = trees.compile_tree(db, MULTI_KW, node)

        def tagged(b):
            key = F.sort_array(F.array(*[F.concat(F.lit(f"{b.name}."), F.col(c).cast("string")) for c in b.rows.columns if c != "terms"]))
            df = b.rows.withColumn("ids", key).withColumn("terms", F.col("ids"))
            return trees.Branch(df.drop("ids"), [(o, k, tagged(c)) for o, k, c in b.children], b.name, b.unique)

        # a result is the set of its tuples; line items without a key of their own count by their references
        ids.append(trees.joined(tagged(rows)).select(F.sort_array("terms").alias("ids"), F.lit(i).alias("cn")).distinct())
    both = functools.reduce(lambda a, b: a.unionByName(b), ids)
    return both.groupBy("ids").agg(F.count("*").alias("n")).where("n > 1").agg(F.count("*").alias("n_shared"))


@query(sql.frequencies([Node("documents", 3)], ["eine", "nicht"]))
def single_relation_cot_documents(db):
    return session.network_frequencies(db, ["eine", "nicht"], Node("documents", 3))


@query(sql.frequencies([workloads.event_pair()], ["purchase", "building"]))
def pair_cot_events_customer(db):
    return session.network_frequencies(db, ["purchase", "building"], workloads.event_pair())


# ---- counting --------------------------------------------------------------------------------------------------------


@query("select part::int as part, count(*)::bigint as n from (select ntile(2) over (order by p_partkey) as part from part) group by part")
def even_input_splits(db):
    from pyspark.sql import Window

    # the exact split of the example numbers all rows in one task; scans split by bytes instead
    return db.table("part").select(F.ntile(2).over(Window.orderBy("p_partkey")).alias("part")).groupBy("part").agg(F.count("*").alias("n"))


@query("select conv_id as key, count(*)::bigint as num, count(*)::bigint as bags from conversations group by conv_id")
def combine_leaf_counts(db):
    rows = db.table("conversations").select(F.col("conv_id").alias("key"), F.array(F.col("role")).alias("terms"))
    bags = volumes.combine_leaf(volumes.Leaf(rows))
    return bags.groupBy("key").agg(F.sum(F.when(F.col("term").isNull(), F.col("n"))).alias("num"), F.sum(F.when(F.col("term").isNotNull(), F.col("n"))).alias("bags"))


@query("select p_partkey as key, 1::bigint as num from part")
def combine_skip_pk(db):
    return volumes.num_array(volumes.Leaf(db.view("part").withColumnRenamed("p_partkey", "key"), unique=True))


@query("select l_partkey, l_suppkey, count(*)::bigint as m, (2 * count(*))::bigint as n_terms from lineitem group by all")
def combine_fact_counts(db):
    bags = volumes.combine_fact(db.view("lineitem"), ["l_partkey", "l_suppkey"])
    return bags.groupBy("l_partkey", "l_suppkey").agg(F.sum(F.when(F.col("term").isNull(), F.col("n"))).alias("m"), F.sum(F.when(F.col("term").isNotNull(), F.col("n"))).alias("n_terms"))


@query("select conv_id as key, count(*)::bigint as num from conversations group by conv_id")
def num_array_conversations(db):
    return volumes.num_array(volumes.Leaf(db.table("conversations").select(F.col("conv_id").alias("key"))))


ORDER_KW = ["r", "a", "building"]


def _order_root_sql(what: str) -> str:
    base = f"(select * from {sql.tuple_set('orders', ORDER_KW, 0)})"
    n1 = f"(select l_orderkey as k1, count(*) as n1 from {sql.tuple_set('lineitem', ORDER_KW, 1)} group by 1)"
    n2 = f"(select l_orderkey as k2, count(*) as n2 from {sql.tuple_set('lineitem', ORDER_KW, 2)} group by 1)"
    n3 = f"(select c_custkey as k3, count(*) as n3 from {sql.tuple_set('customer', ORDER_KW, 4)} group by 1)"
    return f"with f as (select * from {base} o join {n1} a on o_orderkey = k1 join {n2} b on o_orderkey = k2 join {n3} c on o_custkey = k3) {what}"


@query(_order_root_sql("select o_orderkey as key_1, o_orderkey as key_2, o_custkey as key_3, count(*)::bigint as m, max(n1 * n2 * n3)::bigint as volume from f group by all"))
def fact_volumes_star(db):
    return volumes.fact_volumes(star_of(db, workloads.order_root(), ORDER_KW))


@query(_order_root_sql("select 1::int as leaf, o_orderkey as key, sum(n2 * n3)::bigint as volume from f group by all union all select 2, o_orderkey, sum(n1 * n3)::bigint from f group by all union all select 3, o_custkey, sum(n1 * n2)::bigint from f group by all"))
def leaf_volumes_star(db):
    return volumes.leaf_volumes(star_of(db, workloads.order_root(), ORDER_KW))


@query(_order_root_sql(f"""select 0::int as node, sum(n1 * n2 * n3)::bigint as volume, count(*)::bigint as n from f
  union all select 1, sum(v)::bigint, count(*) from (select o_orderkey as k, sum(n2 * n3) as v from f group by 1) x join {sql.tuple_set('lineitem', ORDER_KW, 1)} on l_orderkey = k
  union all select 2, sum(v)::bigint, count(*) from (select o_orderkey as k, sum(n1 * n3) as v from f group by 1) x join {sql.tuple_set('lineitem', ORDER_KW, 2)} on l_orderkey = k
  union all select 3, sum(v)::bigint, count(*) from (select o_custkey as k, sum(n1 * n2) as v from f group by 1) x join {sql.tuple_set('customer', ORDER_KW, 4)} on c_custkey = k"""))
def volume_records_star(db):
    return volumes.volume_records(star_of(db, workloads.order_root(), ORDER_KW)).groupBy("node").agg(F.sum("volume").alias("volume"), F.count("*").alias("n"))


@query(STAR_FREQ)
def freq_emit_each(db):
    return frequency.star_frequencies(star_of(db), STAR_KW, "each")


@query(STAR_FREQ)
def freq_emit_local(db):
    return frequency.star_frequencies(star_of(db), STAR_KW, "local")


@query(STAR_FREQ)
def star_term_freq(db):
    return frequency.star_frequencies_by_key(star_of(db), STAR_KW)


@query(f"select term, freq, rank() over (order by freq desc)::bigint as rank from ({STAR_FREQ}) f qualify rank <= 12")
def topk_with_ties(db):
    return frequency.top_terms(frequency.star_frequencies(star_of(db), STAR_KW), 12, "all")


@query(f"select count(*)::bigint as n_results from ({sql.results(workloads.order_root(), ORDER_KW)}) r")
def cn_result_count(db):
    return volumes.result_count(star_of(db, workloads.order_root(), ORDER_KW))


# ---- other shapes ----------------------------------------------------------------------------------------------------


@query(CHAIN_FREQ)
def chain_term_freq(db):
    return frequency.star_frequencies(star_of(db, workloads.chain(), CHAIN_KW), CHAIN_KW)


@query(MIX_FREQ)
def mix_term_freq(db):
    return frequency.star_frequencies(star_of(db, workloads.mix(), MIX_KW), MIX_KW)


@query(CHAIN_FREQ)
def tree_chain_term_freq(db):
    return workloads.frequencies(db, workloads.chain(), CHAIN_KW)


@query(MIX_FREQ)
def tree_mix_term_freq(db):
    return workloads.frequencies(db, workloads.mix(), MIX_KW)


@query(sql.frequencies([workloads.order_root()], ORDER_KW))
def order_root_star(db):
    return frequency.star_frequencies(star_of(db, workloads.order_root(), ORDER_KW), ORDER_KW)


SUPPLIER_KW = ["r", "a"]


@query(sql.frequencies([workloads.supplier_root()], SUPPLIER_KW))
def supplier_root_star(db):
    """Two line items of one supplier: hundreds of rows of each leaf a key, so results are many times the rows."""
    return frequency.star_frequencies(star_of(db, workloads.supplier_root(), SUPPLIER_KW), SUPPLIER_KW)


@query(sql.frequencies([workloads.supplier_root()], SUPPLIER_KW))
def baseline_full_join_supplier_root(db):
    return baselines.straightforward(star_of(db, workloads.supplier_root(), SUPPLIER_KW), SUPPLIER_KW)


@query(sql.frequencies([workloads.order_root()], ORDER_KW))
def cell_kernel_order_root(db):
    """Repeated leaf keys counted inside the slots of a grid."""
    return cell_frequencies(star_of(db, workloads.order_root(), ORDER_KW), [3, 2, 2], {c: c % 5 for c in range(12)}, ORDER_KW)


@query("select round(n1 * n2 / greatest(v1, v2, 1))::bigint as n from (select count(o_custkey) as n1, count(distinct o_custkey) as v1 from orders) a, (select count(c_custkey) as n2, count(distinct c_custkey) as v2 from customer) b")
def merge_size_estimate(db):
    """Rows that the merge of orders and customers is estimated to have; merges go from the smallest on."""
    exact = trees.joined_size(db.table("orders"), db.table("customer"), "o_custkey", "c_custkey", True)
    return exact.select(F.round("n").cast("bigint").alias("n"))


def _conversations(db: Database) -> Database:
    g = orders_schema()
    g.add(Relation("user_turns", ("conv_id",), ("text",), table="conversations", where="role = 'user'"))
    g.add(Relation("assistant_turns", ("conv_id",), ("text",), table="conversations", where="role = 'assistant'"))
    return Database(db.spark, db.where, g)


def _turns_sql() -> str:
    turn = lambda role, a, b: f"(select conv_id, {sql.tokens('text')} as terms from conversations where role = '{role}' and list_contains({sql.tokens('text')}, '{a}') and not list_contains({sql.tokens('text')}, '{b}'))"
    return f"select term, count(*)::bigint as freq from (select unnest(list_concat(u.terms, a.terms)) as term from (select distinct conv_id from conversations) c join {turn('user', 'and', 'of')} u using (conv_id) join {turn('assistant', 'of', 'and')} a using (conv_id)) x where term not in ('and', 'of') group by term"


@query(_turns_sql())
def conversation_root_star(db):
    db = _conversations(db)
    root = db.table("conversations").select("conv_id").distinct().select(F.col("conv_id").alias("k1"), F.col("conv_id").alias("k2"), F.array().cast("array<string>").alias("terms"))
    leaf = lambda name, mask: volumes.Leaf(tuplesets.tuple_set(db.view(name), ["and", "of"], mask).withColumnRenamed("conv_id", "key"))
    return frequency.star_frequencies(volumes.Star(root, ["k1", "k2"], [leaf("user_turns", 1), leaf("assistant_turns", 2)]), ["and", "of"])


# ---- baselines -------------------------------------------------------------------------------------------------------


@query(STAR_FREQ)
def baseline_full_join_star(db):
    return baselines.straightforward(star_of(db), STAR_KW)


@query(STAR_FREQ)
def baseline_star_two_scan(db):
    return baselines.two_scans(star_of(db), STAR_KW)


@query(STAR_FREQ)
def baseline_cascade_star(db):
    return baselines.binary_cascade(star_of(db), STAR_KW)


@query(STAR_FREQ)
def baseline_precomputed_star(db):
    return baselines.precomputed(star_of(db), shared_folder(db.spark), STAR_KW)


@query("select 0::bigint as n_differences")
def exactness_star(db):
    return measures.mismatches(frequency.star_frequencies(star_of(db), STAR_KW), baselines.straightforward(star_of(db), STAR_KW)).agg(F.count("*").alias("n_differences"))


# ---- workloads -------------------------------------------------------------------------------------------------------

for _shape, _first in (("star", 1), ("chain", 4), ("mix", 7)):
    for _n in range(3):
        _make = {"star": workloads.star, "chain": workloads.chain, "mix": workloads.mix}[_shape]

        def _run(db, shape=_shape, n=_n):
            return workloads.batch_top(db, shape, n)

        query(sql.batch(workloads.batch(_shape, _n), _make), f"{_shape}_q{_first + _n}")(_run)


MAKE = {"star": workloads.star, "chain": workloads.chain, "mix": workloads.mix}


def _counts_sql() -> str:
    each = " union all ".join(f"select '{shape}' as shape, {n}::int as batch, {q}::int as qid, count(*)::bigint as n_results from ({sql.results(make(), kw)}) r" for shape, make in MAKE.items() for n in range(3) for q, kw in workloads.batch(shape, n))
    views = {r: sql.view(r) for r in ("lineitem", "part", "supplier", "orders", "customer")}
    for r, text in views.items():
        each = each.replace(text, f"{r}_view")
    return "with " + ", ".join(f"{r}_view as materialized {text}" for r, text in views.items()) + " " + each


@query(_counts_sql())
def workload_result_counts(db):
    """Results of all ninety queries, none of which may be empty of rows here: a query without results counts 0."""
    parts = [workloads.batch_result_counts(db, shape, workloads.batch(shape, n)).select(F.lit(shape).alias("shape"), F.lit(n).alias("batch"), "qid", "n_results") for shape in MAKE for n in range(3)]
    return functools.reduce(lambda a, b: a.unionByName(b), parts)


@query()
def generated_batches(db):
    """Ten queries of each shape, made from the texts of joined results, with their numbers of results."""
    parts = []
    for shape in MAKE:
        made = list(enumerate(workloads.generated_batch(db, shape)))
        words = db.spark.createDataFrame([(q, " ".join(kw)) for q, kw in made], "q int, keywords string")
        counts = workloads.batch_result_counts(db, shape, made)
        parts.append(counts.join(F.broadcast(words), F.col("qid") == F.col("q")).select(F.lit(shape).alias("shape"), "qid", "keywords", "n_results"))
    return functools.reduce(lambda a, b: a.unionByName(b), parts)


@query(" union all ".join(f"select '{r}' as relation, t as term, count(*)::bigint as n from (select unnest(list_distinct(terms)) as t from {sql.view(r)}) x group by t" for r in ("part", "supplier", "orders", "customer")))
def workload_bags(db):
    return workloads.workload_bags(db)


#: The worked example's shape on given tables: a root with three leaves whose keys repeat, and rows that dangle.
REPEATED = (("c_custkey", "orders", "o_custkey", ("o_orderstatus", "o_orderpriority")), ("c_custkey", "events", "user_id", ("event_type",)), ("c_nationkey", "supplier", "s_nationkey", ("s_name",)))


def _repeated_sql() -> str:
    bag = lambda columns: sql.tokens(f"concat_ws(' ', {', '.join(columns)})")
    joins = " ".join(f"join (select {key} as key, {bag(text)} as terms from {table}) l{i} on l{i}.key = {own}" for i, (own, table, key, text) in enumerate(REPEATED))
    return f"select term, count(*)::bigint as freq from (select unnest(flatten([{bag(['c_mktsegment'])}, l0.terms, l1.terms, l2.terms])) as term from customer {joins}) r group by term"


@query(_repeated_sql(), "running_example")
def running_example_query(db):
    bag = lambda columns: tokenize(text_of(columns)).alias("terms")
    own = [k for k, *_ in REPEATED]
    root = db.table("customer").select(*[F.col(k).alias(c) for k, c in zip(own, "ABC")], bag(["c_mktsegment"]))
    return frequency.star_frequencies(volumes.Star(root, ["A", "B", "C"], [volumes.Leaf(db.table(t).select(F.col(k).alias("key"), bag(text))) for _, t, k, text in REPEATED]))


@query("select l_suppkey, count(*)::bigint as n from lineitem group by 1 qualify row_number() over (order by n desc, l_suppkey) <= 20")
def fact_key_skew_profile(db):
    return db.table("lineitem").groupBy("l_suppkey").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "l_suppkey").limit(20)


