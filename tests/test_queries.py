"""Every registered query of the search engine against its DuckDB twin, on the smallest tables."""

import pytest
from conftest import SF

from termgrid.catalog import Database
from termgrid.operators import measures
from termgrid.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(name, same):
    same(QUERIES[name], ORACLES[name])


def _rows(name, spark):
    return [r.asDict() for r in QUERIES[name](spark, SF).collect()]


def _n(spark, table, what="*"):
    return spark.read.parquet(f"{SF}/{table}.parquet").selectExpr(f"count({what}) as n").first().n


def test_every_query_without_sql_is_tested():
    assert set(QUERIES) - set(ORACLES) == {"cn_list", "sample_simple_counts", "sample_stratified", "approx_distinct_keys", "approx_top_terms", "generated_batches", "skew_experiment", "placement_simple_sample"}


def test_networks_of_the_star_query(spark):
    got = _rows("cn_list", spark)
    # parts, suppliers and orders meet in line items only, so the star is the one network of four nodes, and the smallest
    assert got[0]["shape"] == "star" and got[0]["size"] == 4 and all(r["size"] <= 5 for r in got)
    assert [r["cn_id"] for r in got] == list(range(len(got))) and len({r["network"] for r in got}) == len(got)


def test_samples_are_near_their_fractions(spark):
    orders = spark.read.parquet(f"{SF}/orders.parquet")
    n = _rows("sample_simple_counts", spark)[0]["n"]
    assert abs(n - 0.1 * orders.count()) < 5 * (0.09 * orders.count()) ** 0.5
    per = {r["o_orderstatus"]: r["count"] for r in orders.groupBy("o_orderstatus").count().collect()}
    for r in _rows("sample_stratified", spark):
        p = {"O": 0.1, "F": 0.2, "P": 0.3}[r["o_orderstatus"]]
        assert abs(r["n"] - p * per[r["o_orderstatus"]]) < 5 * (p * (1 - p) * per[r["o_orderstatus"]]) ** 0.5


def test_approximate_answers_are_near_the_exact_ones(spark):
    got = _rows("approx_distinct_keys", spark)[0]
    assert abs(got["suppliers"] / _n(spark, "lineitem", "distinct l_suppkey") - 1) < 0.1
    assert abs(got["parts"] / _n(spark, "lineitem", "distinct l_partkey") - 1) < 0.1
    exact = {r["term"]: r["n"] for r in _rows("wordcount_documents", spark)}
    top = _rows("approx_top_terms", spark)
    least = sorted(exact.values())[-10]
    assert len(top) == 10 and all(exact[r["term"]] >= 0.95 * least and abs(r["count"] / exact[r["term"]] - 1) < 0.05 for r in top)


def test_generated_queries_have_results(spark):
    got = _rows("generated_batches", spark)
    assert {(r["shape"], r["qid"]) for r in got} == {(s, q) for s in ("star", "chain", "mix") for q in range(10)}
    assert all(r["n_results"] > 0 for r in got)


def test_uneven_placement_balances_the_slots(spark):
    got = {(r["batch"], r["cells"]): r for r in _rows("skew_experiment", spark)}
    assert set(got) == {(b, n) for b in ("Q1", "Q4", "Q5") for n in (8, 27)}
    for b in ("Q1", "Q4", "Q5"):
        # the more cells, the more copies, and the nearer the hottest slot is to the mean
        assert got[b, 27]["records"] > got[b, 8]["records"] and got[b, 27]["ratio"] < got[b, 8]["ratio"] and got[b, 27]["facts"] == got[b, 8]["facts"]
    sampled, even = _rows("placement_simple_sample", spark), _rows("placement_one_each", spark)
    assert sum(r["facts"] for r in sampled) == sum(r["facts"] for r in even)
    peak = lambda rows: max(r["facts"] for r in rows) / sum(r["facts"] for r in rows)
    assert peak(sampled) < peak(even)


def test_entry_has_rows(spark):
    import __spark_entry__

    rows = __spark_entry__.entry(spark).collect()
    assert rows and rows[0].asDict().keys() == {"term", "freq", "rank"}
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())


def test_nothing_else_imports_the_corpus_operators():
    from pathlib import Path

    import termgrid

    root = Path(termgrid.__file__).parent
    for p in root.rglob("*.py"):
        if "llm" not in p.relative_to(root).parts:
            assert "llm" not in p.read_text(), p


def test_whole_queries_cover_all_documents_and_orders(spark):
    read = lambda t: spark.read.parquet(f"{SF}/{t}.parquet")
    assert QUERIES["map_term_counts"](spark, SF).select("doc_id").distinct().count() == read("documents").where("text rlike '[a-zA-Z]'").count()
    assert QUERIES["distribution_windows"](spark, SF).count() == read("orders").count()
    assert QUERIES["intersect_all_terms"](spark, SF).count() > 0 and QUERIES["except_all_terms"](spark, SF).count() > 0


def test_whole_triangle_has_every_line_item(spark):
    lines = {tuple(r) for r in spark.read.parquet(f"{SF}/lineitem.parquet").select("l_partkey", "l_suppkey", "l_orderkey").collect()}
    r, s, t = ({(x[i], x[j]) for x in lines} for i, j in ((0, 1), (1, 2), (0, 2)))
    suppliers = {}
    for b, c in s:
        suppliers.setdefault(c, set()).add(b)
    want = sorted((a, b, c) for a, c in t for b in suppliers[c] if (a, b) in r)
    got = sorted(tuple(x) for x in QUERIES["triangle_grid_join"](spark, SF).collect())
    assert got == want and lines <= set(got)


@pytest.mark.parametrize("name", ["leaf_replication_factor", "roundtrip_json_csv", "running_example", "schema_graph_edges"])
def test_small_queries_read_given_tables(name, spark):
    read = []
    table = Database.table

    def noted(self, name):
        read.append(name)
        return table(self, name)

    with pytest.MonkeyPatch.context() as m:
        m.setattr(Database, "table", noted)
        assert QUERIES[name](spark, SF).count() > 0
    assert read


def test_measured_copies_are_the_planned_ones(spark):
    got = {r["leaf"]: (r["factor"], r["n_rows"]) for r in _rows("leaf_replication_factor", spark)}
    assert got == {i: (f, _n(spark, t)) for i, (f, t) in enumerate(zip(measures.replication_factors([2, 2, 2]), ("part", "supplier", "orders")), 1)}
