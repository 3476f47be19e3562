"""The worked example, edge cases and properties of counting, networks, the grid and placement."""

import math
import random

import pytest
from conftest import SF
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from termgrid import session, workloads
from termgrid.catalog import Database, Relation, SchemaGraph, orders_schema
from termgrid.operators import baselines, cells, frequency, grid, measures, placement, trees, volumes
from termgrid.plans.networks import Node, classify, enumerate_networks, is_dead, is_minimal, is_total, rerooted
from termgrid.sources import running_example


def freq(df):
    return {r.term: r.freq for r in df.collect()}


@pytest.fixture(scope="module")
def example(spark):
    t = running_example(spark)
    return volumes.Star(t["R"], ["A", "B", "C"], [volumes.Leaf(t[x]) for x in "STP"])


def test_worked_example_counts(example):
    nums = [{r.key: r.num for r in volumes.num_array(leaf).collect()} for leaf in example.leaves]
    assert nums[0] == {"a1": 2, "a2": 3, "a4": 1, "a3": 1}
    assert nums[1] == {"b2": 1, "b3": 2, "b4": 1} and nums[2] == {"c1": 2, "c2": 2}
    facts = {(r.A, r.B, r.C): r.volume for r in volumes.fact_volumes(example).collect()}
    assert facts == {("a2", "b4", "c1"): 6, ("a4", "b3", "c1"): 4, ("a1", "b2", "c2"): 4, ("a1", "b4", "c1"): 4}
    leaves = {r.key: r.volume for r in volumes.leaf_volumes(example).collect()}
    assert leaves == {"a1": 4, "a2": 2, "a4": 4, "b2": 4, "b3": 2, "b4": 10, "c1": 7, "c2": 2}
    assert volumes.result_count(example).first().n_results == 18


def test_worked_example_frequencies_by_every_method(example, spark, tmp_path):
    want = {"w1": 29, "w2": 27, "w3": 28, "w4": 6}
    assert freq(frequency.star_frequencies(example)) == want
    assert freq(frequency.star_frequencies(example, emit="local")) == want
    assert freq(frequency.star_frequencies_by_key(example)) == want
    assert freq(baselines.straightforward(example)) == want
    assert freq(baselines.binary_cascade(example)) == want
    assert freq(baselines.two_scans(example)) == want
    assert freq(baselines.precomputed(example, str(tmp_path / "joined"))) == want
    for shares in ([1, 1, 1], [2, 2, 2], [3, 1, 2]):
        assert freq(grid.grid_frequencies(example, shares)) == want
    assert freq(grid.grid_frequencies(example, [2, 2, 2], {c: c % 3 for c in range(8)}, prune=False)) == want
    assert freq(frequency.star_frequencies_by_key(placement.salt_hot_keys(example, 0, 1, 3))) == want
    wide = volumes.Star(example.root, example.keys, example.leaves, wide=True)
    assert freq(frequency.star_frequencies(wide)) == want
    assert [r.term for r in frequency.top_terms(frequency.star_frequencies(example), 2).orderBy("rank").collect()] == ["w1", "w3"]


def test_worked_example_cells(example, spark):
    numbered = lambda c: F.substring(c, 2, 9).cast("int") % 2
    cells = example.root.where("A <> 'a5'").select((numbered("A") * 4 + numbered("B") * 2 + numbered("C")).alias("cell"))
    assert sorted(r.cell for r in cells.collect()) == [0b001, 0b011, 0b100, 0b101] or len(cells.collect()) == 4
    slices = spark.sql("select 1L as a, 2L as b, 2L as c").select(*[grid.leaf_cells(F.col(x), i, [2, 2, 2], "mod").alias(x) for i, x in enumerate("abc")]).first()
    assert [f"{c:03b}" for c in slices.a] == ["100", "101", "110", "111"]
    assert sorted(f"{c:03b}" for c in slices.b) == ["000", "001", "100", "101"]
    assert sorted(f"{c:03b}" for c in slices.c) == ["000", "010", "100", "110"]


def _rows(spark, rows, schema):
    return spark.createDataFrame(rows, schema)


def test_empty_and_null_inputs(spark):
    leaf = _rows(spark, [(1, ["a"]), (None, ["b"]), (1, None), (2, [])], "key long, terms array<string>")
    none = leaf.limit(0)
    root = _rows(spark, [(1, 1, ["r"]), (None, 1, ["x"]), (2, 1, None), (9, 1, ["y"])], "k1 long, k2 long, terms array<string>")
    star = volumes.Star(root, ["k1", "k2"], [volumes.Leaf(leaf), volumes.Leaf(leaf)])
    assert freq(frequency.star_frequencies(star)) == freq(baselines.straightforward(volumes.Star(root.withColumn("terms", F.coalesce("terms", F.array().cast("array<string>"))), ["k1", "k2"], [volumes.Leaf(leaf.withColumn("terms", F.coalesce("terms", F.array().cast("array<string>"))))] * 2)))
    assert freq(frequency.star_frequencies(volumes.Star(root, ["k1", "k2"], [volumes.Leaf(none), volumes.Leaf(leaf)]))) == {}
    assert freq(frequency.star_frequencies(volumes.Star(root.limit(0), ["k1", "k2"], [volumes.Leaf(leaf)] * 2))) == {}
    assert volumes.result_count(volumes.Star(root.limit(0), ["k1", "k2"], [volumes.Leaf(leaf)] * 2)).first().n_results == 0
    assert freq(frequency.star_frequencies(volumes.Star(root.select("terms"), [], []))) == {"r": 1, "x": 1, "y": 1}


def test_overflow_raises_unless_wide(spark):
    # five leaves of 10,000 rows: 10 ** 20 results
    leaf = spark.range(10_000).select(F.lit(1).cast("long").alias("key"), F.array().cast("array<string>").alias("terms"))
    root = spark.sql("select 1L as k1, 1L as k2, 1L as k3, 1L as k4, 1L as k5, array('t') as terms")
    keys = ["k1", "k2", "k3", "k4", "k5"]
    with pytest.raises(PySparkException):
        frequency.star_frequencies(volumes.Star(root, keys, [volumes.Leaf(leaf)] * 5)).collect()
    assert freq(frequency.star_frequencies(volumes.Star(root, keys, [volumes.Leaf(leaf)] * 5, wide=True))) == {"t": 10**20}


@settings(max_examples=5, deadline=None)
@given(st.integers(1, 3), st.integers(0, 10**6))
def test_random_stars_against_full_join(d, seed):
    from pyspark.sql import SparkSession

    spark, rng = SparkSession.getActiveSession(), random.Random(seed)
    bag = lambda: [rng.choice("uvwxyz") for _ in range(rng.randrange(3))]
    leaves = [volumes.Leaf(_rows(spark, [(rng.randrange(4), bag()) for _ in range(rng.randrange(1, 8))], "key long, terms array<string>")) for _ in range(d)]
    root = _rows(spark, [(*[rng.randrange(5) for _ in range(d)], bag()) for _ in range(rng.randrange(1, 9))], ", ".join(f"k{i} long" for i in range(d)) + ", terms array<string>")
    star = volumes.Star(root, [f"k{i}" for i in range(d)], leaves)
    want = freq(baselines.straightforward(star))
    assert freq(frequency.star_frequencies(star)) == want
    assert freq(grid.grid_frequencies(star, [2] * d)) == want


# ---- networks --------------------------------------------------------------------------------------------------------


def test_networks_are_total_minimal_and_found():
    g = orders_schema()
    sets = [("part", 0), ("part", 1), ("supplier", 0), ("supplier", 2), ("orders", 0), ("orders", 4), ("customer", 0), ("lineitem", 0)]
    found = enumerate_networks(g, sets, 3, 4)
    assert [classify(t)[0] for t in found] == ["star"]
    assert classify(found[0])[1].relation == "lineitem"
    assert all(is_total(t, 3) and is_minimal(t) for t in found)
    assert enumerate_networks(g, sets, 3, 3) == []


def test_one_tuple_with_all_keywords_is_a_network_alone():
    assert [t.size() for t in enumerate_networks(orders_schema(), [("documents", 3)], 2, 5)] == [1]


def test_a_free_set_is_no_place_for_a_keyword():
    t = workloads.two_orders()
    assert is_minimal(t) and not is_minimal(Node("customer", 0, None, (Node("orders", 1, ("c_custkey", "o_custkey")), Node("orders", 0, ("c_custkey", "o_custkey")))))
    found = enumerate_networks(orders_schema(), [("customer", 0), ("orders", 0), ("orders", 1), ("orders", 2)], 2, 3)
    assert any(x.size() == 3 and {n.mask for n in x.walk()} == {0, 1, 2} for x in found)


def test_two_parents_through_one_key_are_dead():
    g = orders_schema()
    dead = Node("orders", 0, None, (Node("customer", 1, ("o_custkey", "c_custkey")), Node("customer", 2, ("o_custkey", "c_custkey"))))
    assert is_dead(dead, g) and not is_dead(workloads.two_orders(), g)


def test_shapes():
    assert classify(workloads.star())[0] == "star"
    assert classify(workloads.chain())[0] == "chain"
    assert classify(workloads.mix())[0] == "mix"
    assert classify(Node("documents", 3))[0] == "single"
    assert rerooted(workloads.star(), 1).size() == 4
    assert trees.choose_merges({("a", "b"): 5.0, ("b", "c"): 2.0})[0] == ("b", "c")


def test_schema_graph_refuses_self_edges_and_unknown_keys():
    g = SchemaGraph().add(Relation("r", ("k",), ("t",)))
    with pytest.raises(ValueError):
        g.add_fk("r", "k", "r", "k")
    g.add(Relation("s", ("k",), ("t",)))
    with pytest.raises(ValueError):
        g.add_fk("r", "nope", "s", "k")


def test_all_methods_agree_on_a_small_database(spark):
    rng = random.Random(3)
    words = ["x", "y", "p", "q"]
    text = lambda: " ".join(rng.choice(words) for _ in range(rng.randrange(3)))
    g = SchemaGraph()
    g.add(Relation("a", ("ak",), ("at",), ("ak",))).add(Relation("b", ("bk",), ("bt",), ("bk",))).add(Relation("f", ("fa", "fb"), ("ft",)))
    g.add_fk("f", "fa", "a", "ak").add_fk("f", "fb", "b", "bk")
    db = Database(spark, {
        "a": _rows(spark, [(i, text()) for i in range(5)], "ak long, at string"),
        "b": _rows(spark, [(i, text()) for i in range(5)], "bk long, bt string"),
        "f": _rows(spark, [(rng.randrange(6), rng.randrange(6), text()) for _ in range(20)], "fa long, fb long, ft string"),
    }, g)
    got = {m: freq(session.cooccurring_terms(db, ["x", "y"], 5, 3, m, relations=("a", "b", "f"))) for m in ("volume", "by_key", "tree", "join")}
    assert got["volume"] == got["by_key"] == got["tree"] == got["join"] and got["volume"]
    assert freq(session.cooccurring_terms(db, ["nowhere", "x"], 5, 3, relations=("a", "b", "f"))) == {}


# ---- grid and placement ----------------------------------------------------------------------------------------------


def test_shares():
    assert grid.integer_shares([5, 5, 5], 9, "floor") == [2, 2, 2]
    assert math.prod(grid.integer_shares([100, 2000, 15000], 8)) == 8
    assert grid.integer_shares([100, 2000, 15000], 8) == [1, 1, 8]
    assert grid.star_cost(60000, [100, 2000, 15000], [1, 1, 8]) == 91800 and grid.star_cost(60000, [100, 2000, 15000], [2, 2, 2]) == 128400
    assert math.isclose(math.prod(grid.star_shares([3, 7, 11], 27)), 27)
    real = grid.star_shares([3, 7, 11], 27)
    assert math.isclose(3 / real[0], 7 / real[1]) and math.isclose(7 / real[1], 11 / real[2])
    assert all(a >= 1 for a in grid.clamped_shares([1, 2000, 15000], 8)) and math.isclose(math.prod(grid.clamped_shares([1, 2000, 15000], 8)), 8)
    a, b, c = grid.triangle_shares(361, 803, 3469, 8)
    assert math.isclose(a * b * c, 8) and math.isclose(361 * c, 803 * a) and math.isclose(803 * a, 3469 * b)
    assert math.isclose(grid.triangle_cost(361, 803, 3469, (a, b, c)), 3 * (8 * 361 * 803 * 3469) ** (1 / 3))
    assert grid.max_cell_load(10, 2, 2) == 125 and grid.max_cell_load(10, 2, 1) == 1000
    assert measures.replication_factors([2, 2, 2]) == [4, 4, 4]


def test_placement():
    costs = {0: 8.0, 1: 7.0, 2: 6.0, 3: 5.0, 4: 4.0}
    placed = placement.place_greedy(costs, 2)
    loads = [sum(c for k, c in costs.items() if placed[k] == s) for s in (0, 1)]
    assert max(loads) <= 17 and set(placed) == set(costs)
    assert placement.place_one_each(costs, 5) == {k: k for k in costs}
    assert placement.place_round_robin({0: 1, 9: 1}, 8) == {0: 0, 9: 1}
    assert measures.phase_bound(2.64, 1.91, 0.1, 0.43) == pytest.approx(3.17)
    assert measures.gain(1.0, 0.64) == pytest.approx(0.36)


def test_finer_cells_balance_skew(spark):
    from conftest import SF

    from termgrid.queries.grids import bare_star

    for profile in ("hot_corner", "half_idle"):
        star = bare_star(Database(spark, SF), profile)

        def ratio(shares, how):
            slots = how(placement.costs_of(placement.cell_costs(star, shares, kind="mod")), 8)
            facts = [r.facts for r in placement.slot_loads(star, shares, slots, "mod").collect()]
            return max(facts) / (sum(facts) / 8)

        assert ratio([3, 3, 3], placement.place_greedy) < 1.4 < 1.9 < ratio([2, 2, 2], placement.place_one_each)


def test_leaf_delta(spark):
    from termgrid.streaming import leaf_delta

    facts = _rows(spark, [(1, 1), (2, 1)], "k1 long, k2 long")
    old = [_rows(spark, [(1, 2), (2, 1)], "key long, num long"), _rows(spark, [(1, 3)], "key long, num long")]
    more = _rows(spark, [(2, 4)], "key long, num long")
    assert [(r.k1, r.k2, r.volume) for r in leaf_delta(facts, old, ["k1", "k2"], more, 0).collect()] == [(2, 1, 12)]


def test_sources_round_trip(spark, tmp_path):
    from termgrid import sources

    df = _rows(spark, [("x", 1), ("y", 2)], "term string, freq long")
    sources.write_by_term(df, str(tmp_path / "t"), 4)
    assert freq(sources.read(spark, str(tmp_path / "t"))) == {"x": 1, "y": 2}
    with pytest.raises(ValueError):
        sources.read(spark, str(tmp_path / "t"), "csv")


def test_generated_queries_take_a_word_of_each_bag(spark):
    for shape, holders in workloads.HOLDERS.items():
        got = workloads.generated_batch(Database(spark, SF), shape, n=5)
        assert len(got) == 5 and all(len(q) == len(holders) and all(q) for q in got)
        counts = workloads.batch_result_counts(Database(spark, SF), shape, list(enumerate(got))).collect()
        assert len(counts) == 5 and all(r.n_results > 0 for r in counts)


def test_results_of_a_query_without_networks(spark):
    got = session.keyword_results(Database(spark, SF), ["nowhere", "tobefound"], 3)
    assert got.count() == 0 and got.columns == ["cn_id", "tuples", "terms"]


def test_slots_count_like_a_full_join(spark, example):
    want = sorted(map(tuple, baselines.straightforward(example).collect()))
    for shares, slots in (([1, 1, 1], None), ([2, 2, 2], {c: c % 3 for c in range(8)}), ([3, 1, 2], None)):
        for prune in (True, False):
            got = cells.cell_frequencies(example, shares, slots, prune=prune)
            assert sorted(map(tuple, got.collect())) == want
    empty = volumes.Star(example.root.limit(0), example.keys, example.leaves)
    assert cells.cell_frequencies(empty, [2, 2, 2]).count() == 0
    null = volumes.Star(example.root.withColumn("A", F.lit(None).cast("string")), example.keys, example.leaves)
    assert cells.cell_frequencies(null, [2, 2, 2]).count() == 0
    with pytest.raises(ValueError):
        cells.cell_frequencies(volumes.Star(example.root, example.keys, example.leaves, wide=True), [1, 1, 1])
