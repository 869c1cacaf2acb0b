import random

import pytest

from multiagg.operators.baselines import preaggregate, traditional
from multiagg.operators.multiway import arm_entries, enumerate_rooted_trees, explain_multiway, multiway_aggregate, per_source, prepared, trail_join, trails
from multiagg.plans.cost import best_tree, choose_root, choose_strategy, estimated, gather, join_cardinality, plan_of, predicted
from multiagg.plans.spec import Agg, GroupedJoinSpec, Rel, SpecError, normalize_spec
from multiagg.workloads import SHAPES, workload

SF = "/root/testdata/sf0.001"


def rel(spark, name, columns, rows, group="", measures=""):
    df = spark.createDataFrame(rows, ", ".join(f"{c} {'long' if c in measures.split() else 'string'}" for c in columns.split()))
    return Rel(name, df, {c: c for c in columns.split() if c not in measures.split()}, tuple(group.split()), {m: m for m in measures.split()})


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


def every_way(spec, exact=True):
    want = rows(traditional(spec))
    for how in ("shared_arms", "per_source", "source_batches") + (("packed",) if [a.kind for a in spec.aggs] == ["count"] else ()):
        got = multiway_aggregate(spec, how, batches=2)
        assert rows(got.select(*traditional(spec).columns)) == want, how
    for level in ("inputs", "every_join"):
        assert rows(preaggregate(spec, level).select(*traditional(spec).columns)) == want, level
    return want


@pytest.fixture
def branch(spark):
    return [
        rel(spark, "R1", "g1 j", [("s", "1"), ("s", "1"), ("t", "2"), ("q", "9")], "g1"), rel(spark, "R2", "j b", [("1", "x"), ("1", "y"), ("2", "x")]),
        rel(spark, "R3", "b g2", [("x", "u"), ("x", "u"), ("y", "u"), ("y", "v")], "g2"), rel(spark, "R4", "b g3 v", [("x", "w", 10), ("y", "w", 5)], "g3", "v"),
    ]


def test_self_join(spark):
    r = [("a", "1"), ("a", "1"), ("b", "1"), ("b", "2")]
    spec = GroupedJoinSpec((rel(spark, "A", "g1 p", r, "g1"), rel(spark, "B", "g2 p", r, "g2")))
    assert every_way(spec) == [("a", "a", 4), ("a", "b", 2), ("b", "a", 2), ("b", "b", 2)]


def test_branch_counts_prune_and_weights(spark, branch):
    spec = GroupedJoinSpec(tuple(branch))
    assert every_way(spec) == [("s", "u", "w", 6), ("s", "v", "w", 2), ("t", "u", "w", 2)]
    weights = trails(prepared(spec, "R1"))[1]["R2"]
    assert rows(weights) == [("s", "x", 2), ("s", "y", 2), ("t", "x", 1)]
    assert rows(multiway_aggregate(spec, "shared_arms", reduce_first=True)) == every_way(spec)
    assert rows(per_source(prepared(spec), cache_trails=False)) == rows(per_source(prepared(spec)))


def test_aggregates_in_a_leaf(spark, branch):
    aggs = (Agg.sum("R4", "v"), Agg.min("R4", "v"), Agg.max("R4", "v"), Agg.avg("R4", "v"))
    got = {r[:3]: r[3:] for r in every_way(GroupedJoinSpec(tuple(branch), aggs))}
    assert got["s", "u", "w"][:3] == (50, 5, 10) and abs(got["s", "u", "w"][3] - 50 / 6) < 1e-9
    assert got["s", "v", "w"] == (10, 5, 5, 5.0) and got["t", "u", "w"] == (20, 10, 10, 10.0)


def test_least_and_greatest_without_counts(spark, branch):
    assert every_way(GroupedJoinSpec(tuple(branch), (Agg.min("R4", "v"), Agg.max("R4", "v")))) == [("s", "u", "w", 5, 10), ("s", "v", "w", 5, 5), ("t", "u", "w", 10, 10)]


def test_distinct_counts_having_and_products(spark, branch):
    every_way(GroupedJoinSpec(tuple(branch), (Agg.count(), Agg.count_distinct("R4", "v"))))
    having = GroupedJoinSpec(tuple(branch), having="cnt > 2")
    assert every_way(having) == [("s", "u", "w", 6)]
    two = [*branch[:3], branch[3]]
    two[1] = rel(spark, "R2", "j b x", [("1", "x", 2), ("1", "y", 3), ("2", "x", 7)], "", "x")
    every_way(GroupedJoinSpec(tuple(two), (Agg.sum_product(("R2", "x"), ("R4", "v")),)))


def test_group_in_an_inner_relation(spark):
    spec = GroupedJoinSpec((rel(spark, "R1", "g1 p0", [("a", "1"), ("a", "2")], "g1"), rel(spark, "R2", "p0 g2 p1", [("1", "k", "5"), ("1", "k", "5"), ("2", "m", "5")], "g2"), rel(spark, "R3", "p1 g3", [("5", "z"), ("5", "z"), ("6", "z")], "g3")))
    assert every_way(spec) == [("a", "k", "z", 4), ("a", "m", "z", 2)]


def test_join_only_leaf_multiplies(spark):
    spec = GroupedJoinSpec((rel(spark, "R1", "g1 j", [("a", "1")], "g1"), rel(spark, "R2", "j g2", [("1", "b")], "g2"), rel(spark, "R5", "j", [("1",), ("1",), ("1",)])))
    assert every_way(spec) == [("a", "b", 3)]


def test_null_keys_go_and_null_groups_stay(spark):
    spec = GroupedJoinSpec((rel(spark, "A", "g1 p", [(None, "1"), (None, None), ("a", "1")], "g1"), rel(spark, "B", "p q g2", [("1", "2", None), (None, "2", "x"), ("1", None, "y")], "g2"), rel(spark, "C", "q g3", [("2", "z"), ("2", None)], "g3")))
    assert every_way(spec) == sorted([(None, None, "z", 1), (None, None, None, 1), ("a", None, "z", 1), ("a", None, None, 1)], key=repr)


def test_empty_relation(spark, branch):
    spec = GroupedJoinSpec((*branch[:3], rel(spark, "R4", "b g3", [], "g3")))
    assert every_way(spec) == []


def test_two_groups_in_one_relation_and_group_that_joins(spark):
    spec = GroupedJoinSpec((rel(spark, "A", "g1 g2 p", [("a", "b", "1"), ("a", "c", "1")], "g1 g2"), rel(spark, "B", "p h", [("1", "x"), ("2", "y")], "p h")))
    want = [("a", "b", "1", "x", 1), ("a", "c", "1", "x", 1)]
    assert every_way(spec) == want


def test_random_trees_with_bushy_branches(spark):
    r = random.Random(5)
    for _ in range(1):
        val = lambda k=2: r.choice([str(i) for i in range(k)])
        many = lambda n, k: [tuple(val() for _ in range(k)) for _ in range(n)]
        spec = GroupedJoinSpec((
            rel(spark, "S", "g0 x", many(6, 2), "g0"), rel(spark, "H", "x y z", many(8, 3)), rel(spark, "P", "y p q", many(8, 3)), rel(spark, "Q", "z s t", many(8, 3), ""),
            rel(spark, "L1", "p g1", many(6, 2), "g1"), rel(spark, "L2", "q g2", many(6, 2), "g2"), rel(spark, "L3", "s g3", many(6, 2), "g3"), rel(spark, "L4", "t g4", many(6, 2), "g4"),
        ))
        want = every_way(spec)
        assert want
        total = join_cardinality(spec).first()[0]
        assert total == sum(w[-1] for w in want)
        assert rows(multiway_aggregate(spec, "shared_arms", root="L3").select(*traditional(spec).columns)) == want


def test_doubled_rows_double_counts(spark, branch):
    spec, twice = GroupedJoinSpec(tuple(branch)), list(branch)
    twice[1] = Rel("R2", branch[1].df.union(branch[1].df), branch[1].attrs)
    assert [r[-1] for r in rows(multiway_aggregate(GroupedJoinSpec(tuple(twice)), "shared_arms"))] == [2 * r[-1] for r in rows(multiway_aggregate(spec, "shared_arms"))]


def test_literal_trail_join_on_one_spine(spark, branch):
    graph = prepared(GroupedJoinSpec(tuple(branch)), "R1")
    _, seen = trails(graph)
    names = {"R3": ["g2"], "R4": ["g3"]}
    both = trail_join(seen["R3"], seen["R4"], ["g1"], ["__L0_b"], ["__L0_b"])
    weighted = trail_join(seen["R2"], both, ["g1"], ["__L0_b"], ["__L0_b"])
    got = rows(weighted.groupBy("g1", *names["R3"], *names["R4"]).sum("__m"))
    assert got == [("s", "u", "w", 6), ("s", "v", "w", 2), ("t", "u", "w", 2)]
    assert arm_entries(graph, "R3").where("g1 = 's' and g2 = 'u'").first()["entries"][0]["count"] == 2


def test_rooted_trees_sum_to_the_join(spark, branch):
    spec = GroupedJoinSpec(tuple(branch))
    assert enumerate_rooted_trees(spec).agg({"tuples": "sum"}).first()[0] == join_cardinality(spec).first()[0] == 10


def test_packed_refuses_large_graphs(spark, branch):
    from multiagg.operators.multiway import packed

    with pytest.raises(SpecError, match="edges"):
        packed(prepared(GroupedJoinSpec(tuple(branch))), limit=3)


def test_packed_hands_large_graphs_over(spark, branch, monkeypatch):
    from multiagg.operators import multiway

    monkeypatch.setattr(multiway, "PACKED_EDGES", 3)
    spec = GroupedJoinSpec(tuple(branch))
    assert rows(multiway_aggregate(spec, "packed")) == [("s", "u", "w", 6), ("s", "v", "w", 2), ("t", "u", "w", 2)]
    with pytest.raises(SpecError, match="counts only"):
        multiway_aggregate(GroupedJoinSpec(tuple(branch), (Agg.sum("R4", "v"),)), "packed")


def test_choice_and_explanation(spark):
    assert choose_strategy(workload("pairs_suppliers", spark, SF)).strategy == "shared_arms"
    text = explain_multiway(workload("syn_b2", spark, SF))
    assert "branch" in text and "source" in text


@pytest.mark.parametrize("name", ["syn_s3", "syn_c3", "syn_b3", "tpch_zip", "triple_events", "bushy"])
def test_published_sizes(spark, name):
    known = {"syn_s3": (65988, 40698), "syn_c3": (258854, 10828), "syn_b3": (120278, 83172), "tpch_zip": (57430, 1500), "triple_events": (4679926, 125), "bushy": (1971056, 3960)}
    out = multiway_aggregate(workload(name, spark, SF), "shared_arms")
    assert (out.agg({"cnt": "sum"}).first()[0], out.count()) == known[name]
    assert join_cardinality(workload(name, spark, SF)).first()[0] == known[name][0]


def test_scans_read_relevant_columns_only(spark):
    plan = multiway_aggregate(workload("pairs_suppliers", spark, SF), "shared_arms")._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_orderkey:bigint,l_suppkey:bigint>" in plan and len(SHAPES) > 25


def test_root_of_least_work(spark):
    spec = workload("syn_b2", spark, SF)
    stats = gather(normalize_spec(spec))
    assert estimated(best_tree(spec), stats).rows < estimated(plan_of(spec, "r1"), stats).rows
    assert choose_root(spec) in ("r3", "r4") and best_tree(workload("pairs_suppliers", spark, SF)) is None
    want = rows(multiway_aggregate(spec, "shared_arms", root="r1"))
    assert rows(multiway_aggregate(spec, "shared_arms")) == rows(multiway_aggregate(spec, "shared_arms", root="r2")) == want


def test_smaller_arms_come_first(spark):
    hub = rel(spark, "H", "x y", [(str(i % 7), str(i % 5)) for i in range(35)])
    big, small = rel(spark, "B", "x g1", [(str(i % 7), str(i)) for i in range(700)], "g1"), rel(spark, "S", "y g2", [(str(i % 5), "one") for i in range(5)], "g2")
    spec = normalize_spec(GroupedJoinSpec((hub, big, small)))
    tree = plan_of(spec, "H")
    estimated(tree, gather(spec))
    assert tree.order == ["S", "B"]


def test_choice_by_work_and_state(spark):
    spec = workload("syn_b2", spark, SF)
    assert choose_strategy(spec).strategy == "shared_arms"
    choice = choose_strategy(spec, state_rows=1000)
    assert choice.strategy == "source_batches" and choice.batches >= 2 and choice.tree.group
    assert choose_strategy(spec, gain=1e9).strategy == "preagg_every"
    assert choose_strategy(workload("tpch_zip", spark, SF), blow_up=100).strategy == "traditional"
    p = predicted("branch", 500_000, 50, 50_000)
    assert p["operator"] < p["preaggregate"]


def test_slices_run_one_after_the_other(spark, branch, monkeypatch):
    from multiagg.operators import multiway

    made = []
    whole = multiway.arm
    monkeypatch.setattr(multiway, "arm", lambda g, n, *a: made.append(n.name) or whole(g, n, *a))
    got = multiway.source_batches(prepared(GroupedJoinSpec(tuple(branch)), "R1"), 3)
    assert made.count("R2") == 1 and made.count("R1") == 3 and got.count() == 3


def test_read_through_jdbc(spark):
    from multiagg.sources.tables import edge_query, load_jdbc

    url, driver = "jdbc:derby:memory:shop", "org.apache.derby.iapi.jdbc.AutoloadedDriver"
    sold = spark.createDataFrame([(i % 3, i % 5) for i in range(40)], "ORD int, PART int")
    sold.write.format("jdbc").options(url=url + ";create=true", driver=driver, dbtable="sold").save()
    got = load_jdbc(spark, url, edge_query("sold", ["ORD", "PART"]), driver=driver)
    assert rows(got) == rows(sold.groupBy("ORD", "PART").count())
    parts = load_jdbc(spark, url, "SELECT ORD, PART FROM sold", "PART", (0, 5), 3, driver=driver)
    assert rows(parts) == rows(sold) and parts.rdd.getNumPartitions() == 3


def test_new_measures(spark):
    from multiagg.operators.measure import growth

    got = growth({"p1": workload("syn_p1", spark, SF)}).collect()
    assert [r["strategy"] for r in got] == ["operator", "preagg_every"] and got[0]["rows"] == got[1]["rows"] > 0
    assert got[0]["load_seconds"] > 0 and got[0]["peak_mb"] > 0
    assert all(r["most_rows_between"] > 0 and r["operator_peak_mb"] > 0 for r in got)


def test_arms_go_on_with_the_values_they_start_from(spark):
    """A hub of two arms: the inner one is walked from each source and its own value, not from each pair of both arms' values."""
    from multiagg.operators.measure import plan_nodes

    hub = spark.range(8000).selectExpr("id % 2 as x", "id % 80 as y", "id div 80 as z")
    spec = GroupedJoinSpec((
        Rel("S", spark.range(4).selectExpr("id as g0", "id % 2 as x"), {"g0": "g0", "x": "x"}, ("g0",)), Rel("H", hub, {"x": "x", "y": "y", "z": "z"}),
        Rel("M", spark.range(400).selectExpr("id % 80 as y", "id % 5 as w"), {"y": "y", "w": "w"}), Rel("L1", spark.range(20).selectExpr("id % 5 as w", "id % 4 as g1"), {"w": "w", "g1": "g1"}, ("g1",)),
        Rel("L2", spark.range(100).selectExpr("id as z", "id % 3 as g2"), {"z": "z", "g2": "g2"}, ("g2",)),
    ))
    want = rows(traditional(spec))
    made = per_source(prepared(spec))
    assert rows(made.select(*traditional(spec).columns[:-1], "__m")) == want
    whole = trails(prepared(spec))[0]
    shuffled = lambda df: (df.collect(), sum(int(p.metrics().get("shuffleRecordsWritten").get().value()) for name, p in plan_nodes(df) if name == "ShuffleExchangeExec"))[1]
    assert shuffled(made) < shuffled(whole) / 2


def test_large_relations_are_not_broadcast(spark, monkeypatch):
    from multiagg.operators import baselines

    monkeypatch.setattr(baselines, "BROADCAST_ROWS", 3)
    few, many = ([(str(i), str(i % 2)) for i in range(n)] for n in (3, 4))
    spec = GroupedJoinSpec((rel(spark, "A", "g1 p", many, "g1"), rel(spark, "B", "g2 p", many, "g2"), rel(spark, "C", "g3 p", few, "g3")))
    made = traditional(spec, "broadcast", "hash")
    assert rows(made) == rows(traditional(spec, "merge"))
    hints = made._jdf.queryExecution().analyzed().toString()
    assert hints.count("ResolvedHint (strategy=broadcast)") == 1
