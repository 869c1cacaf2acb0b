"""Registered queries on tables of another size than their SQL's domains were made for."""

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
DRAWN = (
    "combine_cost__syn_b3", "graph_size__syn_b3", "group_size__syn_s3", "join_rows__syn_s3", "syn_b1", "syn_b1__preagg_inputs", "syn_b1__shared_arms", "syn_c1", "syn_c1__per_source",
    "syn_c1__preagg_every", "syn_c1__preagg_inputs", "syn_c1__shared_arms", "syn_c2", "syn_c2__per_source", "syn_p3",
)


def by_sql(text, tables=("lineitem",), folder=SF):
    with duckdb.connect() as c:
        for t in tables:
            c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
        return sorted(c.execute(text).fetchall(), key=repr)


@pytest.mark.parametrize("name", DRAWN)
def test_drawn_relations_follow_their_sql_at_every_size(spark, name):
    got = sorted((tuple(r) for r in entry.queries()[name](spark, SF).collect()), key=repr)
    assert got == by_sql(entry.oracle_sql()[name])


def test_a_join_beyond_long_may_have_groups_that_fit(spark):
    from multiagg.operators.multiway import multiway_aggregate
    from multiagg.plans.cost import choose_strategy
    from multiagg.plans.spec import GroupedJoinSpec, Rel

    many = spark.range(300).selectExpr("id as g", "1 as j", "'x' as b")
    same = spark.range(20000).selectExpr("1 as j", "'x' as b")
    rels = [Rel("r0", many, {"g": "g", "j": "j"}, ("g",)), *(Rel(f"r{i}", same, {"j": "j"}) for i in (1, 2, 3)), Rel("r4", spark.range(50000).selectExpr("1 as j"), {"j": "j"})]
    spec = GroupedJoinSpec(tuple(rels))
    assert choose_strategy(spec).join_rows > 2**63
    assert {r["cnt"] for r in multiway_aggregate(spec).collect()} == {20000**3 * 50000}


def test_ears_are_folded_without_adding_up_between_them(spark):
    from multiagg.operators.measure import plan_nodes
    from multiagg.operators.multiway import prepared
    from multiagg.plans.cost import join_size, ungrouped
    from multiagg.plans.spec import GroupedJoinSpec, Rel

    rows = spark.range(3000).selectExpr("id % 11 as j", "id % 13 as b")
    spec = GroupedJoinSpec((Rel("a", rows, {"j": "j"}), Rel("mid", rows, {"j": "j", "b": "b"}), Rel("c", rows, {"b": "b"}), Rel("d", rows, {"b": "b"})))
    want = rows.alias("m").join(rows.alias("a"), "j").groupBy("m.b").count().collect()
    n = {r["b"]: r["count"] for r in rows.groupBy("b").count().collect()}
    assert join_size(spec) == sum(r["count"] * n[r["b"]] ** 2 for r in want)
    plan = prepared(ungrouped(spec)).edges["a"]
    assert len([1 for name, _ in plan_nodes(plan) if "HashAggregate" in name]) <= 2 * 6
