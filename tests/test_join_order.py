"""The classic plan joins what makes rows last."""

import pytest

from multiagg.operators.baselines import traditional
from multiagg.operators.measure import plan_nodes
from multiagg.plans.cost import gather, join_order, plan_of
from multiagg.plans.spec import GroupedJoinSpec, Rel, normalize_spec


@pytest.fixture
def chain(spark):
    supply = spark.range(2000).selectExpr("id % 20 as part", "id % 97 as supp")
    items, ords = spark.range(3000).selectExpr("id % 20 as part", "id % 700 as ord"), spark.range(700).selectExpr("id as ord", "id % 50 as cust")
    custs = spark.range(50).selectExpr("id as cust", "if(id = 3, null, id % 4) as zip")
    return GroupedJoinSpec((Rel("supply", supply, {"part": "part", "supp": "supp"}, ("supp",)), Rel("items", items, {"part": "part", "ord": "ord"}), Rel("ords", ords, {"ord": "ord", "cust": "cust"}), Rel("custs", custs, {"cust": "cust", "zip": "zip"}, ("zip",))))


def test_the_join_that_makes_rows_comes_last(chain):
    order = join_order(plan_of(chain), gather(normalize_spec(chain)))
    assert order[-1] == "supply" and sorted(order) == ["custs", "items", "ords", "supply"]


@pytest.mark.parametrize("join", [None, "shuffle_hash", "merge", "broadcast"])
def test_the_whole_join_is_made_and_dealt_once(chain, join):
    got = traditional(chain, join)
    by = {r.name: r.df for r in chain.relations}
    want = by["supply"].join(by["items"], "part").join(by["ords"], "ord").join(by["custs"], "cust").groupBy("supp", "zip").count()
    assert got.columns == ["supp", "zip", "cnt"]
    assert sorted(map(tuple, got.collect()), key=repr) == sorted(map(tuple, want.collect()), key=repr)
    joins = [int(p.metrics().apply("numOutputRows").value()) for name, p in plan_nodes(got) if "Join" in name]
    assert max(joins) == 2000 * 150 and sum(joins) < 2000 * 150 + 3 * 3000 + 3000
