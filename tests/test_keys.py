"""Relations that branch below a key are joined to the relation above before the product of their arms is made."""

import pytest

from multiagg.operators import cells
from multiagg.operators.baselines import traditional
from multiagg.operators.measure import measure
from multiagg.operators.multiway import multiway_aggregate
from multiagg.plans.cost import gather, keys_joined
from multiagg.plans.spec import Agg, GroupedJoinSpec, Rel, normalize_spec


@pytest.fixture
def star(spark):
    hub = spark.range(3000).selectExpr("id % 700 as ord", "if(id % 50 = 3, null, id * 7 % 400) as part")
    goods = spark.range(400).selectExpr("id as part", "id % 5 as brand", "id * 3 % 7 as size")
    few = spark.range(40).selectExpr("id % 5 as brand", "id % 7 as size", "if(id % 9 = 0, null, id % 20) as kind")
    return [
        Rel("o1", spark.range(690).selectExpr("id as ord", "id % 3 as priority"), {"ord": "ord", "priority": "priority"}, ("priority",)), Rel("hub", hub, {"ord": "ord", "part": "part"}),
        Rel("goods", goods, {"part": "part", "brand": "brand", "size": "size"}), Rel("p1", few, {"brand": "brand", "kind1": "kind"}, ("kind1",)), Rel("p2", few, {"size": "size", "kind2": "kind"}, ("kind2",)),
    ]


def rows(df):
    return sorted((tuple(r) for r in df.select("priority", "kind1", "kind2", "cnt").collect()), key=repr)


@pytest.mark.parametrize("in_cells", [True, False])
@pytest.mark.parametrize("strategy", ["auto", "shared_arms", "per_source", "source_batches"])
def test_a_key_that_branches_hands_its_values_on(star, monkeypatch, strategy, in_cells):
    if in_cells:
        monkeypatch.setattr(cells, "PARTS", 0, raising=False)
    spec = GroupedJoinSpec(tuple(star))
    made = multiway_aggregate(spec, strategy)
    assert rows(made) == rows(traditional(spec))
    if strategy in ("shared_arms", "per_source"):
        assert measure(made).most_rows_between < 2 * 3000  # before, every part met the product of its arms


def test_only_keys_that_branch_are_joined(star):
    spec = normalize_spec(GroupedJoinSpec(tuple(star)))
    few, stats = keys_joined(spec, gather(spec))
    assert [r.name for r in few.relations] == ["o1", "hub", "p1", "p2"] == list(stats.values)
    assert set(few.by_name["hub"].attrs) == {"ord", "brand", "size"} == set(stats.values["hub"])
    twice = [r if r.name != "goods" else Rel("goods", r.df.union(r.df), r.attrs) for r in star]
    spec = normalize_spec(GroupedJoinSpec(tuple(twice)))
    assert keys_joined(spec, gather(spec))[0].relations == spec.relations


@pytest.mark.parametrize("strategy", ["shared_arms", "per_source", "source_batches"])
def test_other_aggregates_over_joined_keys(star, strategy):
    with_x = [r if r.name != "hub" else Rel("hub", r.df, r.attrs, measures={"x": "ord * 2"}) for r in star]
    spec = GroupedJoinSpec(tuple(with_x), (Agg.count(), Agg.sum("hub", "x"), Agg.max("hub", "x")))
    want, got = traditional(spec), multiway_aggregate(spec, strategy)
    assert sorted(map(tuple, got.select(*want.columns).collect()), key=repr) == sorted(map(tuple, want.collect()), key=repr)
