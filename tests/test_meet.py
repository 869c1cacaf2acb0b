"""Joins whose product is added up within the tasks."""

import numpy as np
import pyarrow as pa
import pytest

from multiagg.operators import meet
from multiagg.operators.baselines import preaggregate, traditional
from multiagg.operators.measure import measure
from multiagg.operators.multiway import multiway_aggregate
from multiagg.plans.spec import GroupedJoinSpec, Rel

GOT = ["g", "h", "__m"]


def multiply(left, right, size=None):
    """Rows (key, group, count) of both sides by the task's function, in batches of `size`."""
    rows = sorted([(k, 0, g, None, m) for k, g, m in left] + [(k, 1, None, g, m) for k, g, m in right], key=lambda r: (r[0], r[1]))
    t = pa.Table.from_pylist([dict(zip(("k0", "side", "c0", "c1", "m"), r)) for r in rows], pa.schema([("k0", pa.int64()), ("side", pa.int32()), ("c0", pa.string()), ("c1", pa.string()), ("m", pa.int64())]))
    out = {}
    for b in meet._multiplier(["k0"], ["c0"], ["c1"], ["g", "h"], ["g", "h"])(iter(t.to_batches(size))):
        for r in b.to_pylist():
            out[r["g"], r["h"]] = out.get((r["g"], r["h"]), 0) + r["__m"]
    return out


def by_hand(left, right):
    out = {}
    for k, g, m in left:
        for j, h, n in right:
            if k == j:
                out[g, h] = out.get((g, h), 0) + m * n
    return out


def test_the_product_never_stands_between_operators(spark):
    rows = spark.range(4000).selectExpr("id % 40 as g", "id % 7 as j")
    spec = GroupedJoinSpec((Rel("a", rows, {"g": "g", "j": "j"}, ("g",)), Rel("b", rows, {"h": "g", "j": "j"}, ("h",))))
    want = sorted(map(tuple, traditional(spec).collect()))
    for made in (multiway_aggregate(spec, "shared_arms"), multiway_aggregate(spec, "per_source"), preaggregate(spec, "inputs"), preaggregate(spec)):
        assert sorted(map(tuple, made.select("g", "h", "cnt").collect())) == want
        assert measure(made).most_rows_between < 40 * 40 * 7


@pytest.mark.parametrize("thin", [True, False])
@pytest.mark.parametrize("run_rows", [3, 1000])
def test_runs_and_both_ways_of_multiplying(monkeypatch, thin, run_rows):
    monkeypatch.setattr(meet, "RUN_ROWS", run_rows)
    monkeypatch.setattr(meet, "CELLS", 5)
    monkeypatch.setattr(meet, "DENSE", 0 if thin else 10**9)
    pick = np.random.default_rng(1)
    side = lambda: [(int(k), None if g == 0 else f"g{g}", int(m)) for k, g, m in zip(pick.integers(0, 9, 60), pick.integers(0, 6, 60), pick.integers(1, 9, 60))]
    left, right = side() + [(77, "alone", 1)], side() + [(5, "g1", 2)] * 20
    assert multiply(left, right, 4) == by_hand(left, right)
    assert multiply([(1, "a", 1)], [(2, "b", 1)]) == {} == multiply([(1, "a", 1)], [])


@pytest.mark.parametrize("thin", [True, False])
def test_counts_beyond_doubles_are_exact_and_overflow_is_an_error(monkeypatch, thin):
    monkeypatch.setattr(meet, "DENSE", 0 if thin else 10**9)
    left, right = [(1, "a", 2**31 + 1), (2, "a", 3)], [(1, "b", 2**30 + 1), (2, "b", 5)]
    assert multiply(left, right) == by_hand(left, right) == {("a", "b"): (2**31 + 1) * (2**30 + 1) + 15}
    assert multiply([(1, "a", 2**62)], [(1, "b", 1)]) == {("a", "b"): 2**62}
    with pytest.raises(ArithmeticError):
        multiply([(1, "a", 2**40)], [(1, "b", 2**40)])


def test_a_product_that_is_not_added_up_yet_stays_where_it_is(spark):
    from multiagg.operators.measure import plan_nodes

    rows = spark.range(400).selectExpr("id % 20 as g", "id % 7 as j")
    spec = GroupedJoinSpec(tuple(Rel(x, rows, {f"g{x}": "g", "j": "j"}, (f"g{x}",)) for x in "abc"))
    made = preaggregate(spec, "inputs")
    assert not [1 for name, _ in plan_nodes(made) if "MapInArrow" in name]
    assert sorted(map(tuple, made.select("ga", "gb", "gc", "cnt").collect())) == sorted(map(tuple, traditional(spec).select("ga", "gb", "gc", "cnt").collect()))
