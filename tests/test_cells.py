"""Joins whose groups are dealt, so that whole sums leave the tasks."""

import numpy as np
import pyarrow as pa
import pytest

from multiagg.operators import cells
from multiagg.operators.measure import measure
from multiagg.operators.multiway import multiway_aggregate
from multiagg.plans.spec import GroupedJoinSpec, Rel


def cell(*sides):
    """Groups and counts by the task's function; a side is rows of (key, group, count), packed three at a time."""
    packs = []
    for i, rows in enumerate(sides):
        t = pa.table({"block": pa.array([0] * len(rows), pa.int32()), "k0": [r[0] for r in rows], f"c{i}": pa.array([r[1] for r in rows], pa.string()), "m": pa.array([r[2] for r in rows], pa.int64())})
        packs += [(i, x) for b in cells._pack(["k0", f"c{i}", "m"])(iter(t.to_batches(3))) for x in b.column("rows").to_pylist()]
    given = pa.RecordBatch.from_arrays([pa.array([i for i, _ in packs], pa.int32()), pa.array([x for _, x in packs], pa.binary())], names=["side", "rows"])
    names = [f"g{i}" for i in range(len(sides))]
    got = [tuple(r.values()) for b in cells._cell(["k0"], [[f"c{i}"] for i in range(len(sides))], names, names)(iter([given])) for r in b.to_pylist()]
    assert len({r[:-1] for r in got}) == len(got)  # whole sums
    return {r[:-1]: r[-1] for r in got}


def by_hand(first, *others):
    made = [((g,), k, m) for k, g, m in first]
    for side in others:
        made = [((*g, h), k, m * n) for g, k, m in made for j, h, n in side if j == k]
    out = {}
    for g, _, m in made:
        out[g] = out.get(g, 0) + m
    return out


@pytest.mark.parametrize("arms", [1, 2, 3])
@pytest.mark.parametrize("thin", [True, False])
@pytest.mark.parametrize("size", [7, 1000])
def test_cells_by_hand(monkeypatch, arms, thin, size):
    monkeypatch.setattr(cells, "CELLS", size)
    monkeypatch.setattr(cells, "PACK_ROWS", 5)
    monkeypatch.setattr(cells, "DENSE", 0 if thin else 10**9)
    pick = np.random.default_rng(1)
    side = lambda: [(int(k), None if g == 0 else f"g{g}", int(m)) for k, g, m in zip(pick.integers(0, 9, 40), pick.integers(0, 6, 40), pick.integers(1, 9, 40))]
    sides = [side() + [(77, "alone", 1)], *(side() + [(5, "g1", 2)] * 3 for _ in range(arms))]
    assert cell(*sides) == by_hand(*sides)
    assert cell([(1, "a", 1)], *[[(2, "b", 1)]] * arms) == {} == cell([(1, "a", 1)], *[[]] * arms)


@pytest.mark.parametrize("arms", [1, 2])
@pytest.mark.parametrize("thin", [True, False])
def test_counts_beyond_doubles_are_exact_and_overflow_is_an_error(monkeypatch, arms, thin):
    monkeypatch.setattr(cells, "DENSE", 0 if thin else 10**9)
    one = [[(1, "c", 1), (2, "c", 1)]] * (arms - 1)
    sides = [[(1, "a", 2**31 + 1), (2, "a", 3)], *one, [(1, "b", 2**30 + 1), (2, "b", 5)]]
    assert cell(*sides) == by_hand(*sides)
    assert list(cell([(1, "a", 2**62)], *one, [(1, "b", 1)]).values()) == [2**62]
    with pytest.raises(ArithmeticError):
        cell([(1, "a", 2**40)], *one, [(1, "b", 2**40)])


@pytest.mark.parametrize("cache", [True, False])
def test_a_branch_leaves_its_tasks_with_whole_sums(spark, monkeypatch, cache):
    monkeypatch.setattr(cells, "PARTS", 0, raising=False)
    rows = spark.range(6000).selectExpr("if(id % 32 = 0, null, id % 32) as g", "id * 7 % 41 % 30 as j", "id * 11 % 43 % 30 as b")
    spec = GroupedJoinSpec((Rel("r1", rows, {"g1": "g", "j": "j"}, ("g1",)), Rel("r2", rows, {"j": "j", "b": "b"}), *(Rel(f"r{i}", rows, {"b": "b", f"g{i}": "g"}, (f"g{i}",)) for i in (3, 4))))
    want = sorted(map(tuple, multiway_aggregate(spec, "shared_arms").select("g1", "g3", "g4", "cnt").collect()), key=repr)
    made = multiway_aggregate(spec, "per_source", cache_trails=cache).select("g1", "g3", "g4", "cnt")
    assert sorted(map(tuple, made.collect()), key=repr) == want and len(want) == 32**3
    assert measure(made).most_rows_between <= 32**3


def test_pairs_are_added_up_where_they_are_made(spark, monkeypatch):
    monkeypatch.setattr(cells, "PARTS", 0, raising=False)
    rows = spark.range(9000).selectExpr("id * 7 % 64 as user", "id * 11 % 97 % 50 as k")
    spec = GroupedJoinSpec(tuple(Rel(f"r{i}", rows, {"k": "k", f"user{i}": "user"}, (f"user{i}",)) for i in (1, 2)))
    made = multiway_aggregate(spec)
    by_k = rows.groupBy("user", "k").count().collect()
    want = {}
    for a in by_k:
        for b in by_k:
            if a["k"] == b["k"]:
                want[a["user"], b["user"]] = want.get((a["user"], b["user"]), 0) + a["count"] * b["count"]
    assert {(r["user1"], r["user2"]): r["cnt"] for r in made.collect()} == want
    plan = made._jdf.queryExecution().executedPlan().toString()
    assert plan.index("MapInArrow") < plan.index("Exchange")  # nothing is dealt after the product
