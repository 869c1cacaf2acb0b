import pytest

from multiagg.plans.spec import Agg, GroupedJoinSpec, Rel, SpecError, normalize_spec
from multiagg.plans.tree import build_hypergraph, classify, decompose, is_acyclic, split_attributes


def spec(**rels):
    made = []
    for name, (attrs, group) in rels.items():
        made.append(Rel(name, None, {a: a for a in attrs.split()}, tuple(group.split())))
    return normalize_spec(GroupedJoinSpec(tuple(made)))


WORKED = dict(A=("g1 j", "g1"), B=("j jc jd", ""), C=("jc g2", "g2"), D=("jd je", ""), E=("je g3", "g3"), F=("je g4", "g4"))


def test_worked_splits_and_roles():
    tree = decompose(build_hypergraph(spec(**WORKED)), "A")
    splits, roles = split_attributes(tree), classify(tree)
    assert splits["A"] == (("g1",), ("j",)) and splits["B"] == (("j",), ("jc", "jd")) and splits["C"] == (("jc",), ("g2",))
    assert splits["D"] == (("jd",), ("je",)) and splits["E"] == (("je",), ("g3",)) and splits["F"] == (("je",), ("g4",))
    assert {n for n, r in roles.items() if "branch" in r} == {"B", "D"}
    assert roles["A"] == {"source"} and "group" in roles["C"]


def test_inner_group_relation_is_a_branch_of_its_join_values():
    tree = decompose(build_hypergraph(spec(R1=("g1 j0", "g1"), R2=("j0 j1 g2", "g2"), R3=("j1 g3", "g3"))), "R1")
    assert split_attributes(tree)["R2"] == (("j0", "j1"), ("g2",))
    assert classify(tree)["R2"] == {"branch", "group"}


def test_cyclic_joins_are_refused():
    s = spec(R=("a b x", "x"), S=("b c", ""), T=("a c y", "y"))
    assert not is_acyclic(build_hypergraph(s))
    with pytest.raises(SpecError, match="cyclic"):
        decompose(build_hypergraph(s))


def test_relations_that_join_nothing_are_refused():
    with pytest.raises(SpecError):
        decompose(build_hypergraph(spec(R=("a x", "x"), S=("b y", "y"))))


def test_group_attribute_that_joins_is_copied():
    s = spec(R=("a", "a"), S=("a g", "g"))
    assert s.by_name["R"].group == ("a__own",) and set(s.by_name["R"].attrs) == {"a", "a__own"}


def test_unknown_measure_is_refused():
    with pytest.raises(SpecError, match="measure"):
        normalize_spec(GroupedJoinSpec((Rel("R", None, {"a": "a"}, ("a",)),), (Agg.sum("R", "x"),)))
