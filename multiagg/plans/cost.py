"""Exact and estimated sizes, and the choice they lead to."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace
from functools import reduce
from itertools import permutations
from math import ceil, expm1, prod

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.operators.algebra import M
from multiagg.operators.multiway import prepared, shared_arms
from multiagg.plans.spec import Agg, GroupedJoinSpec, Rel, normalize_spec
from multiagg.plans.tree import Node, build_hypergraph, decompose


def selectivity(df: DataFrame, cols: list[str], exact: bool = True, rsd: float = 0.02) -> DataFrame:
    """(n_rows, n_values, selectivity): distinct values over rows; 1 for a key, low for a join that blows up."""
    values = F.count_distinct(*cols) if exact else F.approx_count_distinct(F.struct(*cols), rsd)
    out = df.agg(F.count("*").alias("n_rows"), values.alias("n_values"))
    return out.withColumn("selectivity", F.round(F.try_divide(F.col("n_values").cast("double"), F.col("n_rows").cast("double")), 6))


def ungrouped(spec: GroupedJoinSpec) -> GroupedJoinSpec:
    return replace(spec, relations=tuple(replace(r, group=()) for r in spec.relations), aggs=(Agg.count("join_rows"),), having=None)


def join_cardinality(spec: GroupedJoinSpec) -> DataFrame:
    """Exact number of join rows before aggregation, in linear time: weights are summed up the tree, nothing is joined out."""
    graph = prepared(ungrouped(normalize_spec(spec)))
    return shared_arms(graph).select(F.coalesce(F.col(M), F.lit(0)).cast("long").alias("join_rows"))


def join_size(spec: GroupedJoinSpec) -> int:
    """The same for choosing: summed in doubles, as groups may each fit into a long where the whole join doesn't. Exact up to 2^53."""
    graph = prepared(replace(ungrouped(normalize_spec(spec)), count_type="double"))
    return int(shared_arms(graph).first()[0] or 0)


@dataclass(frozen=True)
class Stats:
    """Rows, different edges and different values of each attribute, by relation."""

    rows: dict[str, float]
    edges: dict[str, float]
    values: dict[str, dict[str, float]]


def gather(spec: GroupedJoinSpec, rsd: float = 0.05) -> Stats:
    """Sketches of all relations in one job; relations that read the same columns of one table share a scan. Takes a normalized spec."""
    like: dict[tuple, list[Rel]] = {}
    for r in spec.relations:
        like.setdefault((id(r.df), r.where, *(r.attrs[a] for a in sorted(r.attrs, key=r.attrs.get))), []).append(r)
    made = []
    for (first, *_) in like.values():
        cols = sorted(first.attrs, key=first.attrs.get)
        each = [F.approx_count_distinct(c, rsd).cast("double") for c in cols]
        made.append(first.frame(cols).agg(F.lit(first.name).alias("name"), F.count("*").cast("double").alias("n"), F.approx_count_distinct(F.struct(*cols), rsd).cast("double").alias("edges"), F.array(*each).alias("each")))
    found = {r["name"]: r for r in reduce(DataFrame.unionByName, made).collect()}
    rows, edges, values = {}, {}, {}
    for first, *others in like.values():
        got = found[first.name]
        for r in (first, *others):
            rows[r.name], edges[r.name] = got["n"], max(got["edges"], 1.0)
            values[r.name] = {a: max(v, 1.0) for a, v in zip(sorted(r.attrs, key=r.attrs.get), got["each"])}
    return Stats(rows, edges, values)


@dataclass
class Sized:
    """An intermediate table as it is expected: rows and different values of its columns."""

    rows: float
    values: dict[str, float]

    def keys(self, cols: Iterable[str]) -> float:
        return min(self.rows, prod(self.values[c] for c in cols)) if self.rows > 1 else 1.0

    def met(self, other: Sized, on: Iterable[str], keep: Iterable[str]) -> Sized:
        """Rows that agree in `on`, values spread evenly and the smaller set of them inside the larger."""
        on = list(on)
        rows = self.rows * other.rows / max(self.keys(on), other.keys(on), 1.0)
        both = {**other.values, **self.values} | {a: min(self.values[a], other.values[a]) for a in on}
        return Sized(rows, {a: min(both[a], max(rows, 1.0)) for a in keep})

    def collapsed(self, cols: Iterable[str]) -> Sized:
        """Groups that so many rows fill, each group being as likely."""
        cols = list(cols)
        space = prod(self.values[c] for c in cols)
        rows = self.rows if space > 1e6 * max(self.rows, 1.0) else space * -expm1(-self.rows / space)
        return Sized(max(rows, 1.0), {c: min(self.values[c], max(rows, 1.0)) for c in cols})


@dataclass
class Work:
    """Rows that the joins make, and the most that one of them makes."""

    rows: float = 0.0
    widest: float = 0.0

    def __add__(self, other: Work) -> Work:
        return Work(self.rows + other.rows, max(self.widest, other.widest))


def edge_sizes(spec: GroupedJoinSpec, stats: Stats | None) -> dict[str, Sized] | None:
    """Sizes of the edge tables as they are expected; only where counts alone are asked for."""
    if stats is None or [a.kind for a in spec.aggs] != ["count"]:
        return None
    return {n: Sized(stats.edges[n], dict(v)) for n, v in stats.values.items()}


def keys_joined(spec: GroupedJoinSpec, stats: Stats) -> tuple[GroupedJoinSpec, Stats]:
    """Relations that branch and have one row for each value of a join attribute are joined to the relation that shares it. Takes a normalized spec.

    Below such a value hangs the product of the branches' groups, while the values that the branches start from are few:
    a row takes these instead of its key, no rows are made, and the branches become the other relation's own.
    """
    rels, stats = list(spec.relations), Stats(dict(stats.rows), dict(stats.edges), dict(stats.values))
    while True:
        shares = lambda a: [r for r in rels if a in r.attrs]  # noqa: B023, E731
        found = next(((k, a) for k in rels for a in k.attrs if len(rels) > 2 and not k.group and not k.measures and len(k.attrs) > 2 and len(shares(a)) == 2
                      and all(len(shares(b)) > 1 for b in k.attrs) and stats.rows[k.name] <= 1.2 * stats.values[k.name][a]), None)
        if not found:
            return replace(spec, relations=tuple(rels)), stats
        k, a = found
        to = next(r for r in shares(a) if r is not k)
        if set(to.attrs) & set(k.attrs) != {a}:
            return replace(spec, relations=tuple(rels)), stats
        attrs = [*(x for x in to.attrs if x != a), *(x for x in k.attrs if x != a)]
        df = to.frame([*to.attrs, *to.measures]).join(k.frame(list(k.attrs)), a).select(*attrs, *to.measures)
        made = Rel(to.name, df, {x: x for x in attrs}, to.group, {m: m for m in to.measures}, loose=True)
        rels = [made if r is to else r for r in rels if r is not k]
        both = {**stats.values[k.name], **stats.values[to.name]}
        stats.values[to.name] = {x: both[x] for x in attrs}
        for part in (stats.rows, stats.edges, stats.values):
            del part[k.name]


def below(n: Node) -> list[str]:
    return [g for x in n.walk() for g in x.group]


def estimated(tree: Node, stats: Stats) -> Work:
    """Work of shared arms on a tree; sets the order in which the arms of each relation are met.

    Up to five arms are tried in every order, more of them smaller ones first.
    """

    def visit(n: Node) -> tuple[Sized, Work]:
        own = list(dict.fromkeys([*n.up, *n.down, *n.group]))
        start = Sized(stats.edges[n.name], {a: stats.values[n.name][a] for a in own})
        arms = {c.name: (c, *visit(c)) for c in n.children}
        spent = reduce(Work.__add__, (w for _, _, w in arms.values()), Work())

        def run(order: tuple[str, ...]) -> tuple[Sized, Work]:
            table, work, have = start, Work(), list(n.group)
            for i, name in enumerate(order):
                c, side, _ = arms[name]
                have += below(c)
                needed = list(dict.fromkeys([*n.up, *(a for x in order[i + 1 :] for a in arms[x][0].up), *have]))
                table = table.met(side, c.up, needed)
                work = work + Work(table.rows, table.rows)
                table = table.collapsed(needed)
            return table.collapsed([*n.up, *have]), work

        names = sorted(arms, key=lambda x: (-len(list(arms[x][0].walk())), arms[x][1].rows, x))
        tried = [(run(o), o) for o in (permutations(names) if len(names) <= 5 else [tuple(names)])]
        (table, work), order = min(tried, key=lambda x: x[0][1].rows)
        n.order = list(order)
        return table, spent + work

    return visit(tree)[1]


def estimated_preaggregation(tree: Node, stats: Stats) -> Work:
    """Work of joining the weighted relations one by one from the root, adding up after each join."""
    nodes, work = list(tree.walk()), Work()
    attrs = {n.name: {*n.up, *n.down} for n in nodes}
    sized = lambda n: Sized(stats.edges[n.name], {a: stats.values[n.name][a] for a in {*attrs[n.name], *n.group}})
    table, have, groups = sized(nodes[0]), set(attrs[nodes[0].name]), list(nodes[0].group)
    for i, n in enumerate(nodes[1:], 1):
        on = sorted(have & attrs[n.name])
        have = (have | attrs[n.name]) & set().union(*(attrs[x.name] for x in nodes[i + 1 :]))
        groups += n.group
        table = table.met(sized(n), on, [*sorted(have), *groups])
        work = work + Work(table.rows, table.rows)
        table = table.collapsed([*sorted(have), *groups])
    return work


def join_order(tree: Node, stats: Stats) -> list[str]:
    """An order for joining rows one relation at a time, each next to one before it: from every start the least growing join comes next, and the order with the fewest rows between the joins is taken."""
    nodes = {n.name: n for n in tree.walk()}
    links = {name: set() for name in nodes}
    for n in nodes.values():
        for c in n.children:
            links[n.name].add((c.name, c.up))
            links[c.name].add((n.name, c.up))
    made = []
    for start in nodes:
        order, table, between = [start], Sized(stats.rows[start], stats.values[start]), 0.0
        while len(order) < len(nodes):
            near = [(x, up) for name in order for x, up in links[name] if x not in order]
            tried = [(table.met(Sized(stats.rows[x], stats.values[x]), up, {**table.values, **stats.values[x]}), x) for x, up in near]
            between += table.rows
            table, name = min(tried, key=lambda t: (t[0].rows, list(nodes).index(t[1])))
            order.append(name)
        made.append((round(between), len(made), order))
    return min(made)[2]


def trees(spec: GroupedJoinSpec, stats: Stats, sources_only: bool = False) -> list[tuple[Work, Node]]:
    """The join tree under each possible root with its estimated work, least work first. Sources are relations with a group."""
    h = build_hypergraph(spec)
    roots = [r.name for r in spec.relations if r.group or not sources_only] or [spec.relations[0].name]
    made = [(estimated(t := decompose(h, root), stats), t) for root in roots]
    return sorted(made, key=lambda x: x[0].rows)


def best_tree(spec: GroupedJoinSpec, sources_only: bool = False, stats: Stats | None = None) -> Node | None:
    """The tree of least work; None, which leaves the first group relation on top, where two relations at most leave nothing to choose."""
    spec = normalize_spec(spec)
    return trees(spec, stats or gather(spec), sources_only)[0][1] if len(spec.relations) > 2 else None


def choose_root(spec: GroupedJoinSpec, sources_only: bool = True) -> str:
    """The relation that the least work has on top, out of those with a group or out of all."""
    spec = normalize_spec(spec)
    return trees(spec, gather(spec), sources_only)[0][1].name


@dataclass(frozen=True)
class Choice:
    strategy: str
    join_rows: int
    input_rows: int
    reason: str
    tree: Node | None = None
    batches: int | None = None
    stats: Stats | None = None


def choose_strategy(spec: GroupedJoinSpec, blow_up: float = 2.0, gain: float = 0.8, state_rows: float = 1e11) -> Choice:
    """The classic plan if the join hardly grows beyond its inputs, else what promises the least work.

    The join's size is counted, not estimated; it costs one linear pass over the join columns. Work is estimated from sketches:
    pre-aggregation is taken below `gain` times the work of the best tree, slices of the sources where a join
    makes more than `state_rows` rows. `per_source` and `packed` never make fewer rows and are only run by name.
    """
    normal = normalize_spec(spec)
    join_rows = join_size(spec)
    stats = gather(normal)
    most = int(max(stats.rows.values(), default=0))
    if join_rows <= blow_up * most:
        return Choice("traditional", join_rows, most, "the join is no larger than its inputs allow")
    joined, after = keys_joined(normal, stats)
    work, tree = trees(joined, after)[0]
    other = estimated_preaggregation(decompose(build_hypergraph(normal)), stats)
    if other.rows < gain * work.rows:
        return Choice("preagg_every", join_rows, most, f"pre-aggregation makes some {other.rows:.3g} rows, the best tree {work.rows:.3g}")
    if work.widest > state_rows:
        work, tree = trees(joined, after, True)[0]
        return Choice("source_batches", join_rows, most, f"one join makes some {work.widest:.3g} rows", tree, max(2, ceil(work.widest / state_rows)), stats)
    return Choice("shared_arms", join_rows, most, f"the join has {join_rows} rows, the largest input {most}, the tree under {tree.name} makes some {work.rows:.3g}", tree, stats=stats)


def combine_cost(spec: GroupedJoinSpec) -> DataFrame:
    """Rows that meet at each branch relation: the sum over branch values of the product of their arms' sizes."""
    from multiagg.operators.multiway import arm

    graph = prepared(spec)
    out = []
    for n in graph.tree.walk():
        if len(n.children) > 1:
            table = graph.edges[n.name].select(*graph.keys(n), F.lit(1).cast("long").alias("rows"))
            for i, c in enumerate(n.children):
                table = table.join(arm(graph, c).groupBy(*c.up).agg(F.count("*").alias(f"n{i}")), list(c.up)).withColumn("rows", F.col("rows") * F.col(f"n{i}")).drop(f"n{i}")
            out.append(table.agg(F.coalesce(F.sum("rows"), F.lit(0)).alias("rows")).select(F.lit(n.name).alias("relation"), "rows"))
    if not out:
        spark = graph.edges[graph.tree.name].sparkSession
        return spark.createDataFrame([], "relation string, rows long")
    return reduce(DataFrame.unionByName, out)


def predicted(shape: str, n: float, a: float, b: float) -> dict[str, float]:
    """The analysis' leading terms for n rows per relation, a group and b join values: work of the classic plan, of the operator, of pre-aggregation."""
    from math import log2

    sort = lambda x: x * log2(max(x, 2))
    if shape == "self":
        return {"traditional": sort(n * n / b), "operator": a * a * b, "preaggregate": sort(a * a * b)}
    if shape == "chain2":
        return {"traditional": sort(n**4 / b**3), "operator": a * a * b, "preaggregate": sort(a * a * b) + sort(a * b * b)}
    if shape == "chain4":
        return {"traditional": sort(n**4 / b**3), "operator": a * sort(n * n / b), "preaggregate": min(sort(n**4 / b**3), sort(a**4 * b))}
    if shape == "branch":
        return {"traditional": sort(n**5 / b**4), "operator": max(a * a * b, a * sort(n)), "preaggregate": sort(a**4 * b)}
    raise ValueError(shape)


def plan_of(spec: GroupedJoinSpec, root: str | None = None):
    spec = normalize_spec(spec)
    return decompose(build_hypergraph(spec), root)
