"""The multiway aggregate: grouped aggregates over an acyclic join that is never built.

`shared_arms` collapses the tree from the leaves: what lies below a join value does not depend
on the source, so it is computed once for all sources. At a branch the arms are joined on the
branch value, the products go straight into a partial hash aggregation, and the value is dropped.

`per_source` keeps, for each source value, the trail of branch values passed so far and starts
its count at one again behind each branch; arm entries of sibling arms meet on (source, trail),
the trail's own weight is multiplied once, then its last level is dropped. `trails` carries whole
trails, for inspection; the strategy carries of each what an arm starts from.

`source_batches` stores the arms below the source once, then runs slices of the sources one after the
other, each as a job of its own that appends its groups, which caps the state.
`packed` walks a small graph in the tasks; the graph's size is checked before it is broadcast, and
`multiway_aggregate` hands a larger one over to `shared_arms`.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import replace
from functools import reduce

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from multiagg.operators.algebra import M
from multiagg.operators.cells import fitting, met_in_cells
from multiagg.operators.graph import DataGraph, added, load_graph, multiplied, reduce_graph
from multiagg.operators.measure import scratch_dir
from multiagg.operators.meet import met
from multiagg.plans.spec import COPY, GroupedJoinSpec, SpecError, normalize_spec
from multiagg.plans.tree import Node, build_hypergraph, classify, decompose

STRATEGIES = ("shared_arms", "per_source", "source_batches", "packed")
PACKED_EDGES = 2_000_000


class TooManyEdges(SpecError):
    """The graph is too large to be broadcast."""


def carried(graph: DataGraph, n: Node) -> list[str]:
    """Group columns of a relation and all below it."""
    return [g for x in n.walk() for g in [*x.group, *graph.algebra.extra_groups(x.name)]]


def depth(n: Node) -> int:
    return 1 + max(map(depth, n.children), default=0)


def in_order(n: Node) -> list[Node]:
    """The order that the costs have found, else longest trails first; AQE picks the method of each join from measured sizes."""
    return sorted(n.children, key=lambda c: (n.order.index(c.name) if c.name in n.order else len(n.order), -depth(c), c.name))


def arm(graph: DataGraph, n: Node, edges: DataFrame | None = None, known: dict[str, DataFrame] | None = None) -> DataFrame:
    """What hangs on a relation: (join value above, group values below, annotations), added up.

    A join value is dropped, and rows that then agree are added, as soon as no open arm needs it.
    `edges` stands for the relation's own, `known` has arms that are made already.
    """
    table, open_, have = edges if edges is not None else graph.edges[n.name], in_order(n), [*n.group, *graph.algebra.extra_groups(n.name)]
    size = (graph.sizes or {}).get(n.name)
    needed = lambda: list(dict.fromkeys([*n.up, *(a for c in open_ for a in c.up), *have]))
    while open_:
        c = open_.pop(0)
        before = set(table.columns)
        have += carried(graph, c)
        below = known[c.name] if known and c.name in known else arm(graph, c)
        keep, side = list(dict.fromkeys(needed())), arm_size(graph, c)
        blocks, size = sized_step(graph, size, side, list(c.up), keep, [g for g in carried(graph, c)], bool(open_))
        if blocks:
            table = met_in_cells(graph, table, [(below, carried(graph, c))], list(c.up), keep, blocks)
        elif blocks == () or open_ and before - graph.algebra.have(list(before)) <= set(needed()):
            table = multiplied(graph, table, below, list(c.up), needed())
        else:
            table = met(graph, table, below, list(c.up), needed())
    return table if n.children else added(graph, table, needed())


def sized_step(graph: DataGraph, size, side, on: list[str], keep: list[str], there: list[str], more: bool) -> tuple[tuple[int, ...] | None, object]:
    """How a join is met as far as sizes are known, and what size comes of it: blocks of cells; () for rows that hardly fall together and are left as they are for the next join; None for the usual way."""
    if size is None or side is None:
        return None, None
    here, made = [x for x in keep if x not in there], size.met(side, on, keep)
    if set(on) <= set(keep):
        return None, made.collapsed(keep)
    blocks = fitting(graph, size, [side], on, here, [there]) if not set(on) & set(keep) else None
    if blocks is None and more and graph.joined and made.rows <= 1.2 * size.rows and made.rows < 4 * made.collapsed(keep).rows:
        return (), made
    return blocks, made.collapsed(keep)


def arm_size(graph: DataGraph, n: Node):
    """The size that is expected of an arm, None where it isn't known."""
    size, have, open_ = (graph.sizes or {}).get(n.name), [*n.group], in_order(n)
    while open_ and size:
        c = open_.pop(0)
        side, have = arm_size(graph, c), [*have, *carried(graph, c)]
        keep = list(dict.fromkeys([*n.up, *(a for x in open_ for a in x.up), *have]))
        size = size.met(side, c.up, keep).collapsed(keep) if side else None
    return size.collapsed([*n.up, *have]) if size else None


def in_cells(graph: DataGraph) -> bool:
    """Whether the one join of two relations is made in cells."""
    n = graph.tree
    (c,) = n.children or (None,)
    if c is None or not graph.sizes:
        return False
    return bool(sized_step(graph, graph.sizes[n.name], arm_size(graph, c), list(c.up), [*n.group, *carried(graph, c)], carried(graph, c), False)[0])


def shared_arms(graph: DataGraph) -> DataFrame:
    return arm(graph, graph.tree)


def branches(graph: DataGraph, n: Node) -> bool:
    return len(n.children) > 1 or bool(n.children and n is not graph.tree and (n.group or graph.algebra.extra_groups(n.name)))


def _one(graph: DataGraph, df: DataFrame) -> DataFrame:
    """The count starts at one again."""
    return df.withColumn(M, F.lit(1).cast(graph.spec.count_type)) if graph.algebra.counts else df


def trails(graph: DataGraph, cache_trails: bool = True) -> tuple[DataFrame, dict[str, DataFrame]]:
    """The result by sources, and the entries it was made from: weights of trails by branch relation, arm entries by group relation."""
    source = [*graph.tree.group, *graph.algebra.extra_groups(graph.tree.name)]
    seen: dict[str, DataFrame] = {}

    def visit(n: Node, front: DataFrame | None, levels: list[str]) -> DataFrame:
        edges, own = graph.edges[n.name], [] if n is graph.tree else [*n.group, *graph.algebra.extra_groups(n.name)]
        at = [*source, *levels]
        if not branches(graph, n):
            after = list(n.down) if n.children else own
            merged = cache_trails or not n.children
            if front is None:
                step = added(graph, edges, [*at, *after]) if merged else edges
            else:
                step = (met if merged else multiplied)(graph, front, edges, list(n.up), [*at, *after])
            if n.children:
                return visit(n.children[0], step, levels)
            seen[n.name] = step
            return step
        value = list(n.down) if not own else sorted({*n.up, *n.down})
        names = {a: f"__L{len(levels)}_{a}" for a in value}
        if front is None:
            reached = added(graph, edges, [*at, *value])
        elif own:
            reached = added(graph, multiplied(graph, front, edges.select(*value).distinct(), list(n.up), [*at, *value]), [*at, *value])
        else:
            reached = met(graph, front, edges, list(n.up), [*at, *value])
        weights = reached.withColumnsRenamed(names)
        seen[n.name] = weights
        trail = weights.select(*at, *names.values())
        deeper = [*levels, *names.values()]
        arms = []
        if own:
            here = _one(graph, trail.select("*", *(F.col(names[a]).alias(a) for a in value)))
            arms.append(met(graph, here, edges, value, [*source, *deeper, *own]))
            seen[n.name + COPY] = arms[0]
        for c in in_order(n):
            start = trail.select("*", *(F.col(names[a]).alias(a) for a in c.up))
            arms.append(visit(c, _one(graph, start), deeper))
        out, have = weights, []
        for a in arms:
            have += [x for x in a.columns if x not in graph.algebra.have(a.columns) and x not in source and x not in deeper]
            out = multiplied(graph, out, a, deeper, [*source, *deeper, *have], by_value=tuple(source))
        return added(graph, out, [*at, *have])

    return visit(graph.tree, None, []), seen


def per_source(graph: DataGraph, cache_trails: bool = True) -> DataFrame:
    """The result of `trails` with shorter trails: behind a branch an arm goes on with the values that it starts from, and its entries meet on these and the source.

    An arm of one relation starts at one and takes one step, so its edges are its entries, for every source. A branch's own group is carried with its weights.
    Where sizes are known and a step or a branch would leave its tasks with many parts of sums, it is made in cells of whole sums.
    """
    source = [*graph.tree.group, *graph.algebra.extra_groups(graph.tree.name)]
    sizes = graph.sizes or {}

    def visit(n: Node, front: DataFrame | None, levels: list[str], level: int, size=None) -> DataFrame:
        edges, own = graph.edges[n.name], [] if n is graph.tree else [*n.group, *graph.algebra.extra_groups(n.name)]
        at, after = [*source, *levels], [*n.down, *own]
        merged = cache_trails or not n.children or branches(graph, n)
        size, blocks = sizes.get(n.name) if front is None else size, None
        if front is not None and size and n.name in sizes:
            alone = bool(n.children) and not any(c.children for c in n.children)  # its rows are read once
            blocks, size = sized_step(graph, size, sizes[n.name], list(n.up), [*at, *after], after, alone) if merged else (None, size.met(sizes[n.name], n.up, [*at, *after]))
            merged = merged and blocks != ()
        if front is None:
            step = added(graph, edges, [*at, *after]) if merged else edges
        elif blocks:
            step = met_in_cells(graph, front, [(edges, after)], list(n.up), [*at, *after], blocks)
        else:
            step = (met if merged else multiplied)(graph, front, edges, list(n.up), [*at, *after])
        if not n.children:
            return step
        if not branches(graph, n):
            return visit(n.children[0], step, levels, level, size)
        names = {a: f"__L{level}_{a}" for a in n.down}
        weights, arms, leaves = step.withColumnsRenamed(names), [], []
        for c in in_order(n):
            up = [names[a] for a in c.up]
            if c.children:
                start = weights.select(*source, *up).distinct().select("*", *(F.col(names[a]).alias(a) for a in c.up))
                arms.append((up, source, visit(c, _one(graph, start), up, level + 1)))
            else:
                arms.append((up, [], graph.edges[c.name].withColumnsRenamed(dict(zip(c.up, up)))))
                leaves.append(c)
        if size and len(leaves) == len(arms) and all(c.up == n.down and c.name in sizes for c in leaves):
            blocks = fitting(graph, size, [sizes[c.name] for c in leaves], list(n.down), [*at, *own], [list(c.group) for c in leaves])
            if blocks:
                made = [(a, list(c.group)) for c, (_, _, a) in zip(leaves, arms)]
                return met_in_cells(graph, weights, made, arms[0][0], [*at, *own, *(g for c in leaves for g in c.group)], blocks)
        out, have = weights, own
        size = replace(size, values={names.get(x, x): v for x, v in size.values.items()}) if size and graph.joined else None
        for i, (up, by, a) in enumerate(arms):
            later = list(dict.fromkeys(x for others, _, _ in arms[i + 1 :] for x in others))
            there = [x for x in a.columns if x not in graph.algebra.have(a.columns) and x not in by and x not in up]
            have, c = [*have, *there], in_order(n)[i]
            side = None if by or c.name not in sizes else replace(sizes[c.name], values={names.get(x, x): v for x, v in sizes[c.name].values.items()})
            keep = list(dict.fromkeys([*at, *later, *have]))
            blocks, size = sized_step(graph, size, side, up, keep, there, bool(later))
            if blocks:
                out = met_in_cells(graph, out, [(a, there)], up, keep, blocks)
            elif size and blocks is None and not set(up) <= set(keep):
                out = met(graph, out, a, up, keep)
            else:
                out = multiplied(graph, out, a, up, keep, by_value=tuple(by))
        return added(graph, out, [*at, *have])

    return visit(graph.tree, None, [], 0)


def arm_entries(graph: DataGraph, group_relation: str) -> DataFrame:
    """For inspection: the list of (trail, count) at each group node of a relation, per source."""
    entries = trails(graph)[1]
    table = entries.get(group_relation + COPY, entries.get(group_relation))
    levels = [c for c in table.columns if c.startswith("__L")]
    rest = [c for c in table.columns if c not in levels and c != M]
    return table.groupBy(*rest).agg(F.sort_array(F.collect_list(F.struct(*levels, F.col(M).alias("count")))).alias("entries"))


def trail_join(left: DataFrame, right: DataFrame, source: list[str], left_levels: list[str], right_levels: list[str]) -> DataFrame:
    """The literal rule for a single spine: entries meet where the shorter trail starts the longer one. Level columns of both sides bear the same names."""
    shared = left_levels if len(left_levels) <= len(right_levels) else right_levels
    extra = [c for c in right.columns if c in (*source, *left_levels, *right_levels, M)]
    right = right.withColumnsRenamed({c: c + "__r" for c in extra})
    on = reduce(Column.__and__, [F.col(c).eqNullSafe(F.col(c + "__r")) for c in [*source, *shared]])
    joined = left.join(right, on).withColumn(M, F.col(M) * F.col(M + "__r"))
    gone = [c + "__r" for c in extra] + [c for c in left_levels if c not in shared]
    return joined.drop(*gone)


def sliced(graph: DataGraph, batches: int, known: dict[str, DataFrame] | None = None) -> list[DataFrame]:
    """One result per slice of the sources; every group belongs to one slice, so they only need to be appended."""
    n = graph.tree
    which = F.pmod(F.xxhash64(*n.group), F.lit(batches))
    return [arm(graph, n, graph.edges[n.name].where(which == i), known) for i in range(batches)]


def source_batches(graph: DataGraph, batches: int = 4) -> DataFrame:
    """The slices' results, each run and written before the next one starts; they share the stored arms."""
    n = graph.tree
    spark = graph.edges[n.name].sparkSession
    at = scratch_dir(spark)

    def stored(df: DataFrame, name: str) -> DataFrame:
        df.write.mode("append").parquet(f"{at}/{name}")
        return spark.read.schema(df.schema).parquet(f"{at}/{name}")

    known = {c.name: stored(arm(graph, c), f"arm{i}") for i, c in enumerate(n.children)}
    return [stored(df, "result") for df in sliced(graph, batches, known)][-1]


class PackedGraph:
    """Edge tables as arrays, sorted by the value above: offsets, neighbours' values and multiplicities."""

    def __init__(self, graph: DataGraph, tables: dict[str, pd.DataFrame]):
        self.tree, self.sides = graph.tree, {}
        for n in graph.tree.walk():
            t = tables[n.name]
            left = list(n.up)
            keys = list(zip(*(t[c] for c in left))) if left else [()] * len(t)
            order = sorted(range(len(t)), key=lambda i: keys[i])
            starts: dict = {}
            for place, i in enumerate(order):
                lo, _ = starts.get(keys[i], (place, place))
                starts[keys[i]] = (lo, place + 1)
            rows = t.iloc[order]
            pick = lambda cols, rows=rows: list(zip(*(rows[c].astype(object).where(rows[c].notna(), None) for c in cols))) if cols else [()] * len(rows)
            self.sides[n.name] = (starts, [pick(list(c.up)) for c in n.children], pick(list(n.group)), rows[M].tolist())

    def below(self, n: Node, key: tuple, known: dict) -> dict[tuple, int]:
        """Counts by group values below a join value; each value is walked once."""
        if (n.name, key) in known:
            return known[n.name, key]
        starts, downs, groups, weight = self.sides[n.name]
        out: dict[tuple, int] = {}
        for i in range(*starts.get(key, (0, 0))):
            for g, c in self.through(n, i, downs, groups, weight, known).items():
                out[g] = out.get(g, 0) + c
        known[n.name, key] = out
        return out

    def through(self, n: Node, i: int, downs, groups, weight, known: dict) -> dict[tuple, int]:
        made = {groups[i]: weight[i]}
        for c, values in zip(n.children, downs):
            side = self.below(c, values[i], known)
            made = {a + b: x * y for a, x in made.items() for b, y in side.items()}
        return made


def packed(graph: DataGraph, limit: int = PACKED_EDGES) -> DataFrame:
    """Counts by a walk in the tasks. Refuses a graph of more than `limit` edges, which is counted first."""
    if [a.kind for a in graph.spec.aggs] != ["count"]:
        raise SpecError("the packed walk counts only")
    edges = sum(df.count() for df in graph.edges.values())
    if edges > limit:
        raise TooManyEdges(f"{edges} edges are more than the {limit} that may be broadcast")
    spark = graph.edges[graph.tree.name].sparkSession
    tables = {name: df.toPandas() for name, df in graph.edges.items()}
    # Broadcasts pickle classes by reference, and workers need not have this package.
    shared = spark.sparkContext.broadcast(cloudpickle.dumps(PackedGraph(graph, tables)))
    top, below = graph.edges[graph.tree.name], carried(graph, graph.tree)[len(graph.tree.group) :]
    ids = top.select(*graph.tree.group, *graph.tree.down, M)
    kinds = {f.name: f.dataType.simpleString() for df in graph.edges.values() for f in df.schema}
    schema = ", ".join(f"`{c}` {kinds[c]}" for c in [*graph.tree.group, *below, M])

    def walk(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g, known = pickle.loads(shared.value), {}
        n = g.tree
        for f in frames:
            f = f.astype(object).where(f.notna(), None)
            downs, groups = [list(zip(*(f[a] for a in c.up))) for c in n.children], list(zip(*(f[a] for a in n.group)))
            out: dict[tuple, int] = {}
            for i, w in enumerate(f[M].tolist()):
                for k, c in g.through(n, i, downs, groups, {i: w}, known).items():
                    out[k] = out.get(k, 0) + c
            yield pd.DataFrame([(*k, c) for k, c in out.items()], columns=[*n.group, *below, M])

    return added(graph, ids.mapInPandas(walk, schema), [*graph.tree.group, *below])


def packed_or_shared(graph: DataGraph) -> DataFrame:
    """The walk in the tasks where the graph may be broadcast, else the same counts by shared arms."""
    try:
        return packed(graph, PACKED_EDGES)
    except TooManyEdges:
        return shared_arms(graph)


def finish(graph: DataGraph, table: DataFrame, sort: bool = False) -> DataFrame:
    """Result columns under their own names: distinct counts, averages, `having`, order."""
    spec, a = graph.spec, graph.algebra
    groups = spec.groups
    if a.distinct:
        extra = [(F.count_distinct if d.kind == "count_distinct" else F.approx_count_distinct)(d.over[0][1]).alias(d.alias) for d in a.distinct]
        table = table.groupBy(*groups).agg(*(c.alias(k) for k, c in a.plus(a.have(table.columns)).items()), *extra)
    names = {g: g.removesuffix(COPY) for g in groups}
    by_alias = {d.alias: F.col(d.alias) for d in a.distinct}
    made = iter(a.final(a.have(table.columns)))
    out = table.select(*(F.col(g).alias(n) for g, n in names.items()), *(by_alias[x.alias] if x.alias in by_alias else next(made) for x in spec.aggs))
    out = out.where(spec.having) if spec.having else out
    return out.orderBy(*names.values()) if sort else out


def prepared(spec: GroupedJoinSpec, root: str | None = None, pre_aggregate: bool = True, reduce_first: bool = False, tree: Node | None = None) -> DataGraph:
    spec = normalize_spec(spec)
    graph = load_graph(spec, tree or decompose(build_hypergraph(spec), root), pre_aggregate)
    return reduce_graph(graph) if reduce_first else graph


def multiway_aggregate(spec: GroupedJoinSpec, strategy: str = "auto", root: str | None = None, sort: bool = False, batches: int | None = None, cache_trails: bool = True, reduce_first: bool = False, pre_aggregate: bool = True) -> DataFrame:
    """The operator. `auto` weighs the exact size of the join and the estimated work of the strategies, and may hand over to a classic or a pre-aggregating plan.

    Without a given `root`, `shared_arms` and `source_batches` take the tree of least estimated work.
    """
    from multiagg.plans.cost import best_tree, choose_strategy, edge_sizes, gather, keys_joined

    tree, stats, wide, chosen = None, None, len(spec.relations) > 2, strategy == "auto"
    if strategy == "auto":
        choice = choose_strategy(spec)
        strategy, tree, batches, stats = choice.strategy, None if root else choice.tree, batches or choice.batches, choice.stats
    elif strategy in ("shared_arms", "source_batches") and root is None and wide or strategy == "per_source" and [a.kind for a in spec.aggs] == ["count"]:
        stats = gather(normalize_spec(spec))
    joined = False
    if stats and wide and root is None and pre_aggregate:
        few, stats = keys_joined(normalize_spec(spec), stats)
        joined = len(few.relations) < len(spec.relations)
        spec = few if joined else spec
    if strategy in ("shared_arms", "source_batches") and stats and tree is None and root is None:
        tree = best_tree(spec, strategy == "source_batches", stats)
    if strategy in ("traditional", "preagg_every"):
        from multiagg.operators.baselines import preaggregate, traditional

        out = traditional(spec) if strategy == "traditional" else preaggregate(spec)
        return out.orderBy(*spec.groups) if sort else out
    graph = prepared(spec, root, pre_aggregate, reduce_first, tree)
    if strategy == "per_source" or joined or not wide:
        graph.sizes, graph.joined = edge_sizes(spec, stats), joined
    if chosen and strategy == "source_batches" and not wide and in_cells(graph):
        strategy = "shared_arms"  # slices cap a state that cells don't have
    run = {"shared_arms": shared_arms, "per_source": lambda g: per_source(g, cache_trails), "source_batches": lambda g: source_batches(g, batches or 4), "packed": packed_or_shared}
    if strategy not in run:
        raise SpecError(f"no strategy {strategy}")
    return finish(graph, run[strategy](graph), sort)


def explain_multiway(spec: GroupedJoinSpec, root: str | None = None) -> str:
    """Hypergraph, tree, splits and roles in words."""
    from multiagg.plans.tree import drawn, split_attributes

    spec = normalize_spec(spec)
    h = build_hypergraph(spec)
    tree = decompose(h, root)
    lines = ["relations:"] + [f"  {n}({', '.join(sorted(a))})" for n, a in h.edges.items()] + ["tree:"] + ["  " + x for x in drawn(tree)] + ["edges:"]
    roles = classify(tree)
    for n, (left, right) in split_attributes(tree).items():
        lines.append(f"  {n}: ({', '.join(left)}) -> ({', '.join(right)})  [{', '.join(sorted(roles[n]))}]")
    return "\n".join(lines)


def enumerate_rooted_trees(spec: GroupedJoinSpec, root: str | None = None) -> DataFrame:
    """For small graphs: every choice of one edge per relation that fits together, with the tuples it stands for. The sum of `tuples` is the join's size."""
    graph = prepared(spec, root)

    def grow(n: Node) -> DataFrame:
        table = graph.edges[n.name]
        for c in n.children:
            sub = grow(c)
            keep = list(dict.fromkeys([*(x for x in table.columns if x != M), *(x for x in sub.columns if x != M)]))
            table = multiplied(graph, table, sub, list(c.up), keep)
        return table

    return grow(graph.tree).withColumnRenamed(M, "tuples")
