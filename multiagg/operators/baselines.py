"""What the operator is compared with: the classic binary plan, and partial pre-aggregation."""

from __future__ import annotations

from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.operators.graph import added, multiplied
from multiagg.operators.meet import met
from multiagg.operators.multiway import carried, finish, prepared
from multiagg.plans.cost import gather, join_order
from multiagg.plans.spec import COPY, GroupedJoinSpec, normalize_spec
from multiagg.plans.tree import Node, build_hypergraph, decompose

#: How much memory an operator may count on decides which joins and aggregates are sensible.
PROFILES = {"constrained": ("merge", "sort"), "roomy": ("shuffle_hash", "hash")}
#: Rows of a relation up to which a broadcast is asked for; the driver holds them all.
BROADCAST_ROWS = 4_000_000
#: Rows of a relation that one task may be expected to hold in a hash table.
HASHED_ROWS = 500_000


def _join_order(tree: Node) -> list[Node]:
    return list(tree.walk())


def traditional(spec: GroupedJoinSpec, join: str | None = None, agg: str = "hash", profile: str | None = None, reduce: bool = False, root: str | None = None) -> DataFrame:
    """Join relation by relation, then aggregate the join's rows.

    Of three and more relations, those whose joins make rows come last, by sketches of their columns, so that as few rows as
    possible stand between the joins. `join` is a hint: merge, shuffle_hash or broadcast; none leaves it to Spark. A relation is counted before it is
    broadcast, and a larger one than `BROADCAST_ROWS` is left to Spark as well. `agg='sort'` sorts by the group
    columns first and, while spark.sql.execution.replaceHashWithSortAgg is on, then aggregates sorted input.
    `reduce` applies semi-joins first.
    """
    if profile:
        join, agg = PROFILES[profile]
    spec = normalize_spec(spec)
    tree = decompose(build_hypergraph(spec), root)
    frames = {}
    for n in tree.walk():
        rel = spec.by_name[n.name]
        used = [m for m in rel.measures if any((n.name, m) in a.over for a in spec.aggs)]
        rows = rel.frame(list(dict.fromkeys([*n.up, *n.down, *n.group, *used])))
        frames[n.name] = rows.withColumnsRenamed({m: f"{n.name}.{m}" for m in used})
    if reduce:
        for n in reversed(_join_order(tree)):
            for c in n.children:
                frames[n.name] = frames[n.name].join(frames[c.name].select(*c.up), list(c.up), "left_semi")
        for n in _join_order(tree):
            for c in n.children:
                frames[c.name] = frames[c.name].join(frames[n.name].select(*c.up), list(c.up), "left_semi")
    order = _join_order(tree)
    stats = gather(spec) if len(order) > 2 else None
    names = join_order(tree, stats) if stats else [n.name for n in order]
    joined, attrs = frames[names[0]], {n.name: {*n.up, *n.down} for n in order}
    for i, name in enumerate(names[1:], 1):
        right = frames[name]
        hinted = join and (join != "broadcast" or right.count() <= BROADCAST_ROWS)
        on = sorted(set().union(*(attrs[x] for x in names[:i])) & attrs[name])
        if stats and join == "shuffle_hash":  # a number that is given isn't lowered, so a partition's hash table stays small
            right = right.repartition(max(int(right.sparkSession.conf.get("spark.sql.shuffle.partitions")), ceil(stats.rows[name] / HASHED_ROWS)), *on)
        joined = joined.join(right.hint(join) if hinted else right, on)
    groups = [g for n in order for g in n.group]
    if agg == "sort":
        joined = joined.repartition(*groups).sortWithinPartitions(*groups)
    made = []
    for a in spec.aggs:
        cols = [F.col(f"`{r}.{m}`") for r, m in a.over]
        x = cols[0] if cols else None
        for c in cols[1:]:
            x = x * c
        how = {"count": lambda: F.count("*"), "count_of": lambda: F.count(x), "sum": lambda: F.sum(x), "min": lambda: F.min(x), "max": lambda: F.max(x), "avg": lambda: F.avg(x.cast("double")), "count_distinct": lambda: F.count_distinct(x), "approx_distinct": lambda: F.approx_count_distinct(x)}
        made.append(how[a.kind]().alias(a.alias))
    out = joined.groupBy(*groups).agg(*made).withColumnsRenamed({g: g.removesuffix(COPY) for g in groups})
    return out.where(spec.having) if spec.having else out


def preaggregate(spec: GroupedJoinSpec, level: str = "every_join", join: str | None = None, order: list[str] | None = None, root: str | None = None) -> DataFrame:
    """Weighted relations joined one by one, top down. `inputs` aggregates only before the joins and at the end, `every_join` after each join as well.

    `order` is a list of relation names, each joining one before it.
    """
    graph = prepared(spec, root)
    nodes = {n.name: n for n in graph.tree.walk()}
    names = [n for n in order if n in nodes] if order else list(nodes)
    attrs = {n: set(graph.keys(nodes[n])) - set(nodes[n].group) - set(graph.algebra.extra_groups(n)) for n in names}
    own = {n: [*nodes[n].group, *graph.algebra.extra_groups(n)] for n in names}
    table, have, groups = graph.edges[names[0]], set(attrs[names[0]]), list(own[names[0]])
    for i, n in enumerate(names[1:], 1):
        on = sorted(have & attrs[n])
        later = set().union(*(attrs[x] for x in names[i + 1 :])) if names[i + 1 :] else set()
        have = (have | attrs[n]) & later
        groups += own[n]
        keys = [*sorted(have), *groups]
        if not join and (level == "every_join" or len(names) == 2):  # else the left side's product would be dealt anew
            table = met(graph, table, graph.edges[n], on, keys)
        else:
            table = multiplied(graph, table, graph.edges[n], on, keys, join)
            if level == "every_join":
                table = added(graph, table, keys)
    done = not join and (level == "every_join" and len(names) > 1 or len(names) == 2)
    return finish(graph, table if done else added(graph, table, carried(graph, graph.tree)))
