"""SQL text of a spec for other engines: the plain join, and its equal that sums weights up the tree."""

from __future__ import annotations

from multiagg.plans.spec import COPY, GroupedJoinSpec, normalize_spec
from multiagg.plans.tree import Node, build_hypergraph, decompose


def _source(rel) -> str:
    every = {**rel.attrs, **rel.measures}
    where = f" WHERE {rel.where}" if rel.where else ""
    return f"SELECT {', '.join(f'{e} AS {k}' for k, e in every.items())} FROM {rel.table}{where}"


def edges_sql(spec: GroupedJoinSpec) -> dict[str, str]:
    """The weighted edges of each relation: its attributes and the multiplicity m."""
    spec = normalize_spec(spec)
    out = {}
    for r in spec.relations:
        joins = " AND ".join(f"{a} IS NOT NULL" for a in r.attrs if a in spec.join_attrs)
        keys = ", ".join(r.attrs)
        out[r.name] = f"SELECT {keys}, CAST(count(*) AS BIGINT) AS m FROM ({_source(r)}) AS t WHERE {joins} GROUP BY {keys}"
    return out


def plain_sql(spec: GroupedJoinSpec) -> str:
    """Join everything, then group."""
    tree = decompose(build_hypergraph(spec := normalize_spec(spec)))
    order, groups = list(tree.walk()), spec.groups
    text = f"{order[0].name}"
    for n in order[1:]:
        text += f" JOIN {n.name} USING ({', '.join(n.up)})"
    made = []
    for a in spec.aggs:
        x = " * ".join(f"{r}.{m}" for r, m in a.over)
        made.append({"count": "CAST(count(*) AS BIGINT)", "count_of": f"CAST(count({x}) AS BIGINT)", "sum": f"sum({x})", "min": f"min({x})", "max": f"max({x})", "avg": f"avg(CAST({x} AS DOUBLE))", "count_distinct": f"CAST(count(DISTINCT {x}) AS BIGINT)"}[a.kind] + f" AS {a.alias}")
    ctes = ", ".join(f"{n.name} AS ({_source(spec.by_name[n.name])})" for n in order)
    columns = ", ".join(f"{g} AS {g.removesuffix(COPY)}" for g in groups)
    group_by = f" GROUP BY {', '.join(groups)}" if groups else ""
    return f"WITH {ctes} SELECT {', '.join(filter(None, [columns, *made]))} FROM {text}{group_by}"


def weighted_sql(spec: GroupedJoinSpec) -> str:
    """Counts only: each relation grouped to weights, joined with what its children have summed, leaves first."""
    tree = decompose(build_hypergraph(spec := normalize_spec(spec)))
    ctes: list[str] = []

    def below(n: Node) -> list[str]:
        groups = list(n.group)
        rel, keys = spec.by_name[n.name], list(dict.fromkeys([*n.up, *n.down, *n.group]))
        subs = [(c, below(c)) for c in n.children]
        ctes.append(f"{n.name}_e AS (SELECT {', '.join([*keys, 'count(*) AS m'])} FROM ({_source(rel)}) AS t GROUP BY {', '.join(keys)})")
        table, open_ = f"{n.name}_e", list(subs)
        columns = set(keys)
        step = 0
        while open_:
            c, g = open_.pop(0)
            groups += g
            keep = list(dict.fromkeys([*n.up, *(a for d, _ in open_ for a in d.up), *groups]))
            match = " AND ".join(f"l.{a} = r.{a}" for a in c.up)
            pick = [f"{'l' if k in columns else 'r'}.{k}" for k in keep]
            by = f" GROUP BY {', '.join(pick)}" if pick else ""
            name = f"{n.name}_{step}"
            ctes.append(f"{name} AS (SELECT {', '.join([*pick, 'CAST(sum(l.m * r.m) AS BIGINT) AS m'])} FROM {table} AS l JOIN {c.name}_s AS r ON {match}{by})")
            table, columns, step = name, set(keep), step + 1
        ctes.append(f"{n.name}_s AS (SELECT * FROM {table})")
        return groups

    groups = below(tree)
    order = spec.groups
    assert set(order) == set(groups)
    columns = ", ".join(f"{g} AS {g.removesuffix(COPY)}" for g in order)
    return f"WITH {', '.join(ctes)} SELECT {columns}, CAST(m AS BIGINT) AS {spec.aggs[0].alias} FROM {tree.name}_s"
