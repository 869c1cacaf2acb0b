"""What is asked: relations, natural equi-joins between them, group attributes and aggregates."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

COPY = "__own"


@dataclass(frozen=True)
class Rel:
    """One relation. `attrs` maps attribute names of the query to SQL expressions over `df`; relations join on the names they share.

    `group` names the attributes that the result is grouped by (several count as one packed value),
    `measures` the inputs of aggregates, `where` a condition on `df`. `table` is for generated SQL only.
    """

    name: str
    df: DataFrame | None
    attrs: dict[str, str]
    group: tuple[str, ...] = ()
    measures: dict[str, str] = field(default_factory=dict)
    where: str | None = None
    table: str | None = None
    #: Rows stand for themselves at load, as they are not expected to fall together.
    loose: bool = False

    def frame(self, keep: list[str]) -> DataFrame:
        """The relation's relevant columns; the filter and the pruning stand right above the scan."""
        rows = self.df.where(self.where) if self.where else self.df
        every = {**self.attrs, **self.measures}
        return rows.select(*(F.expr(every[k]).alias(k) for k in keep))


@dataclass(frozen=True)
class Agg:
    """One aggregate: kind, name in the result, and the (relation, measure) pairs that it reads."""

    kind: str
    alias: str
    over: tuple[tuple[str, str], ...] = ()

    @staticmethod
    def count(alias: str = "cnt") -> Agg:
        return Agg("count", alias)

    @staticmethod
    def count_of(rel: str, measure: str, alias: str) -> Agg:
        return Agg("count_of", alias, ((rel, measure),))

    @staticmethod
    def sum(rel: str, measure: str, alias: str = "total") -> Agg:
        return Agg("sum", alias, ((rel, measure),))

    @staticmethod
    def sum_product(*over: tuple[str, str], alias: str = "total") -> Agg:
        return Agg("sum", alias, tuple(over))

    @staticmethod
    def min(rel: str, measure: str, alias: str = "least") -> Agg:
        return Agg("min", alias, ((rel, measure),))

    @staticmethod
    def max(rel: str, measure: str, alias: str = "most") -> Agg:
        return Agg("max", alias, ((rel, measure),))

    @staticmethod
    def avg(rel: str, measure: str, alias: str = "mean") -> Agg:
        return Agg("avg", alias, ((rel, measure),))

    @staticmethod
    def count_distinct(rel: str, measure: str, alias: str = "different") -> Agg:
        return Agg("count_distinct", alias, ((rel, measure),))

    @staticmethod
    def approx_distinct(rel: str, measure: str, alias: str = "different") -> Agg:
        return Agg("approx_distinct", alias, ((rel, measure),))


@dataclass(frozen=True)
class GroupedJoinSpec:
    relations: tuple[Rel, ...]
    aggs: tuple[Agg, ...] = (Agg.count(),)
    having: str | None = None
    count_type: str = "long"

    @property
    def by_name(self) -> dict[str, Rel]:
        return {r.name: r for r in self.relations}

    @property
    def groups(self) -> list[str]:
        return [g for r in self.relations for g in r.group]

    @property
    def join_attrs(self) -> set[str]:
        seen: dict[str, int] = {}
        for r in self.relations:
            for a in r.attrs:
                seen[a] = seen.get(a, 0) + 1
        return {a for a, n in seen.items() if n > 1}


class SpecError(ValueError):
    """The spec can't be run as asked."""


def normalize_spec(spec: GroupedJoinSpec) -> GroupedJoinSpec:
    """The same query with each group attribute private to its relation: one that joins as well gets a copy.

    Attributes that neither join nor group are dropped. Checks names and, where frames are given, that both sides of a join have one type (integers are widened).
    """
    names = [r.name for r in spec.relations]
    if len(set(names)) < len(names):
        raise SpecError(f"relation names repeat: {names}")
    joins, owner = spec.join_attrs, {}
    for r in spec.relations:
        for g in r.group:
            if g not in r.attrs:
                raise SpecError(f"{r.name} has no attribute {g}")
            if g in owner:
                raise SpecError(f"group attribute {g} is given by {owner[g]} and {r.name}")
            owner[g] = r.name
    out = []
    for r in spec.relations:
        attrs = {a: e for a, e in r.attrs.items() if a in joins}
        group = []
        for g in r.group:
            own = g + COPY if g in joins else g
            attrs[own] = r.attrs[g]
            group.append(own)
        out.append(replace(r, attrs=attrs, group=tuple(group)))
    for a in spec.aggs:
        for rel, m in a.over:
            if m not in spec.by_name[rel].measures:
                raise SpecError(f"{rel} has no measure {m}")
    made = replace(spec, relations=tuple(out))
    return _widened(made) if all(r.df is not None for r in made.relations) else made


def _widened(spec: GroupedJoinSpec) -> GroupedJoinSpec:
    whole = {"tinyint", "smallint", "int", "bigint"}
    kinds: dict[str, set[str]] = {}
    for r in spec.relations:
        for name, kind in r.frame(list(r.attrs)).dtypes:
            if name in spec.join_attrs:
                kinds.setdefault(name, set()).add(kind)
    mixed = {a for a, k in kinds.items() if len(k) > 1}
    for a in mixed:
        if not kinds[a] <= whole:
            raise SpecError(f"the sides of {a} have types {sorted(kinds[a])}")
    return replace(spec, relations=tuple(replace(r, attrs={a: f"CAST({e} AS BIGINT)" if a in mixed else e for a, e in r.attrs.items()}) for r in spec.relations))
