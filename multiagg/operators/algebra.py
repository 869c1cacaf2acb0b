"""Annotations of edges and how they combine.

Every table carries one column per annotation: `m` counts tuples; a sum-like annotation is present
where one of its relations lies below. Side by side, sum-like annotations multiply, and where one
is missing the count stands in; so a sum is multiplied by the count of the rest of the tree.
A least or greatest value is present on one side only and is carried over.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from multiagg.plans.spec import Agg, GroupedJoinSpec

M = "__m"


class Algebra:
    def __init__(self, spec: GroupedJoinSpec):
        self.spec, self.count_type = spec, spec.count_type
        #: annotation -> (kind, {relation: measure}); kinds: sum, present (counts non-null), min, max
        self.parts: dict[str, tuple[str, dict[str, str]]] = {}
        self.of: dict[str, dict[str, str]] = {}
        self.distinct = [a for a in spec.aggs if a.kind in ("count_distinct", "approx_distinct")]
        for i, a in enumerate(spec.aggs):
            kinds = {"sum": ["sum"], "avg": ["sum", "present"], "count_of": ["present"], "min": ["min"], "max": ["max"]}.get(a.kind, [])
            self.of[a.alias] = {k: f"__{k}{i}" for k in kinds}
            for k in kinds:
                self.parts[f"__{k}{i}"] = (k, dict(a.over))
        #: least and greatest values alone need no counts
        self.counts = any(a.kind not in ("min", "max") for a in spec.aggs) or not spec.aggs

    def extra_groups(self, rel: str) -> list[str]:
        """Measures that are grouped by first, for distinct counts."""
        return list(dict.fromkeys(m for a in self.distinct for r, m in a.over if r == rel))

    def load(self, rel: str) -> dict[str, Column]:
        """Annotations of a relation's rows when they are grouped into edges."""
        out = {M: F.count("*").cast(self.count_type)} if self.counts else {}
        for name, (kind, over) in self.parts.items():
            if rel in over:
                x = F.col(over[rel])
                out[name] = {"sum": F.sum(x), "present": F.count(x).cast(self.count_type), "min": F.min(x), "max": F.max(x)}[kind]
        return out

    def single(self, rel: str) -> dict[str, Column]:
        """Annotations of one row, without grouping."""
        out = {M: F.lit(1).cast(self.count_type)} if self.counts else {}
        for name, (kind, over) in self.parts.items():
            if rel in over:
                x = F.col(over[rel])
                out[name] = F.when(x.isNotNull(), 1).otherwise(0).cast(self.count_type) if kind == "present" else x
        return out

    def times(self, left: set[str], right: set[str], other: str) -> dict[str, Column]:
        """Annotations of a joined row; the right side's columns bear the suffix `other`. A side without a count stands for one tuple."""
        weights = [c for c, side in ((F.col(M), left), (F.col(M + other), right)) if M in side]
        out = {M: weights[0] * weights[1] if len(weights) == 2 else weights[0]} if weights else {}
        for name, (kind, _) in self.parts.items():
            here, there = name in left, name in right
            if not (here or there):
                continue
            if kind in ("min", "max"):
                out[name] = F.col(name if here else name + other)
            else:
                sides = [F.col(name) if here else F.col(M) if M in left else None, F.col(name + other) if there else F.col(M + other) if M in right else None]
                sides = [x for x in sides if x is not None]
                out[name] = sides[0] * sides[1] if len(sides) == 2 else sides[0]
        return out

    def plus(self, have: set[str]) -> dict[str, Column]:
        """Annotations of rows that fall together."""
        out = {}
        for name in have:
            kind = "sum" if name == M else self.parts[name][0]
            out[name] = F.min(name) if kind == "min" else F.max(name) if kind == "max" else F.sum(name)
            if name == M and self.count_type != "long":
                out[name] = out[name].cast(self.count_type)
        return out

    def have(self, columns: list[str]) -> set[str]:
        return {c for c in columns if c == M or c in self.parts}

    def final(self, have: set[str]) -> list[Column]:
        out = []
        for a in self.spec.aggs:
            parts = self.of[a.alias]
            if a.kind == "count":
                out.append(F.col(M).alias(a.alias))
            elif a.kind == "count_of":
                out.append(F.col(parts["present"]).alias(a.alias))
            elif a.kind == "avg":
                out.append(F.try_divide(F.col(parts["sum"]).cast("double"), F.col(parts["present"]).cast("double")).alias(a.alias))
            elif a.kind in ("sum", "min", "max"):
                out.append(F.col(parts[a.kind]).alias(a.alias))
        return out
