"""The data graph: one pre-aggregated, weighted edge table per relation."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from multiagg.operators.algebra import M, Algebra
from multiagg.plans.spec import GroupedJoinSpec
from multiagg.plans.tree import Node

OTHER = "__r"


@dataclass
class DataGraph:
    spec: GroupedJoinSpec
    tree: Node
    algebra: Algebra
    edges: dict[str, DataFrame]
    #: Sizes that are expected of the edge tables, where they have been asked for.
    sizes: dict | None = None
    #: Whether relations with a key have been joined to the others before.
    joined: bool = False

    def keys(self, n: Node) -> list[str]:
        """Columns of a relation's edge table that are no annotations."""
        return list(dict.fromkeys([*n.up, *n.down, *n.group, *self.algebra.extra_groups(n.name)]))

    def nodes(self) -> DataFrame:
        """(relation, side, node) of the graph: distinct left and right values as structs written in JSON."""
        from multiagg.plans.tree import split_attributes

        sides = split_attributes(self.tree)
        made = [
            self.edges[name].select(F.lit(name).alias("relation"), F.lit(side).alias("side"), F.to_json(F.struct(*cols)).alias("node")).distinct()
            for name, pair in sides.items() for side, cols in zip(("left", "right"), pair) if cols
        ]
        return reduce(DataFrame.unionByName, made)

    def degrees(self) -> DataFrame:
        """(relation, node, out_degree, weight) of left nodes."""
        from multiagg.plans.tree import split_attributes

        made = [
            self.edges[name].groupBy(F.to_json(F.struct(*left)).alias("node")).agg(F.count("*").alias("out_degree"), F.sum(M).alias("weight")).select(F.lit(name).alias("relation"), "node", "out_degree", "weight")
            for name, (left, _) in split_attributes(self.tree).items() if left
        ]
        return reduce(DataFrame.unionByName, made)

    def stats(self) -> DataFrame:
        """(relation, edges, tuples)."""
        made = [df.agg(F.count("*").alias("n_edges"), F.sum(M).alias("n_tuples")).select(F.lit(name).alias("relation"), "n_edges", "n_tuples") for name, df in self.edges.items()]
        return reduce(DataFrame.unionByName, made)

    def save(self, path: str, bucket_by: dict[str, list[str]] | None = None, buckets: int = 64) -> None:
        """Keep the edge tables for later queries: Parquet under `path`, or tables `path_relation` in buckets by the given columns."""
        for name, df in self.edges.items():
            if bucket_by and name in bucket_by:
                df.write.mode("overwrite").bucketBy(buckets, *bucket_by[name]).sortBy(*bucket_by[name]).saveAsTable(f"{path}_{name}")
            else:
                df.write.mode("overwrite").parquet(f"{path}/{name}")

    @staticmethod
    def open(spark: SparkSession, path: str, spec: GroupedJoinSpec, tree: Node, tables: bool = False) -> DataGraph:
        edges = {n.name: spark.table(f"{path}_{n.name}") if tables else spark.read.parquet(f"{path}/{n.name}") for n in tree.walk()}
        return DataGraph(spec, tree, Algebra(spec), edges)


def load_graph(spec: GroupedJoinSpec, tree: Node, pre_aggregate: bool = True) -> DataGraph:
    """One scan per relation: relevant columns, rows with all join values, grouped to weighted edges.

    Without `pre_aggregate` every row is an edge of weight 1.
    """
    algebra, edges = Algebra(spec), {}
    graph = DataGraph(spec, tree, algebra, edges)
    for n in tree.walk():
        rel = spec.by_name[n.name]
        keys = graph.keys(n)
        measures = [m for m in rel.measures if any((n.name, m) in a.over for a in spec.aggs)]
        rows = rel.frame([k for k in dict.fromkeys([*keys, *measures])]).dropna(subset=sorted({*n.up, *n.down})) if n.up or n.down else rel.frame(list(dict.fromkeys([*keys, *measures])))
        if pre_aggregate and not rel.loose:
            edges[n.name] = rows.groupBy(*keys).agg(*(c.alias(k) for k, c in algebra.load(n.name).items())) if algebra.load(n.name) else rows.select(*keys).distinct()
        else:
            edges[n.name] = rows.select(*keys, *(c.alias(k) for k, c in algebra.single(n.name).items()))
    return fold_ears(graph, pre_aggregate)


def multiplied(graph: DataGraph, left: DataFrame, right: DataFrame, on: list[str], keep: list[str], how: str | None = None, by_value: tuple[str, ...] = ()) -> DataFrame:
    """Join two annotated tables, multiply their annotations, and keep the given columns of either.

    `on` are join attributes, never null; `by_value` are group columns that must agree, where null equals null.
    """
    a = graph.algebra
    l, r = a.have(left.columns), a.have(right.columns)
    both = [*on, *by_value]
    right = right.withColumnsRenamed({c: c + OTHER for c in [*r, *both]})
    match = [F.col(c) == F.col(c + OTHER) for c in on] + [F.col(c).eqNullSafe(F.col(c + OTHER)) for c in by_value]
    joined = left.join(right.hint(how) if how else right, match) if match else left.crossJoin(right)
    return joined.select(*keep, *(c.alias(k) for k, c in a.times(l, r, OTHER).items()))


def added(graph: DataGraph, table: DataFrame, keys: list[str]) -> DataFrame:
    """Rows that agree in `keys` fall together."""
    plus = graph.algebra.plus(graph.algebra.have(table.columns))
    return table.groupBy(*keys).agg(*(c.alias(k) for k, c in plus.items())) if plus else table.select(*keys).distinct()


def fold_ears(graph: DataGraph, pre_aggregate: bool = True) -> DataGraph:
    """Leaves without a group attribute only multiply: each goes into its parent's edges."""

    def fold(n: Node) -> None:
        for c in list(n.children):
            fold(c)
            if not c.children and not graph.keys(Node(c.name, (), c.group)):
                ear = graph.edges.pop(c.name)
                n.children.remove(c)
                columns = [k for k in graph.edges[n.name].columns if k not in graph.algebra.have(graph.edges[n.name].columns)]
                table = multiplied(graph, graph.edges[n.name], ear, list(c.up), columns)
                alone = pre_aggregate and set(columns) == set(graph.keys(n))  # an edge meets one row of the ear at most
                graph.edges[n.name] = table if alone else added(graph, table, graph.keys(n))

    fold(graph.tree)
    return graph


def reduce_graph(graph: DataGraph) -> DataGraph:
    """Full semi-join reduction, up and then down the tree: what is left takes part in a result row."""
    edges = dict(graph.edges)

    def up(n: Node) -> None:
        for c in n.children:
            up(c)
            edges[n.name] = edges[n.name].join(edges[c.name].select(*c.up), list(c.up), "left_semi")

    def down(n: Node) -> None:
        for c in n.children:
            edges[c.name] = edges[c.name].join(edges[n.name].select(*c.up), list(c.up), "left_semi")
            down(c)

    up(graph.tree)
    down(graph.tree)
    return DataGraph(graph.spec, graph.tree, graph.algebra, edges)
