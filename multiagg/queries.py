"""queries() and oracle SQL of the reference's operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from multiagg.operators.baselines import preaggregate, traditional
from multiagg.operators.graph import DataGraph
from multiagg.operators.measure import scratch_dir
from multiagg.operators.multiway import finish, multiway_aggregate, prepared, shared_arms
from multiagg.plans.spec import GroupedJoinSpec
from multiagg.plans.sqlgen import plain_sql, weighted_sql
from multiagg.workloads import SHAPES, SQL_ROWS, agg_workload, registered, workload

RUNS: dict[str, Callable] = {
    "shared_arms": lambda s: multiway_aggregate(s, "shared_arms"),
    "per_source": lambda s: multiway_aggregate(s, "per_source"),
    "source_batches": lambda s: multiway_aggregate(s, "source_batches"),
    "packed": lambda s: multiway_aggregate(s, "packed"),
    "traditional": traditional,
    "traditional_merge_sort": lambda s: traditional(s, "merge", "sort"),
    "traditional_hash": lambda s: traditional(s, "shuffle_hash", "hash"),
    "traditional_broadcast": lambda s: traditional(s, "broadcast", "hash"),
    "traditional_reduced": lambda s: traditional(s, reduce=True),
    "preagg_inputs": lambda s: preaggregate(s, "inputs"),
    "preagg_every": lambda s: preaggregate(s, "every_join"),
    "preagg_every_hash": lambda s: preaggregate(s, "every_join", "shuffle_hash"),
}
#: Workloads that every strategy and baseline runs.
SMALL = ("syn_s3", "syn_c3", "syn_b3", "tpch_zip", "pairs_suppliers", "conv_roles")
#: The same for the paper's own strategies and both pre-aggregations, on branching joins.
BRANCHING = ("syn_b2", "triple_events", "chain4_groups4", "branch5_groups4", "bushy")
#: Published sets with large joins: the operator's strategies and both pre-aggregations, no classic plan.
LARGE = ("syn_s1", "syn_s2", "syn_c1", "syn_c2", "syn_b1", "twohop")
SHAPES_OF_AGG = ("self", "chain", "branch")
KINDS = ("count", "sum", "min", "max", "avg", "count_of", "count_distinct")


def _auto(name: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: multiway_aggregate(registered(name, spark, d))


def _run(name: str, how: str) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, d: RUNS[how](registered(name, spark, d))


def _reopened(spec: GroupedJoinSpec) -> DataFrame:
    """The graph kept and opened again, as for a second query."""
    graph = prepared(spec)
    spark, at = spec.relations[0].df.sparkSession, scratch_dir(spec.relations[0].df.sparkSession)
    graph.save(at)
    again = DataGraph.open(spark, at, graph.spec, graph.tree)
    return finish(again, shared_arms(again))


#: Variants that one workload shows.
VARIANTS: dict[str, Callable] = {
    "syn_s3__no_load_aggregation": lambda s: multiway_aggregate(s, "shared_arms", pre_aggregate=False),
    "syn_b3__no_load_aggregation": lambda s: multiway_aggregate(s, "per_source", pre_aggregate=False),
    "syn_b3__no_trail_cache": lambda s: multiway_aggregate(s, "per_source", cache_trails=False),
    "syn_b3__pruned": lambda s: multiway_aggregate(s, "shared_arms", reduce_first=True),
    "syn_b3__reopened": _reopened,
    "syn_c3__traditional_constrained": lambda s: traditional(s, profile="constrained"),
    "syn_c3__traditional_roomy": lambda s: traditional(s, profile="roomy"),
    "syn_b3__preagg_manual": lambda s: preaggregate(s, "every_join", order=["r3", "r4", "r2", "r1"]),
    "syn_b2__first_root": lambda s: multiway_aggregate(s, "shared_arms", root="r1"),
}


def core_queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    out = {name: _auto(name) for name in SHAPES}
    out |= {f"{name}__{how}": _run(name, how) for name in SMALL for how in RUNS}
    out |= {f"{name}__{how}": _run(name, how) for name in BRANCHING for how in ("shared_arms", "per_source", "source_batches", "preagg_inputs" if name in ("syn_b2", "triple_events") else "preagg_every", "preagg_every")}
    out |= {f"{name}__{how}": _run(name, how) for name in LARGE for how in ("shared_arms", "per_source", "preagg_inputs", "preagg_every") if (name, how) != ("twohop", "preagg_inputs")}  # which builds the whole join
    out |= {key: lambda spark, d, key=key, run=run: run(registered(key.split("__")[0], spark, d)) for key, run in VARIANTS.items()}
    for shape in SHAPES_OF_AGG:
        for kind in KINDS:
            out[f"agg_{kind}__{shape}"] = lambda spark, d, shape=shape, kind=kind: multiway_aggregate(agg_workload(shape, (kind,), spark, d), "shared_arms")
        out[f"agg_all__{shape}"] = lambda spark, d, shape=shape: multiway_aggregate(agg_workload(shape, KINDS[:6], spark, d), "per_source")
    return out


def core_oracles(n: int = SQL_ROWS) -> dict[str, str]:
    """SQL for tables with `n` rows of lineitem."""
    base = {name: (weighted_sql if big else plain_sql)(workload(name, None, "", n)) for name, (_, big) in SHAPES.items()}
    out = {key: base[key.split("__")[0]] for key in core_queries() if key.split("__")[0] in base}
    for shape in SHAPES_OF_AGG:
        for kind in KINDS:
            out[f"agg_{kind}__{shape}"] = plain_sql(agg_workload(shape, (kind,), None, "", n))
        out[f"agg_all__{shape}"] = plain_sql(agg_workload(shape, KINDS[:6], None, "", n))
    return out
