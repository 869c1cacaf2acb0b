"""What a run costs: time, memory, garbage collection, rows between operators."""

from __future__ import annotations

import atexit
import tempfile
import time
import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from multiagg.plans.spec import GroupedJoinSpec


def scratch_dir(spark: SparkSession) -> str:
    """A new folder that driver and executors share; a local one only where no checkpoint folder is set and all runs on one machine."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="multiagg-"))
    path = f"{sc._jsc.sc().getCheckpointDir().get()}/scratch-{uuid.uuid4().hex}"
    atexit.register(_drop, spark, path)
    return path


def _drop(spark: SparkSession, path: str) -> None:
    sc = spark.sparkContext
    if sc._jsc is not None and not sc._jsc.sc().isStopped():
        where = sc._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)


@dataclass
class Cost:
    seconds: float
    rows: int
    gc_ms: int
    peak_bytes: int
    operator_peak_bytes: int
    most_rows_between: int


def _gc_ms(spark: SparkSession) -> int:
    beans = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans()
    return sum(max(0, b.getCollectionTime()) for b in beans)


def _pools(spark: SparkSession) -> list:
    return list(spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans())


def plan_nodes(df: DataFrame) -> list:
    """Operators of the plan that ran, through adaptive stages."""
    out, todo = [], [df._jdf.queryExecution().executedPlan()]
    while todo:
        p = todo.pop()
        name = p.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            todo.append(p.executedPlan())
            continue
        if name.endswith("QueryStageExec"):
            todo.append(p.plan())
            continue
        out.append((name, p))
        kids = p.children()
        todo += [kids.apply(i) for i in range(kids.size())]
    return out


def plan_metric(df: DataFrame, metric: str, kinds: tuple[str, ...] = ()) -> int:
    """The greatest value of a metric over the operators whose name contains one of `kinds`."""
    most = 0
    for name, p in plan_nodes(df):
        if not kinds or any(k in name for k in kinds):
            found = p.metrics().get(metric)
            if found.isDefined():
                most = max(most, int(found.get().value()))
    return most


def max_intermediate(df: DataFrame) -> int:
    """Rows of the largest join output in the plan that `df` has run."""
    return plan_metric(df, "numOutputRows", ("Join",))


def measure(df: DataFrame) -> Cost:
    """Run `df` to its end and keep nothing. Memory is the JVM's, so in local mode the whole engine's."""
    spark = df.sparkSession
    for p in _pools(spark):
        p.resetPeakUsage()
    gc, at = _gc_ms(spark), time.perf_counter()
    collected = df.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64(*df.columns)).alias("h"))  # the hash needs every column
    rows = collected.collect()[0][0]  # first() would run a plan of its own, which metrics are not read from
    took = time.perf_counter() - at
    peak = sum(p.getPeakUsage().getUsed() for p in _pools(spark) if "HEAP" in str(p.getType()).upper())
    return Cost(took, rows, _gc_ms(spark) - gc, int(peak), plan_metric(collected, "peakMemory"), max_intermediate(collected))


def compare(spec: GroupedJoinSpec, strategies: tuple[str, ...]) -> DataFrame:
    """(strategy, seconds, gc_ms, peak_mb, rows, most_rows_between, speed_up): each against the last one."""
    from multiagg.queries import RUNS

    spark = spec.relations[0].df.sparkSession
    costs = {s: measure(RUNS[s](spec)) for s in strategies}
    last = costs[strategies[-1]].seconds
    rows = [(s, round(c.seconds, 3), c.gc_ms, round(c.peak_bytes / 2**20, 1), c.rows, c.most_rows_between, round(last / c.seconds, 3)) for s, c in costs.items()]
    return spark.createDataFrame(rows, "strategy string, seconds double, gc_ms long, peak_mb double, rows long, most_rows_between long, speed_up double")


def load_and_compute(spec: GroupedJoinSpec) -> tuple[float, Cost]:
    """Seconds until the edge tables are stored, and the cost of the operator on the stored ones."""
    from multiagg.operators.graph import DataGraph
    from multiagg.operators.multiway import finish, prepared, shared_arms
    from multiagg.plans.cost import best_tree

    spark = spec.relations[0].df.sparkSession
    at, path = time.perf_counter(), scratch_dir(spark)
    graph = prepared(spec, tree=best_tree(spec))
    graph.save(path)
    took = time.perf_counter() - at
    graph = DataGraph.open(spark, path, graph.spec, graph.tree)
    return took, measure(finish(graph, shared_arms(graph)))


def growth(specs: dict[str, GroupedJoinSpec], baselines: tuple[str, ...] = ("preagg_every",)) -> DataFrame:
    """(sample, strategy, seconds, load_seconds, gc_ms, seconds_without_gc, peak_mb, operator_peak_mb, rows, most_rows_between) for growing samples.

    The operator's seconds are those of computing; baselines load as they run.
    """
    from multiagg.queries import RUNS

    rows = []
    for name, spec in specs.items():
        load, cost = load_and_compute(spec)
        for how, loaded, c in [("operator", load, cost), *((b, 0.0, measure(RUNS[b](spec))) for b in baselines)]:
            rows.append((name, how, round(c.seconds, 3), round(loaded, 3), c.gc_ms, round(c.seconds - c.gc_ms / 1000, 3), round(c.peak_bytes / 2**20, 1), round(c.operator_peak_bytes / 2**20, 1), c.rows, c.most_rows_between))
    spark = next(iter(specs.values())).relations[0].df.sparkSession
    kinds = "sample string, strategy string, seconds double, load_seconds double, gc_ms long, seconds_without_gc double, peak_mb double, operator_peak_mb double, rows long, most_rows_between long"
    return spark.createDataFrame(rows, kinds)


def group_size(spec: GroupedJoinSpec, result: DataFrame, count: str = "cnt") -> DataFrame:
    """(join_rows, n_groups, mean_size) of a counted result."""
    return result.agg(F.sum(count).alias("join_rows"), F.count("*").alias("n_groups")).withColumn("mean_size", F.round(F.col("join_rows") / F.col("n_groups"), 3))


def trail_stats(trails: DataFrame, source: list[str]) -> DataFrame:
    """(n_trails, most_per_source) of a trail or entry table."""
    return trails.groupBy(*source).agg(F.count("*").alias("n")).agg(F.sum("n").alias("n_trails"), F.max("n").alias("most_per_source"))
