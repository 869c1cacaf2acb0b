"""Relational operators around the multiway aggregate; each is a thin, declarative use of the DataFrame API."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def relevant(df: DataFrame, attrs: list[str]) -> DataFrame:
    """Join and group attributes only; the scan reads no other column."""
    return df.select(*attrs)


def derive(df: DataFrame, **exprs: str) -> DataFrame:
    return df.withColumns({k: F.expr(e) for k, e in exprs.items()})


def copy_column(df: DataFrame, name: str, to: str) -> DataFrame:
    return df.withColumn(to, F.col(name))


def project(df: DataFrame, cols: list[str], distinct: bool = False) -> DataFrame:
    out = df.select(*cols)
    return out.distinct() if distinct else out


def where(df: DataFrame, predicate: str | Column) -> DataFrame:
    return df.where(predicate)


def hash_sample(df: DataFrame, k: int, of: int, cols: list[str] | None = None) -> DataFrame:
    """Rows whose hash falls into the first k of `of` parts: growing k gives growing samples."""
    return df.where(F.pmod(F.xxhash64(*(cols or df.columns)), F.lit(of)) < k)


def binary_join(left: DataFrame, right: DataFrame, on, how: str = "inner", method: str | None = None) -> DataFrame:
    """`method`: merge, shuffle_hash or broadcast as a hint; none leaves it to Spark."""
    return left.join(right.hint(method) if method else right, on, how)


def natural_join(left: DataFrame, right: DataFrame) -> DataFrame:
    return left.join(right, [c for c in left.columns if c in right.columns])


def self_join(df: DataFrame, on: str, group: str) -> DataFrame:
    left, right = df.select(F.col(on).alias("k"), F.col(group).alias("g1")), df.select(F.col(on).alias("k"), F.col(group).alias("g2"))
    return left.join(right, "k")


def reduce_by(left: DataFrame, right: DataFrame, on, anti: bool = False) -> DataFrame:
    return left.join(right, on, "left_anti" if anti else "left_semi")


def cross(left: DataFrame, right: DataFrame) -> DataFrame:
    return left.crossJoin(right)


def theta_join(left: DataFrame, right: DataFrame, condition: Column) -> DataFrame:
    return left.join(right, condition)


def range_join(left: DataFrame, right: DataFrame, x: str, low: str, high: str, width: int) -> DataFrame:
    """Points in [low, high]: intervals are listed under the bins they touch, so the join is on the bin."""
    points = left.withColumn("__bin", F.floor(F.col(x) / width))
    spans = right.withColumn("__bin", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return points.join(spans, "__bin").where(F.col(x).between(F.col(low), F.col(high))).drop("__bin")


def interval_join(left: DataFrame, right: DataFrame, key: str, ts: str, other_ts: str, seconds: int) -> DataFrame:
    """Rows of one key whose times are at most so far apart; the right side is listed in three bins."""
    at = lambda c: F.unix_timestamp(F.col(c).cast("timestamp"))
    l = left.withColumn("__bin", F.floor(at(ts) / seconds))
    r = right.withColumn("__bin", F.explode(F.array(*(F.floor(at(other_ts) / seconds) + i for i in (-1, 0, 1)))))
    return l.join(r, [key, "__bin"]).where(F.abs(at(ts) - at(other_ts)) <= seconds).drop("__bin")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, into: str) -> DataFrame:
    """For each left row the last value of the right side before it: one union and one window, linear in both."""
    cols = left.columns
    l = left.select(*cols, F.lit(None).cast(right.schema[value].dataType).alias(into), F.lit(0).alias("__side"))
    r = right.select(*(F.col(c) if c in (key, ts) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in cols), F.col(value).alias(into), F.lit(1).alias("__side"))
    w = Window.partitionBy(key).orderBy(ts, "__side").rowsBetween(Window.unboundedPreceding, -1)
    return l.unionByName(r).withColumn(into, F.last(into, ignorenulls=True).over(w)).where("__side = 0").drop("__side")


def null_safe_join(left: DataFrame, right: DataFrame, a: str, b: str) -> DataFrame:
    return left.join(right, F.col(a).eqNullSafe(F.col(b)))


def lateral_topk(df: DataFrame, sub: DataFrame, condition: Column, order: list[Column], k: int) -> DataFrame:
    return df.lateralJoin(sub.where(condition).orderBy(*order).limit(k))


def aggregate(df: DataFrame, keys: list[str], aggs: dict[str, Column], method: str = "hash") -> DataFrame:
    if method == "sort" and keys:
        df = df.repartition(*keys).sortWithinPartitions(*keys)
    return df.groupBy(*keys).agg(*(c.alias(k) for k, c in aggs.items()))


def two_phase(df: DataFrame, keys: list[str], salt: Column, parts: int = 8) -> DataFrame:
    """Counts with the hot keys spread over `parts` first."""
    first = df.groupBy(*keys, F.pmod(F.xxhash64(salt), F.lit(parts)).alias("__salt")).agg(F.count("*").alias("__n"))
    return first.groupBy(*keys).agg(F.sum("__n").alias("cnt"))


def weighted_count(df: DataFrame, keys: list[str], m: str) -> DataFrame:
    return df.groupBy(*keys).agg(F.sum(m).alias("cnt"))


def domain_size(df: DataFrame, cols: list[str]) -> DataFrame:
    return df.agg(F.count_distinct(*cols).alias("n_values"))


def approx_domain(df: DataFrame, col: str, rsd: float = 0.02) -> DataFrame:
    return df.agg(F.approx_count_distinct(col, rsd).alias("n_values"))


def multi_level(df: DataFrame, kind: str, keys: list[str], aggs: dict[str, Column]) -> DataFrame:
    grouped = {"rollup": df.rollup, "cube": df.cube}[kind](*keys)
    return grouped.agg(*(c.alias(k) for k, c in aggs.items()))


def rank_groups(df: DataFrame, part: list[str], order: list[Column], fn: Column, into: str = "rank") -> DataFrame:
    return df.withColumn(into, fn.over(Window.partitionBy(*part).orderBy(*order)))


def top(df: DataFrame, k: int, by: list[Column], per: list[str] | None = None, offset: int = 0) -> DataFrame:
    if per:
        return df.withColumn("__n", F.row_number().over(Window.partitionBy(*per).orderBy(*by))).where(F.col("__n") <= k).drop("__n")
    return df.orderBy(*by).offset(offset).limit(k)


def union(frames: list[DataFrame], distinct: bool = False) -> DataFrame:
    out = reduce(DataFrame.unionByName, frames)
    return out.distinct() if distinct else out


def set_op(a: DataFrame, b: DataFrame, op: str) -> DataFrame:
    return {"intersect": a.intersect, "intersect_all": a.intersectAll, "except": a.subtract, "except_all": a.exceptAll}[op](b)


def same_rows(a: DataFrame, b: DataFrame) -> DataFrame:
    """(only_here, only_there): rows that one of two results has and the other lacks."""
    b = b.select(*a.columns)
    return a.exceptAll(b).agg(F.count("*").alias("only_here")).crossJoin(b.exceptAll(a).agg(F.count("*").alias("only_there")))
