"""Python functions, for users who extend the engine; the engine's own hot paths use none of them but the packed walk."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def zip_of(customer: DataFrame) -> DataFrame:
    """A derived zip by a vectorised scalar function."""
    made = F.pandas_udf(lambda k: k % 997, "long")
    return customer.select("c_custkey", made("c_custkey").alias("zip"))


def sum_product(df: DataFrame, key: str, a: str, b: str) -> DataFrame:
    """A weighted sum as a grouped-aggregate function; the built-in sum does the same without Python and is preferred."""

    def total(x: pd.Series, y: pd.Series) -> int:
        return int((x * y).sum())

    return df.groupBy(key).agg(F.pandas_udf(total, "long")(a, b).alias("total"))


def walk_source(edges: DataFrame, source: str, target: str, m: str, hop: dict) -> DataFrame:
    """One hop from every source through a broadcast neighbour list, in Arrow batches: (source, target, count)."""
    shared = edges.sparkSession.sparkContext.broadcast(hop)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: dict = {}
            for s, t, w in zip(batch[source].to_pylist(), batch[target].to_pylist(), batch[m].to_pylist()):
                for g, c in shared.value.get(t, ()):
                    out[s, g] = out.get((s, g), 0) + w * c
            yield pa.RecordBatch.from_pydict({"source": [k[0] for k in out], "target": [k[1] for k in out], "cnt": list(out.values())}, schema=pa.schema([("source", pa.int64()), ("target", pa.string()), ("cnt", pa.int64())]))

    return edges.select(source, target, m).mapInArrow(work, "source long, target string, cnt long").groupBy("source", "target").agg(F.sum("cnt").alias("cnt"))


def cogroup_combine(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """Two entry lists (key, g, c) combined per key."""

    def combine(l: pd.DataFrame, r: pd.DataFrame) -> pd.DataFrame:
        both = l.merge(r, on=key, suffixes=("1", "2"))
        both["cnt"] = both["c1"] * both["c2"]
        return both[[key, "g1", "g2", "cnt"]]

    kinds = {n: t for n, t in [*left.dtypes, *right.dtypes]}
    return left.groupBy(key).cogroup(right.groupBy(key)).applyInPandas(combine, f"{key} {kinds[key]}, g1 {dict(left.dtypes)['g']}, g2 {dict(right.dtypes)['g']}, cnt long")


def tree_function(spark):
    """A table function that emits the trees of one source: choices of one value per arm, with their count. Returned for registration or use in SQL."""

    class Trees:
        def eval(self, first: list, second: list):
            for a in first or []:
                for b in second or []:
                    yield a["g"], b["g"], a["c"] * b["c"]

    return F.udtf(Trees, returnType="g1 string, g2 string, cnt long")
