"""Connected components of a link table, by alternating stars.

Each round hangs every node's larger neighbours on the least one it sees, then its smaller ones.
Minima are combined within map tasks before they are shuffled, and written out before they are
joined back, so a node with very many links is only a skewed join, which AQE splits. Nothing is
collected but a count and a checksum per round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.llm.common import checkpointed


def _least(edges: DataFrame) -> DataFrame:
    return checkpointed(edges.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))).withColumnRenamed("u", "c")


def components(links: DataFrame, a: str, b: str) -> DataFrame:
    """(node, root) of every node that has a link, the root being the least node of its component. Null ends and self-links count for nothing."""
    pairs = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"), F.col(a).alias("p"), F.col(b).alias("q")).where("p is not null and q is not null and u <> v").select("u", "v").distinct()
    edges, before = checkpointed(pairs), None
    while True:
        both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.join(_least(both), F.col("u") == F.col("c")).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = checkpointed(large.distinct())
        small = large.join(_least(large), F.col("u") == F.col("c"))
        small = small.select(F.explode(F.array(F.struct("v", "m"), F.struct(F.col("u").alias("v"), "m"))).alias("x")).select(F.col("x.v").alias("u"), F.col("x.m").alias("v"))
        edges = checkpointed(small.where("u <> v").distinct())
        state = tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state == before:
            break
        before = state
    roots = edges.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
    return edges.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(roots)
