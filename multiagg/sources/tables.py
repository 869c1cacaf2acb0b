"""Reading and writing tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load_file(spark: SparkSession, path: str, fmt: str, schema: StructType | str, **options) -> DataFrame:
    """CSV, JSON, ORC or Parquet with a given schema: nothing is inferred, so nothing is read twice."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def load_jdbc(spark: SparkSession, url: str, query: str, partition_col: str | None = None, bounds: tuple[int, int] | None = None, partitions: int = 8, **options) -> DataFrame:
    """A partitioned JDBC read; `query` carries the projection and the pre-aggregation to the store."""
    reader = spark.read.format("jdbc").option("url", url).options(**options)
    if partition_col:
        lo, hi = bounds or (0, 1)
        return reader.option("dbtable", f"({query}) AS q").option("partitionColumn", partition_col).option("lowerBound", lo).option("upperBound", hi).option("numPartitions", partitions).load()
    return reader.option("query", query).load()


def edge_query(table: str, keys: list[str]) -> str:
    """Pre-aggregation as a query for the store."""
    return f"SELECT {', '.join(keys)}, count(*) AS m FROM {table} GROUP BY {', '.join(keys)}"


def save(df: DataFrame, path: str, fmt: str = "parquet", partition_by: list[str] | None = None, **options) -> None:
    writer = df.write.format(fmt).mode("overwrite").options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def save_bucketed(df: DataFrame, table: str, keys: list[str], buckets: int = 64) -> None:
    """A table that joins and groups by `keys` without a shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)


def force(df: DataFrame) -> None:
    """Run the plan and keep nothing."""
    df.write.format("noop").mode("overwrite").save()
