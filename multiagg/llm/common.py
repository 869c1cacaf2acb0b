"""Helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def col(name: str) -> Column:
    """A column by its exact name, dots and backticks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def fresh(df: DataFrame, stem: str) -> str:
    """A column name that `df` does not have, whatever the case of its letters."""
    have, name = {c.lower() for c in df.columns}, stem
    while name.lower() in have:
        name += "_"
    return name


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own only where none is set and all runs on one machine."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="multiagg-"))
    return sc._jsc.sc().getCheckpointDir().get()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint; for narrow tables."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def tabled(df: DataFrame, stem: str) -> DataFrame:
    """Cut the lineage with a compressed table in the shared folder; for wide tables."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{stem}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    atexit.register(_delete, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def _delete(spark: SparkSession, path: str) -> None:
    sc = spark.sparkContext
    if sc._jsc is None or sc._jsc.sc().isStopped():
        return
    where = sc._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)


def vocabulary_file(name: str) -> str:
    """Where the public vocabulary file lies on the driver, which broadcasts its bytes."""
    import public_tokenizers

    return public_tokenizers.path(name)


def read_bytes(path: str) -> bytes:
    with open(path, "rb") as f:
        return f.read()


def bitmap(values: DataFrame, name: str, bits: int) -> np.ndarray:
    """One bit for each value of a long column modulo `bits`; so many bits reach the driver at most, however many values there are."""
    words = values.select(F.pmod(name, F.lit(bits)).alias("b")).select(F.expr("b div 64").alias("w"), F.expr("shiftleft(1L, cast(b % 64 as int))").alias("v")).groupBy("w").agg(F.bit_or("v").alias("v"))
    out = np.zeros(bits // 64, dtype=np.int64)
    found = words.toArrow()
    out[found["w"].to_numpy()] = found["v"].to_numpy()
    return out


def bits_for(count: int) -> int:
    """Bits for a bitmap of so many values: eight each, between 128 KB and 32 MB in all. Beyond that it lets more through, which its users stand."""
    return 1 << min(max((8 * count).bit_length(), 20), 28)


def in_bitmap(values: np.ndarray, words: np.ndarray) -> np.ndarray:
    b = np.mod(values, len(words) * 64)
    return (words[b // 64] >> (b % 64)) & 1 == 1


def give_back() -> None:
    """Return this process's free memory to the system, which a worker that waits for its next task would keep."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        pass  # another C library


def slices(frames: Iterator[pd.DataFrame], rows: int = 1024) -> Iterator[pd.DataFrame]:
    """The frames cut into such of at most so many rows, which bounds what is made of one."""
    for frame in frames:
        for k in range(0, len(frame), rows):
            yield frame.iloc[k : k + rows]
    frame = None
    give_back()


@contextmanager
def batches_of(spark: SparkSession, rows: int) -> Iterator[None]:
    """What is planned within hands so many rows at a time to Python; each task holds a batch in the JVM and twice in its worker."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(rows))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def powers(n: int, base: int) -> np.ndarray:
    """1, base, base**2, ... modulo 2**64."""
    with np.errstate(over="ignore"):
        return np.concatenate([np.ones(1, np.uint64), np.cumprod(np.full(n - 1, base, dtype=np.uint64))]) if n > 1 else np.ones(n, np.uint64)


def distinct(values: np.ndarray) -> np.ndarray:
    """Sorted distinct values, by a sort."""
    values = np.sort(values)
    return values[np.concatenate([[True], values[1:] != values[:-1]])] if len(values) else values


def runs(lengths: np.ndarray) -> np.ndarray:
    """0..n-1 for each n of `lengths`, end to end."""
    total = int(lengths.sum())
    return np.arange(total) - np.repeat(np.cumsum(lengths) - lengths, lengths)
