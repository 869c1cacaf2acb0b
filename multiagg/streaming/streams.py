"""Streams over the event table: maintained edges, windows, joins, and a maintained multiway aggregate."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from multiagg.operators.measure import scratch_dir


def event_stream(spark: SparkSession, sf_dir: str, files_per_batch: int = 1) -> DataFrame:
    """The events as a file stream; times become instants, since watermarks take no others."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", "events*.parquet").parquet(sf_dir)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def stream_edges(stream: DataFrame, keys: list[str]) -> DataFrame:
    """Running multiplicities; the state is one row per edge."""
    return stream.groupBy(*keys).agg(F.count("*").alias("m"))


def windowed(stream: DataFrame, kind: str, size: str, slide: str | None = None, gap: str | None = None, late: str = "1 hour", keys: tuple[str, ...] = ("event_type",)) -> DataFrame:
    """Counts per window: tumbling, sliding or session; later rows than the watermark are dropped."""
    w = {"tumbling": lambda: F.window("ts", size), "sliding": lambda: F.window("ts", size, slide), "session": lambda: F.session_window("ts", gap)}[kind]()
    return stream.withWatermark("ts", late).groupBy(w.alias("w"), *keys).agg(F.count("*").alias("cnt")).select(F.col("w.start").alias("start"), F.col("w.end").alias("stop"), *keys, "cnt")


def deduplicated(stream: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def stream_join(left: DataFrame, right: DataFrame, key: str, within: str, late: str = "2 hours") -> DataFrame:
    """Right rows of the key that follow a left row within an interval."""
    l = left.withWatermark("ts", late).select(F.col(key).alias("lk"), F.col("ts").alias("lt"), F.col("event_id").alias("left_id"))
    r = right.withWatermark("ts", late).select(F.col(key).alias("rk"), F.col("ts").alias("rt"), F.col("event_id").alias("right_id"))
    return l.join(r, F.expr(f"lk = rk AND rt >= lt AND rt <= lt + INTERVAL {within}"))


def with_static(stream: DataFrame, static: DataFrame, condition) -> DataFrame:
    return stream.join(static, condition)


def user_state(stream: DataFrame, key: str = "user_id") -> DataFrame:
    """Events and greatest value per user so far, as custom state."""

    def step(k: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        n, most = state.get if state.exists else (0, float("-inf"))
        for f in frames:
            n, most = n + len(f), max(most, float(f["value"].max()))
        state.update((n, most))
        yield pd.DataFrame({key: [k[0]], "n": [n], "most": [most]})

    return stream.groupBy(key).applyInPandasWithState(step, f"{key} long, n long, most double", "n long, most double", "update", "NoTimeout")


def run_to_table(df: DataFrame, name: str, mode: str = "complete", keys: tuple[str, ...] = ()) -> DataFrame:
    """Run over all that is there now, into Parquet files in the shared folder, and read them.

    Of `complete` results the last one stands; of `update` ones the latest row of each of `keys`.
    Batches are written under their number, so one that is run again replaces what it had written.
    """
    spark = df.sparkSession
    at, seen = scratch_dir(spark), []
    out, writer = f"{at}/{name}", df.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/progress").trigger(availableNow=True)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/batch={number % 2 if mode == 'complete' else number}")
        seen.append(number)

    query = writer.format("parquet").start(out) if mode == "append" else writer.foreachBatch(keep).start()
    query.awaitTermination()
    if mode == "append":
        return spark.read.schema(df.schema).parquet(out)
    if not seen:
        return spark.createDataFrame([], df.schema)
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{out}/batch={seen[-1] % 2}")
    rows = spark.read.schema(StructType([*df.schema.fields, StructField("batch", LongType())])).parquet(out)
    latest = rows.groupBy(*keys).agg(F.max_by(F.struct(*df.columns), "batch").alias("row"))
    return latest.select("row.*")


class MaintainedPairs:
    """Counts of pairs (g, g') that meet on a join value, kept up to date from micro-batches.

    Counts are linear in each side, so a batch with edges D on top of state E adds E*D + D*E + D*D.
    State and result are written per batch under its number: a batch that is run again replaces
    what it had written, so each counts once. Every few batches what came before is merged, so that
    a batch reads one merged state and a bounded number of others.
    """

    def __init__(self, spark: SparkSession, path: str, on: str, group: str, every: int = 16):
        self.spark, self.path, self.on, self.group, self.every = spark, path, on, group, every

    def _folders(self, what: str, label: str) -> dict[int, object]:
        """Finished folders `what/label=n` by n."""
        sc = self.spark.sparkContext
        found = sc._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{what}/{label}=*/_SUCCESS")
        fs = found.getFileSystem(sc._jsc.hadoopConfiguration())
        return {int(s.getPath().getParent().getName().split("=")[1]): (fs, s.getPath().getParent()) for s in fs.globStatus(found) or []}

    def _state(self, what: str, before: int | None = None) -> DataFrame | None:
        """What has been merged last, and the batches since."""
        bases = [n for n in self._folders(what + "_merged", "upto") if before is None or n <= before]
        base = max(bases, default=0)
        paths = [f"{self.path}/{what}_merged/upto={base}"] if bases else []
        paths += [f"{self.path}/{what}/batch={n}" for n in sorted(self._folders(what, "batch")) if n >= base and (before is None or n < before)]
        return self.spark.read.parquet(*paths) if paths else None

    def _merge(self, number: int) -> None:
        """Add up all before this batch, then drop what went into the sum."""
        for what, keys, value in (("edges", ("k", "g"), "m"), ("pairs", ("g1", "g2"), "c")):
            state = self._state(what, number)
            if state is not None and number not in self._folders(what + "_merged", "upto"):
                state.groupBy(*keys).agg(F.sum(value).alias(value)).write.mode("overwrite").parquet(f"{self.path}/{what}_merged/upto={number}")
        for what in ("edges", "pairs"):
            for label, folder in (("batch", what), ("upto", what + "_merged")):
                for n, (fs, path) in self._folders(folder, label).items():
                    if n < number:
                        fs.delete(path, True)

    def apply(self, batch: DataFrame, number: int) -> None:
        if number and number % self.every == 0:
            self._merge(number)
        delta = batch.groupBy(F.col(self.on).alias("k"), F.col(self.group).alias("g")).agg(F.count("*").alias("m")).persist()
        pair = lambda a, b: a.join(b.select("k", F.col("g").alias("g2"), F.col("m").alias("m2")), "k").select(F.col("g").alias("g1"), "g2", (F.col("m") * F.col("m2")).alias("c"))
        made = pair(delta, delta)
        state = self._state("edges", number)
        if state is not None:
            old = state.groupBy("k", "g").agg(F.sum("m").alias("m"))
            made = made.unionByName(pair(old, delta)).unionByName(pair(delta, old))
        made.groupBy("g1", "g2").agg(F.sum("c").alias("c")).write.mode("overwrite").parquet(f"{self.path}/pairs/batch={number}")
        delta.write.mode("overwrite").parquet(f"{self.path}/edges/batch={number}")
        delta.unpersist()

    def run(self, stream: DataFrame, checkpoint: str) -> DataFrame:
        query = stream.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        query.awaitTermination()
        return self.result()

    def result(self) -> DataFrame:
        return self._state("pairs").groupBy("g1", "g2").agg(F.sum("c").alias("cnt"))
