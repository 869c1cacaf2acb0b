"""Token counts of documents in flat token files without an index.

A file is ids end to end, each document closed by an end-of-document id. Its blocks are searched
for that id with vectorised compares. A block can't know which document it starts in, nor how
many ids of it stand before the block; a prefix scan over blocks tells both: the running number
of separators gives each document's number, the running place of the last separator its start.
The scan has two levels, blocks within groups and groups within files, so that no task meets more
than `GROUP` blocks of one file, or one row per group.

Defined results: ids after a file's last separator are one more document, unclosed; an empty file
or block has none. A null block counts as empty. Two separators in a row close an empty document.
A null text counts as empty, repeated rows are counted each by itself, an empty table gives no row,
and only the id and text columns are read, whatever others are called.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from multiagg.llm.byte_bpe import RANKS_FILE, codec_of
from multiagg.llm.common import checkpointed, col, read_bytes, slices, tabled, vocabulary_file

BLOCK_TOKENS = 1 << 16
GROUP = 1024
#: The first id that the vocabulary leaves free.
END_OF_DOCUMENT = 50256
ID = "<u2"


def token_files(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_tokens: int = BLOCK_TOKENS) -> DataFrame:
    """One flat file per partition, as blocks (file, block, data); rows without data name the file's documents in order (file, ordinal, doc_id)."""
    import public_tokenizers

    kind = docs.select(col(id_col)).schema[0].dataType.simpleString()
    shared, pattern = docs.sparkSession.sparkContext.broadcast(read_bytes(vocabulary_file(RANKS_FILE))), public_tokenizers.PATTERN

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec, file, block, ordinal, held = codec_of(shared.value, pattern), TaskContext.get().partitionId(), 0, 0, b""
        size = block_tokens * np.dtype(ID).itemsize
        end = np.array([END_OF_DOCUMENT], dtype=ID).tobytes()
        for part in slices(frames):
            rows = [(file, None, None, ordinal + i, doc) for i, doc in enumerate(part["doc_id"])]
            ordinal += len(part)
            held += b"".join(x for ids in codec.encode(part["text"].tolist()) for x in (ids.astype(ID).tobytes(), end))
            for at in range(0, len(held) - size + 1, size):
                rows.append((file, block, held[at : at + size], None, None))
                block += 1
            held = held[len(held) // size * size :]
            yield _typed(rows)
        if held:
            yield _typed([(file, block, held, None, None)])

    def _typed(rows: list) -> pd.DataFrame:
        return pd.DataFrame(rows, columns=["file", "block", "data", "ordinal", "doc_id"], dtype=object)

    return docs.select(col(id_col).alias("doc_id"), col(text_col).alias("text")).mapInPandas(work, f"file long, block long, data binary, ordinal long, doc_id {kind}")


def blocks_of_files(spark: SparkSession, path: str, block_bytes: int = BLOCK_TOKENS * 2) -> DataFrame:
    """Blocks of flat files that any of Spark's file systems holds, each file below 2 GB."""
    files = spark.read.format("binaryFile").load(path).select(F.xxhash64("path").alias("file"), "path", "length", "content")
    at = F.posexplode(F.expr(f"sequence(0L, greatest(length - 1, 0L) div {block_bytes})")).alias("block", "b")
    return files.select("file", "path", "content", at).select("file", "path", F.col("block").cast("long").alias("block"), F.expr(f"substring(content, cast(b * {block_bytes} + 1 as int), {block_bytes})").alias("data"))


def separators(blocks: DataFrame, end: int = END_OF_DOCUMENT, dtype: str = ID) -> DataFrame:
    """(file, block, n, places): ids in the block and the places of its separators."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            data = [np.frombuffer(d or b"", dtype) for d in frame["data"]]
            yield pd.DataFrame({"file": frame["file"], "block": frame["block"], "n": [len(d) for d in data], "places": [np.flatnonzero(d == end).astype(np.int32) for d in data]})

    return blocks.select("file", "block", "data").mapInPandas(work, "file long, block long, n long, places array<int>")


def count_tokens(blocks: DataFrame, end: int = END_OF_DOCUMENT, dtype: str = ID, group: int = GROUP) -> DataFrame:
    """(file, ordinal, start, n_tokens, closed) of each document; separators aren't counted."""
    found = tabled(separators(blocks, end, dtype), "separators").withColumn("g", F.expr(f"block div {group}"))
    # Within a group: ids, separators, and the place behind the last separator, counted from the group's start.
    inside = Window.partitionBy("file", "g").orderBy("block")
    before = inside.rowsBetween(Window.unboundedPreceding, -1)
    local = found.withColumn("at", F.sum("n").over(inside) - F.col("n")).withColumn("behind", F.col("at") + F.try_element_at("places", F.lit(-1)) + 1)
    local = local.withColumn("seen", F.coalesce(F.sum(F.size("places")).over(before), F.lit(0))).withColumn("open", F.max("behind").over(before))
    groups = checkpointed(local.groupBy("file", "g").agg(F.sum("n").alias("gn"), F.sum(F.size("places")).alias("gs"), F.max("behind").alias("gb")))
    order = Window.partitionBy("file").orderBy("g")
    past = order.rowsBetween(Window.unboundedPreceding, -1)
    groups = groups.withColumn("base", F.sum("gn").over(order) - F.col("gn")).withColumn("docs", F.sum("gs").over(order) - F.col("gs"))
    groups = groups.withColumn("start0", F.coalesce(F.max(F.col("base") + F.col("gb")).over(past), F.lit(0)))
    placed = local.join(checkpointed(groups.select("file", "g", "base", "docs", "start0")), ["file", "g"])
    each = placed.where("size(places) > 0").select("file", "base", "at", "places", (F.col("docs") + F.col("seen")).alias("first"), F.coalesce(F.col("base") + F.col("open"), F.col("start0")).alias("start1"), F.posexplode("places").alias("i", "p"))
    closed = each.select(
        "file", (F.col("first") + F.col("i")).alias("ordinal"),
        F.when(F.col("i") == 0, F.col("start1")).otherwise(F.col("base") + F.col("at") + F.try_element_at("places", F.greatest(F.col("i"), F.lit(1))) + 1).alias("start"),
        (F.col("base") + F.col("at") + F.col("p")).alias("stop"),
    ).select("file", "ordinal", "start", (F.col("stop") - F.col("start")).alias("n_tokens"), F.lit(True).alias("closed"))
    whole = groups.groupBy("file").agg(F.sum("gn").alias("n"), F.sum("gs").alias("ordinal"), F.coalesce(F.max(F.col("base") + F.col("gb")), F.lit(0)).alias("start"))
    rest = whole.where("start < n").select("file", "ordinal", "start", (F.col("n") - F.col("start")).alias("n_tokens"), F.lit(False).alias("closed"))
    return closed.unionByName(rest)


def document_counts(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_tokens, start, file, ordinal): documents written to flat files, then counted from the files alone."""
    files = tabled(token_files(docs, id_col, text_col), "files")
    counts = count_tokens(files.where("data is not null").select("file", "block", "data"))
    return files.where("data is null").select("file", "ordinal", "doc_id").join(counts, ["file", "ordinal"]).select("doc_id", "n_tokens", "start", "file", "ordinal")
