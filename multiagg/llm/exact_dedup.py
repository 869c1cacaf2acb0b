"""Exact dedup by deterministic block naming, with DataFrame functions only.

A text is cut into blocks of fixed size. The distinct blocks are sorted and numbered: equal
blocks get one integer, different blocks different ones. Then adjacent pairs of integers are
named in the same way, level by level, until each document is one integer: its identity.
Nothing rests on a hash being free of collisions: a 64-bit fingerprint only says where a block
stands in the sort, and blocks that share a fingerprint but not their bytes are told apart by
their bytes.

Scale: the text is shuffled once, already reduced to distinct blocks within each map task;
everything after that is integers. Names are written out before they are joined, so both sides
of each such join are plain exchanges, which AQE can split where one block or one pair is in a
third of all rows. The number of levels is the binary logarithm of the longest text in blocks.

Defined results: a null text counts as empty; empty texts are equal to each other. A null id
is below all others. Rows with the same id and the same text are repeats of one document: all
are returned, and of those that stay only the first is marked as kept. An empty table gives an
empty result. Other columns are never read.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.llm.common import checkpointed, col, fresh

BLOCK_BYTES = 1024
#: Texts are first cut to pieces of so many blocks, so that long texts are not copied for each block.
PIECE_BLOCKS = 256


def keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, body_key and body; rows that agree in both keys are repeats of one document."""
    body = F.coalesce(col(text_col), F.lit("")).cast("binary")
    return docs.select(col(id_col).alias("doc_id"), F.xxhash64(body).alias("body_key"), body.alias("body"))


def blocks(rows: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per block: doc_id, body_key, n (blocks of the text), pos, block. An empty text is one empty block."""
    piece = block_bytes * PIECE_BLOCKS
    size = F.octet_length("body")
    pieces = rows.select(
        "doc_id", "body_key", "body",
        F.greatest(F.lit(1), F.ceil(size / F.lit(block_bytes))).cast("int").alias("n"),
        F.explode(F.sequence(F.lit(0), F.expr(f"cast(greatest(octet_length(body) - 1, 0) div {piece} as int)"))).alias("p"),
    ).select("doc_id", "body_key", "n", "p", F.expr(f"substring(body, p * {piece} + 1, {piece})").alias("part"))
    return pieces.select(
        "doc_id", "body_key", "n", "p", "part",
        F.explode(F.sequence(F.lit(0), F.expr(f"cast(greatest(octet_length(part) - 1, 0) div {block_bytes} as int)"))).alias("j"),
    ).select("doc_id", "body_key", "n", F.expr(f"p * {PIECE_BLOCKS} + j").alias("pos"), F.expr(f"substring(part, j * {block_bytes} + 1, {block_bytes})").alias("block"))


def _numbered(distinct: DataFrame, *order: str) -> DataFrame:
    """Integer names, given in sorted order within each partition of an already distinct table."""
    return checkpointed(distinct.sortWithinPartitions(*order).withColumn("name", F.monotonically_increasing_id()))


def name_blocks(cut: DataFrame, fingerprint=lambda block: F.xxhash64(block)) -> DataFrame:
    """Level 0: doc_id, body_key, n, pos, name. Equal blocks share a name, different ones never do."""
    marked = cut.withColumn("fp", fingerprint(F.col("block")))
    distinct = marked.select("fp", "block").distinct()
    names = _numbered(distinct.groupBy("fp").agg(F.count("*").alias("different")), "fp")
    plain = marked.select("doc_id", "body_key", "n", "pos", "fp")
    single = plain.join(names.where("different = 1").select("fp", "name"), "fp").select("doc_id", "body_key", "n", "pos", "name")
    if names.where("different > 1").isEmpty():
        return single
    clashing = names.where("different > 1").select("fp")
    apart = _numbered(distinct.join(clashing, "fp").select("fp", "block"), "fp", "block").withColumn("name", -F.col("name") - 2)
    return single.unionByName(marked.join(apart, ["fp", "block"]).select("doc_id", "body_key", "n", "pos", "name"))


def identities(rows: DataFrame, block_bytes: int = BLOCK_BYTES, **how) -> DataFrame:
    """One row per different (doc_id, body_key) with (level, name): equal exactly for equal texts.

    Repeats of a row hold the same blocks at the same places, so pairing them by place folds
    them into one.
    """
    now = checkpointed(name_blocks(blocks(rows, block_bytes), **how))
    longest = now.agg(F.max("n")).first()[0] or 0
    done, level = [], 0
    while True:
        done.append(now.where("n = 1").select("doc_id", "body_key", F.lit(level).alias("level"), "name"))
        if longest <= 1:
            break
        pairs = (
            now.where("n > 1").groupBy("doc_id", "body_key", "n", F.expr("pos div 2").alias("pos"))
            .agg(F.max(F.expr("if(pos % 2 = 0, name, null)")).alias("left"), F.max(F.expr("if(pos % 2 = 1, name, null)")).alias("right"))
            .withColumn("right", F.coalesce("right", F.lit(-1)))
        )
        names = _numbered(pairs.select("left", "right").distinct(), "left", "right")
        now = checkpointed(pairs.join(names, ["left", "right"]).select("doc_id", "body_key", F.expr("cast((n + 1) div 2 as int)").alias("n"), F.col("pos").cast("int").alias("pos"), "name"))
        longest, level = (longest + 1) // 2, level + 1
    return reduce(DataFrame.unionByName, done)


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per row of `docs`: doc_id, keep_id, group_size, kept, text_sha256, body_key."""
    rows = keyed(docs, id_col, text_col)
    seen = rows.groupBy("doc_id", "body_key", F.sha2("body", 256).alias("text_sha256")).agg(F.count("*").alias("times"))
    named = identities(rows, block_bytes).distinct()
    both = checkpointed(seen.join(named.withColumnsRenamed({"doc_id": "d", "body_key": "k"}), F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("body_key") == F.col("k"))).drop("d", "k"))
    groups = checkpointed(both.groupBy("level", "name").agg(F.max("doc_id").alias("keep_id"), F.sum("times").alias("group_size")))
    return both.join(groups, ["level", "name"]).select(
        "doc_id", "keep_id", "group_size", F.explode(F.expr("sequence(1L, times)")).alias("nth"), "text_sha256", "body_key"
    ).select("doc_id", "keep_id", "group_size", (F.col("doc_id").eqNullSafe(F.col("keep_id")) & (F.col("nth") == 1)).alias("kept"), "text_sha256", "body_key")


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`docs` without the rows whose text another row keeps; all columns stay."""
    d, k, n = fresh(docs, "__id"), fresh(docs, "__body_key"), fresh(docs, "__nth")
    kept = checkpointed(exact_groups(docs, id_col, text_col).where("kept").select(F.col("doc_id").alias(d), F.col("body_key").alias(k + "2")))
    mine = docs.withColumn(k, F.xxhash64(F.coalesce(col(text_col), F.lit("")).cast("binary")))
    left = mine.join(kept, col(id_col).eqNullSafe(col(d)) & (col(k) == col(k + "2")), "left_semi")
    if left.count() > kept.count():  # repeats of a whole (id, text): the first of each stays
        left = left.dropDuplicates([id_col, k])
    return left.drop(k, n)
