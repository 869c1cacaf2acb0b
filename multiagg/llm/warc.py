"""WARC records and a Merkle audit of replicas.

Each record is hashed; the hashes of up to `FAN_OUT` records that follow each other in an archive,
with the range of offsets they cover, are hashed to a node, and so on up to one root per archive.
Replicas are compared by their roots; from level to level only the children of nodes that differ
are looked at, down to the records. Building a tree shuffles hashes and offsets, never records,
and an archive is divided by order, so no node gathers more than `FAN_OUT` rows.

Defined results: a record that one replica lacks is reported as missing there. A null payload is
an empty one, a null URL an empty URI. Archives without records have no root. Repeated rows are
records of their own. An empty table gives no row; columns that are not named are not read, whatever
they are called.
"""

from __future__ import annotations

import gzip
import hashlib
from collections.abc import Iterator

import pandas as pd
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from multiagg.llm.common import checkpointed, col, tabled

FAN_OUT = 64


def record_text(url: Column, payload: Column) -> Column:
    """A resource record as one string."""
    body = F.coalesce(payload, F.lit(""))
    head = F.concat(F.lit("WARC/1.1\r\nWARC-Type: resource\r\nWARC-Target-URI: "), F.coalesce(url, F.lit("")), F.lit("\r\nContent-Type: text/html\r\nContent-Length: "), F.octet_length(body).cast("string"), F.lit("\r\n\r\n"))
    return F.concat(head, body, F.lit("\r\n\r\n"))


def records(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """(record_id, record): one WARC record per row."""
    return pages.select(col(id_col).alias("record_id"), record_text(col(url_col), col(payload_col)).cast("binary").alias("record"))


def parse_warc(data: bytes) -> Iterator[tuple[int, int, dict[str, str], bytes]]:
    """(offset, length, headers, payload) of the records in an uncompressed archive; stops at damage in a header."""
    at = 0
    while data.startswith(b"WARC/", at):
        head = data.find(b"\r\n\r\n", at)
        if head < 0:
            return
        fields = dict(line.split(": ", 1) for line in data[at:head].decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
        size = int(fields.get("Content-Length", 0))
        end = head + 4 + size + 4
        yield at, min(end, len(data)) - at, fields, data[head + 4 : head + 4 + size]
        at = end


def read_warc(spark: SparkSession, path: str) -> DataFrame:
    """Records of .warc and .warc.gz files, each file below 2 GB: (path, offset, length, uri, payload)."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for name, data in zip(frame["path"], frame["content"]):
                raw = gzip.decompress(data) if data[:2] == b"\x1f\x8b" else data
                rows = [(name, o, n, f.get("WARC-Target-URI"), p) for o, n, f, p in parse_warc(raw)]
                yield pd.DataFrame(rows, columns=["path", "offset", "length", "uri", "payload"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInPandas(work, "path string, offset long, length long, uri string, payload binary")


def archived(rows: DataFrame) -> DataFrame:
    """The archive index: (archive, seq, offset, length, sha256, record_id), one archive per partition, records in the order they come."""
    kind = rows.schema["record_id"].dataType.simpleString()

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        archive, seq, offset = TaskContext.get().partitionId(), 0, 0
        for frame in frames:
            out = []
            for name, record in zip(frame["record_id"], frame["record"]):
                out.append((archive, seq, offset, len(record), hashlib.sha256(record).digest(), name))
                seq, offset = seq + 1, offset + len(record)
            yield pd.DataFrame(out, columns=["archive", "seq", "offset", "length", "sha256", "record_id"])

    return rows.select("record_id", "record").mapInPandas(work, f"archive long, seq long, offset long, length long, sha256 binary, record_id {kind}")


def leaves(index: DataFrame) -> DataFrame:
    return index.select("archive", F.lit(0).alias("level"), F.col("seq").alias("node"), F.col("offset").alias("low"), (F.col("offset") + F.col("length")).alias("high"), F.col("sha256").alias("hash"))


def merkle_levels(index: DataFrame, fan_out: int = FAN_OUT) -> list[DataFrame]:
    """The tree's levels, leaves first; the last has one node per archive."""
    now = leaves(index)
    most = index.agg(F.max("seq")).first()[0]
    out = [now]
    while most is not None and most > 0:
        now = checkpointed(
            now.groupBy("archive", F.expr(f"node div {fan_out}").alias("parent"))
            .agg(F.sort_array(F.collect_list(F.struct("node", "low", "high", "hash"))).alias("c"), F.min("low").alias("low"), F.max("high").alias("high"))
            .select("archive", F.lit(len(out)).alias("level"), F.col("parent").alias("node"), "low", "high", F.unhex(F.sha2(F.concat_ws("|", F.transform("c", lambda x: F.concat_ws(":", x["low"], x["high"], F.hex(x["hash"])))).cast("binary"), 256)).alias("hash"))
        )
        out.append(now)
        most //= fan_out
    return out


def audit(ours: DataFrame, theirs: DataFrame, fan_out: int = FAN_OUT) -> DataFrame:
    """Records that differ between two replicas' indexes: (archive, seq, low, high, state), state being changed, missing here or missing there."""
    a, b = merkle_levels(ours, fan_out), merkle_levels(theirs, fan_out)
    while len(a) < len(b):
        a.append(_raised(a[-1]))
    while len(b) < len(a):
        b.append(_raised(b[-1]))
    suspects = None
    for x, y in zip(reversed(a), reversed(b)):
        if suspects is not None:
            x, y = (t.join(suspects, (t["archive"] == suspects["of"]) & (F.expr(f"node div {fan_out}") == suspects["parent"]), "left_semi") for t in (x, y))
        y = y.select("archive", "node", F.col("low").alias("low2"), F.col("high").alias("high2"), F.col("hash").alias("hash2"))
        differ = x.join(y, ["archive", "node"], "full_outer").where("not (hash <=> hash2) or not (low <=> low2) or not (high <=> high2)")
        differ = checkpointed(differ.select("archive", "node", "low", "high", "hash", "low2", "high2", "hash2"))
        suspects = differ.select(F.col("archive").alias("of"), F.col("node").alias("parent"))
    state = F.when(F.col("hash").isNull(), "missing here").when(F.col("hash2").isNull(), "missing there").when(F.col("hash") == F.col("hash2"), "moved").otherwise("changed")
    return differ.select("archive", F.col("node").alias("seq"), F.coalesce("low", "low2").alias("low"), F.coalesce("high", "high2").alias("high"), state.alias("state"))


def _raised(level: DataFrame) -> DataFrame:
    return level.withColumn("level", F.col("level") + 1)


def damaged(pages: DataFrame, url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """A replica to try the audit on: where the URL's SHA-256 starts with 0, the payload's first character has become another."""
    hit = F.substring(F.sha2(F.coalesce(col(url_col), F.lit("")).cast("binary"), 256), 1, 1) == "0"
    other = F.when(F.substring(col(payload_col), 1, 1) == "#", "~").otherwise("#")
    return pages.withColumn(payload_col, F.when(hit & (F.length(col(payload_col)) > 0), F.concat(other, F.expr(f"substring(`{payload_col}`, 2)"))).otherwise(col(payload_col)))


def fixity(pages: DataFrame, replica: DataFrame, id_col: str = "page_id", url_col: str = "url", payload_col: str = "html") -> DataFrame:
    """(record_id, archive, seq, offset, n_bytes, record_sha256, state) of each record of `pages`; state is intact, or what the audit against `replica` found."""
    ours = tabled(archived(records(pages, id_col, url_col, payload_col)), "index")
    theirs = tabled(archived(records(replica, id_col, url_col, payload_col)), "replica")
    found = audit(ours, theirs).select("archive", "seq", "state")
    return ours.join(found, ["archive", "seq"], "left").select("record_id", "archive", "seq", "offset", F.col("length").alias("n_bytes"), F.lower(F.hex("sha256")).alias("record_sha256"), F.coalesce("state", F.lit("intact")).alias("state"))
