"""Removal of repeated passages by prefix-free parsing.

Rolling hashes choose triggers: the place of least hash in each passage-long window of bytes is
one, so a trigger lies in every window, and equal windows have it at the same offset. Triggers cut
a document into phrases; a phrase is the run of windows that share a trigger, with all their
bytes. The dictionary holds the distinct phrases with their numbers, the parse is each document's
list of them. No suffix array and no order is made: two windows of a passage's length are equal
exactly if they agree in trigger, offset and bytes, so grouping and counting hashes finds them. So

* a trigger string met once in the corpus ends the search for its windows;
* a phrase that stands in the parse twice makes all its windows repeats, without looking at them;
* the windows of the other phrases of a shared trigger are compared over the dictionary's distinct
  phrases only, each read from one document: first in blocks of neighbouring offsets, whose shared
  bytes must stand in a second phrase if any window does, and whose whole bytes settle all of them if
  they do; only where blocks lie between these two, at the ends of repeats, are windows compared one by one.

What is found of a phrase goes back to the documents through the parse.

Scale: texts are read where they lie, once for triggers, once for the parse, once for the blocks and
once for the windows at the ends of repeats; bitmaps of bounded size, broadcast, say what is asked.
What they let through besides are true windows too, so it costs time and changes nothing. Equal
windows have one trigger and one block, so a single shuffle by both serves all comparisons of a
step. Texts are shuffled once, to meet what is cut from them.

Strings are compared by two 64-bit hashes, of the trigger and of the bytes around it.

Defined results: a null text counts as empty; a text shorter than a passage loses nothing. Rows
with one id and one text are repeats of one document and all lose what they share. Passages never
cross documents. Bytes are UTF-8. An empty table gives no row.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from multiagg.llm.common import bitmap, bits_for, checkpointed, col, in_bitmap, powers, runs, slices, tabled
from multiagg.llm.spans import worker_cache

PASSAGE = 200
TRIGGER = 64
#: Windows of a phrase are first ordered by blocks of so many offsets.
BLOCK = 16
#: Texts are parsed in stretches of so many bytes.
STRETCH = (1 << 20) - (1 << 12)
BASE = 0x9E3779B97F4A7C15
#: Tells the blocks of a phrase apart.
SALT = 0x0345F4914F6CDD1D
_BYTES = np.random.default_rng(20240229).integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0xA0761D6478BD642F)
    return x ^ (x >> np.uint64(32))


class Stretch:
    """Hashes of one stretch of bytes."""

    def __init__(self, data: np.ndarray, passage: int = PASSAGE, trigger: int = TRIGGER):
        self.n, self.passage, self.trigger = len(data), passage, trigger
        held = worker_cache("passage powers")
        if held.get("size", 0) <= self.n:
            size = max(self.n + 1, STRETCH + (1 << 12))
            held.update(size=size, power=powers(size, BASE), back=powers(size, pow(BASE, -1, 1 << 64)))
        self.back = held["back"]
        with np.errstate(over="ignore"):
            self.sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_BYTES[data] * held["power"][: self.n])])

    def hashes(self, start: np.ndarray, size) -> np.ndarray:
        """Hashes of the bytes start..start+size-1."""
        with np.errstate(over="ignore"):
            return mixed((self.sums[start + size] - self.sums[start]) * self.back[start] + np.uint64(0x632BE59BD9B4E019) * np.asarray(size).astype(np.uint64))

    def anchors(self) -> tuple[np.ndarray, np.ndarray]:
        """For each window, in order: the place of its trigger; and the hash of each place's trigger string."""
        windows = self.n - self.passage + 1
        grams = self.hashes(np.arange(self.n - self.trigger + 1), self.trigger)
        width = self.passage - self.trigger + 1
        low = (grams & ~np.uint64((1 << 20) - 1)) | np.arange(len(grams), dtype=np.uint64)
        size = 1
        while 2 * size <= width:
            low = np.minimum(low[:-size], low[size:])
            size *= 2
        if width > size:
            low = np.minimum(low[: len(low) - (width - size)], low[width - size :])
        return (low[:windows] & np.uint64((1 << 20) - 1)).astype(np.int64), grams


class Parsed:
    """The phrases of some documents, or of a part of a long one. Places count from the start of the stretch; `low` and `high` are its documents' bounds."""

    def __init__(self, data: np.ndarray, low: np.ndarray, high: np.ndarray, begin: int, end: int, number: np.ndarray, passage: int, trigger: int):
        """Windows of all documents, from `begin` up to `end`."""
        self.s, self.passage, self.low, self.high = Stretch(data, passage, trigger), passage, low, high
        where, grams = self.s.anchors() if len(data) >= passage else (np.zeros(0, np.int64), np.zeros(0, np.uint64))
        a, b = np.maximum(low, begin), np.minimum(high - passage + 1, end)
        sizes = np.maximum(b - a, 0)
        windows, doc = np.repeat(a, sizes) + runs(sizes), np.repeat(np.arange(len(low)), sizes)
        at = where[windows]
        new = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (doc[1:] != doc[:-1])])) if len(at) else np.zeros(0, np.int64)
        self.first, self.count, self.place = windows[new], np.diff(np.append(new, len(at))), at[new]
        self.doc, self.number = doc[new], number[doc[new]]
        with np.errstate(over="ignore"):
            self.gram = grams[self.place].view(np.int64)
            self.phrase = mixed(self.s.hashes(self.first, self.count + passage - 1) + (self.place - self.first).astype(np.uint64) * np.uint64(BASE)).view(np.int64)

    def blocks(self, of: np.ndarray) -> tuple[np.ndarray, ...]:
        """The windows of phrases `of` in blocks of offsets to the trigger: (phrase, block, least and greatest offset)."""
        low, high = (self.place - self.first - self.count + 1)[of], (self.place - self.first)[of]
        number = high // BLOCK - low // BLOCK + 1
        block = np.repeat(low // BLOCK, number) + runs(number)
        return np.repeat(of, number), block, np.maximum(BLOCK * block, np.repeat(low, number)), np.minimum(BLOCK * block + BLOCK - 1, np.repeat(high, number))

    def block_hashes(self, of: np.ndarray, block: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Hash of the bytes that all windows of a block share, hash of all their bytes, and whether the document has that many."""
        start = self.place[of] - BLOCK * block
        enough = (start - BLOCK + 1 >= self.low[self.doc[of]]) & (start + self.passage <= self.high[self.doc[of]])
        with np.errstate(over="ignore"):
            salt = block.astype(np.uint64) * np.uint64(BASE)
            core = mixed(self.s.hashes(start, self.passage - BLOCK + 1) + salt)
            full = np.zeros(len(of), np.uint64)
            full[enough] = mixed(self.s.hashes(start[enough] - BLOCK + 1, self.passage + BLOCK - 1) + salt[enough])
        return core.view(np.int64), full.view(np.int64), enough

    def windows(self, of: np.ndarray, low: np.ndarray, high: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Each window of phrases `of` with offsets low..high: (place in `of`, offset, hash)."""
        n = high - low + 1
        which = np.repeat(np.arange(len(of)), n)
        offset = np.repeat(low, n) + runs(n)
        with np.errstate(over="ignore"):
            return which, offset, mixed(self.s.hashes(self.place[of][which] - offset, self.passage) + offset.astype(np.uint64) * np.uint64(BASE)).view(np.int64)


def parsed(bodies: list[bytes], passage: int = PASSAGE, trigger: int = TRIGGER) -> Iterator[Parsed]:
    """Documents parsed together in stretches; `number` is the document's place in `bodies`. A long one is parsed in parts that meet between phrases."""
    held: list[int] = []
    size = 0

    def together() -> Parsed:
        sizes = np.array([len(bodies[i]) for i in held], dtype=np.int64)
        low = np.cumsum(sizes) - sizes
        data = np.frombuffer(b"".join(bodies[i] for i in held), np.uint8)
        return Parsed(data, low, low + sizes, 0, len(data), np.array(held), passage, trigger)

    for i, body in enumerate(bodies):
        n = len(body)
        if n >= STRETCH:
            begin = 0
            while begin <= n - passage:
                at, end = max(0, begin - passage), min(begin + STRETCH - 4 * passage, n - passage + 1)
                data = np.frombuffer(body, np.uint8, min(n, end + 2 * passage) - at, at)
                p = Parsed(data, np.array([-at]), np.array([n - at]), begin - at, end - at, np.array([i]), passage, trigger)
                if end <= n - passage:  # the last phrase may go on: the next part begins with it
                    begin = at + int(p.first[-1])
                    for c in ("first", "count", "place", "doc", "number", "gram", "phrase"):
                        setattr(p, c, getattr(p, c)[:-1])
                else:
                    begin = n
                yield p
            continue
        if n < passage:
            continue
        if size + n >= STRETCH:
            yield together()
            held, size = [], 0
        held.append(i)
        size += n
    if held:
        yield together()


def removed_runs(n: int, first: np.ndarray, count: np.ndarray, passage: int = PASSAGE) -> np.ndarray:
    """Maximal runs (start, end) of bytes that windows first..first+count-1 cover."""
    edge = np.zeros(n + 1, dtype=np.int32)
    np.add.at(edge, first, 1)
    np.add.at(edge, first + count + passage - 1, -1)
    inside = np.concatenate([[0], (np.cumsum(edge)[:n] > 0).astype(np.int8), [0]])
    return np.flatnonzero(np.diff(inside)).reshape(-1, 2)


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, two keys of (id, text) and the bytes; rows that agree in both keys are repeats of one document."""
    id_, text = col(id_col), col(text_col)
    return docs.select(id_.alias("doc_id"), F.xxhash64(id_, text).alias("k1"), F.xxhash64(text, id_, F.lit(1)).alias("k2"), F.coalesce(text, F.lit("")).cast("binary").alias("body"))


def _scan(docs: DataFrame, work, schema: str, id_col: str, text_col: str, passage: int) -> DataFrame:
    """`work(parsed phrases, keys of the documents)` over all texts, where they lie."""

    def read(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            keys = frame[["k1", "k2"]].to_numpy()
            for p in parsed(frame["body"].tolist(), passage):
                yield work(p, keys)

    return _rows(docs, id_col, text_col).select("k1", "k2", "body").mapInPandas(read, schema)


def parse_table(docs: DataFrame, id_col: str, text_col: str, passage: int) -> DataFrame:
    """(k1, k2, gram, phrase, first, count, place): the parse, without phrases whose trigger string is met once; a bitmap lets a few of those through."""
    grams = _scan(docs, lambda p, keys: pd.DataFrame({"gram": p.gram}), "gram long", id_col, text_col, passage)
    again = checkpointed(grams.groupBy("gram").agg(F.count("*").alias("n")).where("n > 1").select("gram"))
    shared = docs.sparkSession.sparkContext.broadcast(bitmap(again, "gram", bits_for(again.count())))

    def work(p: Parsed, keys: np.ndarray) -> pd.DataFrame:
        k = np.flatnonzero(in_bitmap(p.gram, shared.value))
        start = p.low[p.doc[k]]
        return pd.DataFrame({"k1": keys[p.number[k], 0], "k2": keys[p.number[k], 1], "gram": p.gram[k], "phrase": p.phrase[k], "first": p.first[k] - start, "count": p.count[k], "place": p.place[k] - start})

    return tabled(_scan(docs, work, "k1 long, k2 long, gram long, phrase long, first int, count int, place int", id_col, text_col, passage), "parse")


def _in_two(*keys: str) -> Column:
    """Whether rows that agree in the keys stand in two phrases or more."""
    same = Window.partitionBy(*keys)
    return F.min("phrase").over(same) != F.max("phrase").over(same)


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", passage: int = PASSAGE) -> DataFrame:
    """Repeated stretches of windows (k1, k2, first, count)."""
    parse = parse_table(docs, id_col, text_col, passage)
    dictionary = checkpointed(parse.groupBy("gram", "phrase").agg(F.count("*").alias("times"), F.min("k1").alias("at")))
    shared = checkpointed(dictionary.groupBy("gram").agg(F.count("*").alias("phrases")).where("phrases > 1").select("gram"))
    several = checkpointed(dictionary.join(shared, "gram", "left_semi").select(F.col("phrase").bitwiseXOR(F.col("at")).alias("key")))
    asked = docs.sparkSession.sparkContext.broadcast(bitmap(several, "key", bits_for(several.count())))

    def asked_blocks(p: Parsed, keys: np.ndarray) -> tuple[np.ndarray, ...]:
        of = np.flatnonzero(in_bitmap(p.phrase ^ keys[p.number, 0], asked.value))
        return p.blocks(of[np.unique(p.phrase[of], return_index=True)[1]])

    def blocks(p: Parsed, keys: np.ndarray) -> pd.DataFrame:
        of, block, low, high = asked_blocks(p, keys)
        core, full, enough = p.block_hashes(of, block)
        return pd.DataFrame({"gram": p.gram[of], "phrase": p.phrase[of], "block": block, "low": low, "high": high, "core": core, "full": full, "enough": enough})

    cut = _scan(docs, blocks, "gram long, phrase long, block int, low int, high int, core long, full long, enough boolean", id_col, text_col, passage)
    cut = cut.repartition("gram", "block").withColumn("two", _in_two("gram", "block", "core")).where("two")
    cut = cut.withColumn("hit", F.col("enough") & _in_two("gram", "block", "enough", "full"))
    cut = cut.withColumn("edge", F.max(~F.col("hit")).over(Window.partitionBy("gram", "block")))
    open_ = tabled(cut.select("gram", "phrase", "block", "low", "high", "hit", "edge"), "blocks")
    sure = open_.where("hit").select("gram", "phrase", "low", "high")
    # What is left are the blocks at the ends of repeats, window by window, with those of the same trigger and place that may hold their partners.
    edge = open_.where("edge").select(F.col("phrase").bitwiseXOR(F.col("block").cast("long") * F.lit(SALT)).alias("key"))
    edges = docs.sparkSession.sparkContext.broadcast(bitmap(edge, "key", bits_for(edge.count())))

    def windows(p: Parsed, keys: np.ndarray) -> pd.DataFrame:
        of, block, low, high = asked_blocks(p, keys)
        k = np.flatnonzero(in_bitmap(p.phrase[of] ^ block * np.int64(SALT), edges.value))
        of, low, high = of[k], low[k], high[k]
        _, _, window = p.windows(of, low, high)
        ends = np.cumsum(high - low + 1)
        return pd.DataFrame({"gram": p.gram[of], "phrase": p.phrase[of], "block": block[k], "low": low, "windows": pd.Series(np.split(window, ends[:-1]) if len(of) else [], dtype=object)})

    each = _scan(docs, windows, "gram long, phrase long, block int, low int, windows array<long>", id_col, text_col, passage)
    each = each.repartition("gram", "block").select("gram", "phrase", "block", "low", F.posexplode("windows").alias("i", "window"))
    parts = each.withColumn("two", _in_two("gram", "block", "window")).where("two").select("gram", "phrase", (F.col("low") + F.col("i")).alias("low")).withColumn("high", F.col("low"))
    spans = checkpointed(sure.unionByName(parts).groupBy("gram", "phrase").agg(F.collect_set(F.struct("low", "high")).alias("spans")))
    often = dictionary.where("times > 1").select("gram", "phrase", F.lit(None).cast(spans.schema["spans"].dataType).alias("spans"))
    found = checkpointed(often.unionByName(spans.join(often.select("gram", "phrase"), ["gram", "phrase"], "left_anti")))
    marked = parse.join(found, ["gram", "phrase"])
    whole = marked.where("spans is null").select("k1", "k2", "first", "count")
    return whole.unionByName(marked.where("spans is not null").select("k1", "k2", "place", F.explode("spans").alias("x")).select("k1", "k2", F.expr("place - x.high").alias("first"), F.expr("x.high - x.low + 1").alias("count")))


def _kept(body: bytes, bounds: np.ndarray) -> bytes:
    ends = [0, *bounds.tolist(), len(body)]
    return b"".join(body[a:b] for a, b in zip(ends[::2], ends[1::2]))


def remove_repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", passage: int = PASSAGE) -> DataFrame:
    """One row per row of `docs`: doc_id, n_bytes, n_removed, n_spans, kept (the remaining bytes)."""
    marks = checkpointed(repeats(docs, id_col, text_col, passage).groupBy("k1", "k2").agg(F.collect_set(F.struct("first", "count")).alias("m")))
    kind = docs.select(col(id_col)).schema[0].dataType.simpleString()
    rows = _rows(docs, id_col, text_col).join(marks, ["k1", "k2"], "left").select("doc_id", "body", F.col("m.first").alias("first"), F.col("m.count").alias("count"))

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in slices(frames):
            out = []
            for d, body, first, count in zip(frame["doc_id"], frame["body"], frame["first"], frame["count"]):
                cut = removed_runs(len(body), first, count, passage).ravel() if first is not None else np.zeros(0, np.int64)
                out.append((d, len(body), int((cut[1::2] - cut[::2]).sum()), len(cut) // 2, _kept(body, cut)))
            yield pd.DataFrame(out, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "kept"])

    return rows.mapInPandas(work, f"doc_id {kind}, n_bytes long, n_removed long, n_spans long, kept binary")


def removal_digests(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of each row of `docs`."""
    return remove_repeats(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))
