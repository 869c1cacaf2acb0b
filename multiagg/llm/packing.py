"""Packing by concatenate and cut.

Documents are laid end to end, each followed by an end id, and the stream is cut into windows
of a fixed number of ids. Pass 1 tokenises once and keeps, for each partition, ids with their
place in the partition; the partitions' totals give each one its global offset by a prefix sum.
Pass 2 is arithmetic on offsets: it cuts each stretch of ids where a window ends. Only the last
window of all is not full, so padding stays below one window however large the corpus.

The stream is written once, to the shared folder, because both passes need it and tokenising is
what costs. The offsets have one row per partition, which bounds their broadcast.

Defined results: a null text counts as empty, and an empty document is its end id alone.
Repeated rows are packed as often as they stand. An empty table gives no piece.
"""

from __future__ import annotations

import hashlib
import json
import unicodedata
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from multiagg.llm.byte_bpe import ENDS_LETTERS, IS_LETTER, PairTable, merge_all
from multiagg.llm.common import col, read_bytes, slices, tabled, vocabulary_file
from multiagg.llm.spans import ids_of, spread, worker_cache

TOKENIZER_FILE = "word_bpe_49k.json"
WINDOW = 2048
END_ID = 1
#: A stored stretch has at most so many ids; longer documents lie in several.
STRETCH = 1 << 16
#: How the tokenizer file splits normalised text.
WORD_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
#: Words of code points below this are normalised and split here; others go through the library.
LATIN_END = 0x250
WHITE = np.zeros(256, dtype=bool)
WHITE[[32, *range(9, 14)]] = True
SMALL = np.arange(256, dtype=np.uint8)
SMALL[65:91] += 32


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in printable]
    return [chr(b) if b in printable else chr(256 + rest.index(b)) for b in range(256)]


class WordCodec:
    """The ids that the tokenizers library gives, for white-space separated words, each distinct word once.

    The vocabulary's merges run on the matrices of `byte_bpe`. A word with code points from
    `LATIN_END` on, or with the mark of a special token, is given to the library itself.
    """

    def __init__(self, data: bytes):
        import regex
        from tokenizers import Tokenizer

        made = json.loads(data)
        vocab, merges = made["model"]["vocab"], made["model"]["merges"]
        self.library = Tokenizer.from_str(data.decode())
        self.find = regex.compile(WORD_PATTERN).findall
        letters, end = byte_letters(), made["model"]["end_of_word_suffix"]
        self.inner = np.array([vocab[x] for x in letters], dtype=np.int64)
        self.last = np.array([vocab[x + end] for x in letters], dtype=np.int64)
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        rows = np.array([(vocab[a], vocab[b], i, vocab[a + b]) for i, (a, b) in enumerate(pairs)], dtype=np.int64)
        self.table = PairTable(*rows.T)
        self.key = hashlib.sha256(data).hexdigest()

    def pieces(self, pieces: list[str]) -> list[bytes]:
        raw = [p.encode() for p in pieces]
        sizes = np.fromiter(map(len, raw), np.int64, len(raw))
        symbols = np.frombuffer(b"".join(raw), dtype=np.uint8)
        ids = self.inner[symbols]
        ends = np.cumsum(sizes) - 1
        ids[ends] = self.last[symbols[ends]]
        flat, per = merge_all(ids, sizes, self.table)
        whole, cuts = flat.astype("<u4").tobytes(), [0, *(4 * np.cumsum(per)).tolist()]
        return [whole[a:b] for a, b in zip(cuts, cuts[1:])]

    def cut(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The words of the texts, cut once more behind ASCII letters where another ASCII sign follows, unless a word may hold the mark of a special token."""
        white = WHITE[data]
        edge = np.diff(np.concatenate([[True], white, [True]]).astype(np.int8))
        first, last = np.flatnonzero(edge == -1), np.flatnonzero(edge == 1)
        marks = np.concatenate([[0], np.cumsum(data == ord("<"))])
        inner = np.flatnonzero(IS_LETTER[data[:-1]] & ENDS_LETTERS[data[1:]] & ~white[1:]) + 1
        word = np.searchsorted(first, inner, "right") - 1
        inner = inner[marks[last[word]] == marks[first[word]]]
        first, last = np.sort(np.concatenate([first, inner])), np.sort(np.concatenate([last, inner]))
        return first, last, np.searchsorted(starts, first, "right") - 1

    def learn(self, data: np.ndarray, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(flat ids, ids per word); words of ASCII letters need no splitting."""
        strange = np.concatenate([[0], np.cumsum(~IS_LETTER[data])])
        plain = strange[last] == strange[first]
        one, many = np.flatnonzero(plain), np.flatnonzero(~plain)
        sizes = (last - first)[one]
        symbols = SMALL[data[spread(first[one], sizes)]]
        ids, ends = self.inner[symbols], np.cumsum(sizes) - 1
        ids[ends] = self.last[symbols[ends]]
        flat, per = merge_all(ids, sizes, self.table)
        others = [np.frombuffer(x, "<u4") for x in self.learn_words([data[a:b].tobytes() for a, b in zip(first[many].tolist(), last[many].tolist())])]
        counts = np.empty(len(first), dtype=np.int64)
        counts[one], counts[many] = per, [len(x) for x in others]
        out, at = np.empty(int(counts.sum()), dtype=np.int64), np.cumsum(counts) - counts
        out[spread(at[one], per)] = flat
        if others:
            out[spread(at[many], counts[many])] = np.concatenate(others)
        return out, counts

    def learn_words(self, words: list[bytes]) -> list[bytes]:
        """The ids of each word."""
        found, other = [], []
        for i, w in enumerate(words):
            t = w.decode("utf-8", "replace")
            if "<|" in t or (not t.isascii() and ord(max(t)) >= LATIN_END):
                other.append((i, t))
                found.append(())
                continue
            t = unicodedata.normalize("NFC", t).lower()
            found.append((t,) if t.isalpha() else self.find(t))
        distinct = list(set().union(*found))
        ids = dict(zip(distinct, self.pieces(distinct))) if distinct else {}
        out = [ids[p[0]] if len(p) == 1 else b"".join(map(ids.__getitem__, p)) for p in found]
        if other:
            made = self.library.encode_batch([t for _, t in other], add_special_tokens=False)
            for (i, _), e in zip(other, made):
                out[i] = np.array(e.ids, dtype="<u4").tobytes()
        return out

    def encode(self, texts: list[str | None]) -> list[bytes]:
        """The ids of each text, little-endian unsigned 32-bit."""
        out = []
        for flat, per in ids_of(texts, self.key, self.cut, self.learn):
            whole, cuts = flat.astype("<u4").tobytes(), [0, *(4 * np.cumsum(per)).tolist()]
            out += [whole[a:b] for a, b in zip(cuts, cuts[1:])]
        return out


def word_codec(data: bytes) -> WordCodec:
    held = worker_cache("word codecs")
    key = hashlib.sha256(data).hexdigest()
    if key not in held:
        held[key] = WordCodec(data)
    return held[key]


def token_stream(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer_path: str | None = None, end_id: int = END_ID) -> DataFrame:
    """Pass 1: (part, place, doc_id, start, doc_tokens, ids), one row per stretch of a document.

    `place` counts the partition's ids before the stretch, `start` those of its document.
    """
    kind = docs.select(col(id_col)).schema[0].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(read_bytes(tokenizer_path or vocabulary_file(TOKENIZER_FILE)))
    end = np.array([end_id], dtype="<u4").tobytes()

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec, part, place = word_codec(shared.value), TaskContext.get().partitionId(), 0
        for some in slices(frames):
            rows = []
            for doc, ids in zip(some["doc_id"], codec.encode(some["text"].tolist())):
                ids += end
                n = len(ids) // 4
                for start in range(0, n, STRETCH):
                    rows.append((part, place + start, doc, start, n, ids[4 * start : 4 * (start + STRETCH)]))
                place += n
            yield pd.DataFrame(rows, columns=["part", "place", "doc_id", "start", "doc_tokens", "ids"])

    made = docs.select(col(id_col).alias("doc_id"), col(text_col).alias("text"))
    return made.mapInPandas(work, f"part int, place long, doc_id {kind}, start long, doc_tokens long, ids binary")


def cut_stream(stream: DataFrame, window: int = WINDOW) -> DataFrame:
    """Pass 2: pieces (doc_id, start, length, ids, doc_tokens, sequence_id, offset)."""
    totals = stream.groupBy("part").agg(F.max(F.col("place") + F.octet_length("ids") / 4).cast("long").alias("n"))
    before = totals.select(F.col("part").alias("of"), (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("base"))
    laid = stream.join(F.broadcast(before), F.col("part") == F.col("of")).select(
        "doc_id", "start", "doc_tokens", "ids", (F.col("base") + F.col("place")).alias("at"), F.expr("octet_length(ids) div 4").alias("n")
    )
    each = laid.select("*", F.explode(F.expr(f"sequence(at div {window}, (at + n - 1) div {window})")).alias("sequence_id"))
    each = each.withColumn("lo", F.greatest("at", F.col("sequence_id") * window)).withColumn("hi", F.least(F.expr("at + n"), (F.col("sequence_id") + 1) * window))
    return each.select(
        "doc_id", F.expr("start + lo - at").alias("start"), F.expr("hi - lo").alias("length"),
        F.expr("substring(ids, cast(4 * (lo - at) + 1 as int), cast(4 * (hi - lo) as int))").alias("ids"),
        "doc_tokens", "sequence_id", F.expr(f"lo - sequence_id * {window}").alias("offset"),
    )


def pack(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, **how) -> DataFrame:
    """Pieces of all documents; `ids` is the piece's ids as little-endian unsigned 32-bit."""
    return cut_stream(tabled(token_stream(docs, id_col, text_col, **how), "stream"), window)


def sequences(pieces: DataFrame) -> DataFrame:
    """One row per window: sequence_id, n_ids, ids. A window bounds its group."""
    together = pieces.groupBy("sequence_id").agg(F.sort_array(F.collect_list(F.struct("offset", "ids"))).alias("p"), F.sum("length").alias("n_ids"))
    joined = F.aggregate("p", F.unhex(F.lit("")), lambda done, x: F.concat(done, x["ids"]))
    return together.select("sequence_id", "n_ids", joined.alias("ids"))
