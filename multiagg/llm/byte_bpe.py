"""Byte-level BPE encoding and decoding on padded numpy matrices.

Pieces are put in buckets by length, one row per piece. In each round every row of a bucket
merges its leftmost pair of least rank; pairs are looked up in an open-addressing hash table,
all rows at once; rows without a pair left are taken out and columns that have become empty
are cut off. A piece beyond `LONG` symbols is merged with a heap instead, which gives the same
ids in time n log n.

Texts are cut into spans that no piece crosses; equal spans are encoded once (see `spans`) and told
apart by a 64-bit hash. Ids, their decimals and the decoded bytes are made of arrays, not of lists.

Defined results: a null text counts as empty and has no ids. Repeated rows are encoded each by
itself, an empty table gives no row, and only the columns asked for are read, whatever others are called.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from multiagg.llm.common import col, read_bytes, runs, slices, vocabulary_file
from multiagg.llm.spans import ids_of, spread, worker_cache

RANKS_FILE = "byte_bpe_50k.tiktoken"
LONG = 512
CELLS = 1 << 20
BUCKETS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 14, 16, 20, 24, 32, 48, 64, 128, 256, LONG)
NONE = np.int32(2**31 - 1)
IS_LETTER = np.zeros(256, dtype=bool)
IS_LETTER[[*range(65, 91), *range(97, 123)]] = True
#: Bytes that no white space starts with: printable ASCII, and all lead bytes but those of the blocks that hold white space.
FOLLOWS = np.zeros(256, dtype=bool)
FOLLOWS[0x21:0x7F] = FOLLOWS[0xC3:0xF5] = True
FOLLOWS[[0xE1, 0xE2, 0xE3]] = False
ENDS_LETTERS = ~IS_LETTER & (np.arange(256) < 0x80)


class PairTable:
    """(left id, right id) -> (rank, merged id), vectorised."""

    MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)

    def __init__(self, left: np.ndarray, right: np.ndarray, rank: np.ndarray, merged: np.ndarray):
        bits = max(4, int(2 * len(left)).bit_length())
        self.shift, self.mask = np.uint64(64 - bits), np.int64((1 << bits) - 1)
        self.keys = np.full(1 << bits, -1, dtype=np.int64)
        self.values = np.full(1 << bits, NONE, dtype=np.int32)
        self.merged = np.full(int(rank.max(initial=0)) + 1, -1, dtype=np.int32)
        self.merged[rank] = merged
        key = (left.astype(np.int64) << 32) | right.astype(np.int64)
        at, todo = self._home(key), np.arange(len(key))
        while todo.size:
            free = self.keys[at[todo]] == -1
            slot, first = np.unique(at[todo[free]], return_index=True)
            placed = todo[free][first]
            self.keys[slot], self.values[slot] = key[placed], rank[placed]
            todo = np.setdiff1d(todo, placed, assume_unique=True)
            at[todo] = (at[todo] + 1) & self.mask

    def _home(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * self.MULTIPLIER) >> self.shift).astype(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        """The rank of each pair, NONE where it has none; -1 on either side stands for no symbol."""
        key = (left.astype(np.int64) << 32) | right.astype(np.int64)
        key[(left < 0) | (right < 0)] = -2
        at = self._home(key)
        seen = self.keys[at]
        out = np.where(seen == key, self.values[at], NONE)
        open_ = np.flatnonzero((seen != key) & (seen != -1) & (key != -2))
        while open_.size:
            at[open_] = (at[open_] + 1) & self.mask
            seen = self.keys[at[open_]]
            hit = seen == key[open_]
            out[open_[hit]] = self.values[at[open_[hit]]]
            open_ = open_[~hit & (seen != -1)]
        return out


def merge_rows(rows: np.ndarray, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """Rows of symbols, padded with -1 at the end, after all merges: (flat ids, ids per row)."""
    n, width = rows.shape
    done = np.full((n, width), -1, dtype=np.int32)
    where, m = np.arange(n), rows.astype(np.int32)
    rank = table.ranks(m[:, :-1].ravel(), m[:, 1:].ravel()).reshape(n, width - 1)
    while len(where) and m.shape[1] > 1:
        row, w = np.arange(len(where)), m.shape[1]
        j = rank.argmin(1)
        best = rank[row, j]
        live = best < NONE
        alive = int(live.sum())
        if 4 * alive < 3 * len(where) or not alive:
            over = ~live
            done[where[over], :w] = m[over]
            where, m, rank, j, best = where[live], m[live], rank[live], j[live], best[live]
            row, live = row[:alive], live[live]
            if not alive:
                break
        shift = np.arange(w - 1)[None, :] > np.where(live, j, w)[:, None]
        m[:, :-1] = np.where(shift, m[:, 1:], m[:, :-1])
        m[live, w - 1] = -1
        live = row[live]
        at = j[live]
        m[live, at] = table.merged[best[live]]
        short = at == w - 2  # the last pair: nothing has moved, its right side goes
        m[live[short], w - 1] = -1
        rank[:, :-1] = np.where(shift[:, :-1], rank[:, 1:], rank[:, :-1])
        rank[live, w - 2] = NONE
        inner = at < w - 2
        rank[live[inner], at[inner]] = table.ranks(m[live[inner], at[inner]], m[live[inner], at[inner] + 1])
        left = at > 0
        rank[live[left], at[left] - 1] = table.ranks(m[live[left], at[left] - 1], m[live[left], at[left]])
        if (m[:, -1] < 0).all():
            m, rank = m[:, :-1], rank[:, :-1]
    done[where, : m.shape[1]] = m
    return done[done >= 0], (done >= 0).sum(1)


def merge_long(symbols: np.ndarray, table: PairTable) -> list[int]:
    """One long piece: the same merges, by a heap of (rank, place) over a linked list."""
    ids, n = symbols.tolist(), len(symbols)
    following, before = list(range(1, n + 1)), list(range(-1, n - 1))
    rank = table.ranks(symbols[:-1], symbols[1:])
    heap = [(int(rank[i]), i, ids[i], ids[i + 1]) for i in np.flatnonzero(rank < NONE)]
    heapq.heapify(heap)
    known: dict[tuple[int, int], int] = {}

    def push(i: int) -> None:
        j = following[i]
        if j < n:
            pair = (ids[i], ids[j])
            if pair not in known:
                known[pair] = int(table.ranks(np.array([pair[0]]), np.array([pair[1]]))[0])
            if known[pair] < NONE:
                heapq.heappush(heap, (known[pair], i, *pair))

    while heap:
        r, i, left, right = heapq.heappop(heap)
        j = following[i]
        if ids[i] != left or j >= n or ids[j] != right:
            continue
        ids[i], ids[j] = int(table.merged[r]), -1
        following[i] = following[j]
        if following[i] < n:
            before[following[i]] = i
        push(i)
        if before[i] >= 0:
            push(before[i])
    return [x for x in ids if x >= 0]


def merge_all(symbols: np.ndarray, sizes: np.ndarray, table: PairTable) -> tuple[np.ndarray, np.ndarray]:
    """Sequences of symbols, end to end with their sizes, after all merges: (flat ids, ids per sequence)."""
    starts, out_sizes, parts = np.cumsum(sizes) - sizes, np.minimum(sizes, 1), []
    single = np.flatnonzero(sizes == 1)
    parts.append((single, symbols[starts[single]]))
    for low, width in zip(BUCKETS, BUCKETS[1:]):
        inside = np.flatnonzero((sizes > low) & (sizes <= width))
        for k in range(0, len(inside), max(1, CELLS // width)):
            part = inside[k : k + max(1, CELLS // width)]
            n = sizes[part]
            rows = np.full((len(part), int(n.max())), -1, dtype=np.int32)
            rows[np.repeat(np.arange(len(part)), n), runs(n)] = symbols[spread(starts[part], n)]
            flat, out_sizes[part] = merge_rows(rows, table)
            parts.append((part, flat))
    for i in np.flatnonzero(sizes > LONG):
        ids = np.array(merge_long(symbols[starts[i] : starts[i] + sizes[i]], table), dtype=np.int32)
        out_sizes[i] = len(ids)
        parts.append((np.array([i]), ids))
    out = np.empty(int(out_sizes.sum()), dtype=np.int32)
    ends = np.cumsum(out_sizes)
    for part, flat in parts:
        out[spread(ends[part] - out_sizes[part], out_sizes[part])] = flat
    return out, out_sizes


class ByteCodec:
    """The ranks of one vocabulary: encodes lists of texts and decodes ids."""

    def __init__(self, data: bytes, pattern: str):
        import regex

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, filter(None, data.split(b"\n")))}
        self.ranks, self.find = ranks, regex.compile(pattern).findall
        self.key = hashlib.sha256(data + pattern.encode()).hexdigest()
        self.bytes = [b""] * (max(ranks.values()) + 1)
        for token, r in ranks.items():
            self.bytes[r] = token
        self.single = np.array([ranks[bytes([b])] for b in range(256)], dtype=np.int64)
        splits = [(ranks[t[:i]], ranks[t[i:]], r) for t, r in ranks.items() for i in range(1, len(t)) if t[:i] in ranks and t[i:] in ranks]
        left, right, rank = (np.array(x, dtype=np.int64) for x in zip(*splits)) if splits else (np.zeros(0, np.int64),) * 3
        self.table = PairTable(left, right, rank, rank)
        names = np.array([f"{i} " for i in range(len(self.bytes))], dtype=bytes)
        self.decimals, self.decimal_size = names.view(np.uint8).reshape(len(names), -1), np.char.str_len(names)
        self.token_size = np.fromiter(map(len, self.bytes), np.int64, len(self.bytes))
        self.token_start, self.token_bytes = np.cumsum(self.token_size) - self.token_size, np.frombuffer(b"".join(self.bytes), dtype=np.uint8)
        flat, per = merge_all(self.single[self.token_bytes], self.token_size, self.table)
        found = np.full(len(per), -1)
        found[per == 1] = flat[(np.cumsum(per) - per)[per == 1]]
        self.odd = {self.bytes[i]: i for i in np.flatnonzero((found != np.arange(len(per))) & (self.token_size > 0)).tolist()}

    def pieces(self, pieces: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(flat ids, ids per piece); a piece that is itself in the vocabulary is its own id."""
        raw = [p.encode("utf-8", "surrogatepass") for p in pieces]
        own = np.array([self.ranks.get(b, -1) for b in raw], dtype=np.int64)
        todo = np.flatnonzero(own < 0)
        joined = [raw[i] for i in todo.tolist()]
        flat, sizes = merge_all(self.single[np.frombuffer(b"".join(joined), dtype=np.uint8)], np.fromiter(map(len, joined), np.int64, len(joined)), self.table)
        per = np.ones(len(raw), dtype=np.int64)
        per[todo] = sizes
        starts, out = np.cumsum(per) - per, np.empty(int(per.sum()), dtype=np.int64)
        out[starts[own >= 0]] = own[own >= 0]
        out[spread(starts[todo], sizes)] = flat
        return out, per

    def cut(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Spans of the texts. One starts with each text; at each space before a sign that is no white space, as the pattern takes such a space into the piece that
        follows; where a run of ASCII letters ends at another ASCII sign; and at a letter behind a line end or tab."""
        before, here = data[:-1], data[1:]
        begins = np.zeros(len(data), dtype=bool)
        begins[:-1] = (before == 32) & FOLLOWS[here]
        begins[1:] |= IS_LETTER[before] & ENDS_LETTERS[here] | IS_LETTER[here] & (before >= 9) & (before <= 13)
        begins[starts[starts < ends]] = True
        begins[ends[ends < len(data)]] = False  # the line ends between the texts
        first = np.flatnonzero(begins)
        of = np.searchsorted(starts, first, "right") - 1
        return first, np.minimum(np.append(first[1:], len(data)), ends[of]), of

    def learn(self, data: np.ndarray, first: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(flat ids, ids per span) of spans; one of ASCII letters, with a space before it or not, is one piece."""
        strange = np.concatenate([[0], np.cumsum(~IS_LETTER[data])])
        head = first + (data[first] == 32)
        plain = (strange[last] == strange[head]) & (last > head)
        one = np.flatnonzero(plain)
        sizes = (last - first)[one]
        flat, per = merge_all(self.single[data[spread(first[one], sizes)]], sizes, self.table)
        counts = np.empty(len(first), dtype=np.int64)
        counts[one] = per
        many = np.flatnonzero(~plain)
        found = [self.find(data[a:b].tobytes().decode("utf-8", "surrogatepass")) for a, b in zip(first[many].tolist(), last[many].tolist())]
        pieces, sizes = self.pieces([p for f in found for p in f])
        ends = np.concatenate([[0], np.cumsum([len(f) for f in found], dtype=np.int64)])
        ids_before = np.concatenate([[0], np.cumsum(sizes)])
        counts[many] = np.diff(ids_before[ends])
        out, at = np.empty(int(counts.sum()), dtype=np.int64), np.cumsum(counts) - counts
        out[spread(at[one], counts[one])] = flat
        out[spread(at[many], counts[many])] = pieces
        for i, span in self.odd_spans(data, first[one], last[one]):
            out[at[one[i]] : at[one[i]] + 1], counts[one[i]] = span, -counts[one[i]]
        if (counts < 0).any():
            keep = np.ones(len(out), dtype=bool)
            for i in np.flatnonzero(counts < 0).tolist():
                keep[at[i] + 1 : at[i] - counts[i]] = False
            out, counts = out[keep], np.where(counts < 0, 1, counts)
        return out, counts

    def odd_spans(self, data: np.ndarray, first: np.ndarray, last: np.ndarray) -> Iterator[tuple[int, int]]:
        """Spans that are in the vocabulary although merging doesn't lead to them, with their ids."""
        if self.odd:
            for i, (a, b) in enumerate(zip(first.tolist(), last.tolist())):
                if (r := self.odd.get(data[a:b].tobytes())) is not None:
                    yield i, r

    def ids(self, texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(flat ids, ids per text) of some texts at a time."""
        return ids_of(texts, self.key, self.cut, self.learn)

    def encode(self, texts: list[str | None]) -> list[np.ndarray]:
        """The ids of each text."""
        return [x for flat, per in self.ids(texts) for x in np.split(flat, np.cumsum(per)[:-1])]

    def written(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids as decimals, each with a space behind it; and how many signs each takes."""
        width = self.decimal_size[ids]
        return self.decimals[ids][np.arange(self.decimals.shape[1]) < width[:, None]], width

    def decoded(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes that the ids stand for; and how many each does."""
        sizes = self.token_size[ids]
        return self.token_bytes[spread(self.token_start[ids], sizes)], sizes

    def round_trips(self, texts: list[str | None]) -> Iterator[tuple[int, bytes, bytes]]:
        """Of each text the number of ids, the ids as decimals joined by spaces, and the bytes that they decode to."""
        for flat, per in self.ids(texts):
            names, width = self.written(flat)
            raw, sizes = self.decoded(flat)
            cut = np.concatenate([[0], np.cumsum(per)])
            a, b = (np.concatenate([[0], np.cumsum(x)])[cut].tolist() for x in (width, sizes))
            names, raw = names.tobytes(), raw.tobytes()
            for i, n in enumerate(per.tolist()):
                yield n, names[a[i] : max(a[i], a[i + 1] - 1)], raw[b[i] : b[i + 1]]

    def decode(self, ids) -> bytes:
        return b"".join(map(self.bytes.__getitem__, ids))


def codec_of(data: bytes, pattern: str) -> ByteCodec:
    """The codec of these ranks, built once per worker process."""
    held = worker_cache("codecs")
    key = hashlib.sha256(data + pattern.encode()).hexdigest()
    if key not in held:
        held[key] = ByteCodec(data, pattern)
    return held[key]


def map_encoded(docs: DataFrame, derive: Callable, schema: str, keep: list[str], text_col: str = "text", ranks_path: str | None = None, pattern: str | None = None) -> DataFrame:
    """`derive(kept columns, texts, codec)` on batches of rows: one pass, no shuffle.

    The vocabulary file is read on the driver and broadcast: its size is fixed. Ids never leave
    the worker unless `derive` returns them.
    """
    import public_tokenizers

    shared = docs.sparkSession.sparkContext.broadcast(read_bytes(ranks_path or vocabulary_file(RANKS_FILE)))
    pattern = pattern or public_tokenizers.PATTERN

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        codec = codec_of(shared.value, pattern)
        for part in slices(frames):
            yield derive(part[keep], part["__text"].tolist(), codec)

    return docs.select(*(col(c) for c in keep), col(text_col).alias("__text")).mapInPandas(work, schema)


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **how) -> DataFrame:
    """(id, ids array<int>) of each row."""
    kind = docs.select(col(id_col)).schema[0].dataType.simpleString()

    def derive(kept, texts, codec):
        return pd.DataFrame({"id": kept[id_col], "ids": codec.encode(texts)})

    return map_encoded(docs, derive, f"id {kind}, ids array<int>", [id_col], text_col, **how)


def decode(encoded: DataFrame, ids_col: str = "ids", ranks_path: str | None = None) -> DataFrame:
    """`encoded` with a binary column `decoded`; null ids decode to nothing."""
    import public_tokenizers
    from pyspark.sql import functions as F

    shared = encoded.sparkSession.sparkContext.broadcast(read_bytes(ranks_path or vocabulary_file(RANKS_FILE)))
    pattern = public_tokenizers.PATTERN

    def work(ids: pd.Series) -> pd.Series:
        codec = codec_of(shared.value, pattern)
        return pd.Series([b"" if x is None else codec.decode(list(x)) for x in ids])

    return encoded.withColumn("decoded", F.pandas_udf(work, "binary")(col(ids_col)))


def digests(docs: DataFrame, **how) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of each row of `docs`."""

    def derive(kept, texts, codec):
        made = [(n, hashlib.sha256(ids).hexdigest(), hashlib.sha256(raw).hexdigest()) for n, ids, raw in codec.round_trips(texts)]
        return pd.DataFrame(made, columns=["n_tokens", "ids_sha256", "decoded_sha256"]).assign(doc_id=kept["doc_id"].to_numpy())[["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"]]

    return map_encoded(docs, derive, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", ["doc_id"], **how)
