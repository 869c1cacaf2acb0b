"""Encoding of byte spans, many at once: equal spans are encoded once and looked up by a 64-bit hash.

Texts lie end to end in one array of bytes and are cut into spans that no token crosses. Spans are
hashed together by prefix sums; what a worker has learned is kept in sorted arrays, about 40 bytes
a span. When these have grown to their limit, spans that haven't been met again are dropped.
"""

from __future__ import annotations

import hashlib
import sys
import types
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd

from multiagg.llm.common import give_back, powers, runs, slices

#: Spans are hashed in stretches of about so many bytes.
SEGMENT = 1 << 20
#: Texts are encoded together up to about so many bytes.
TOGETHER = 4 << 20
#: Spans that a worker keeps.
KEPT = 1_500_000
#: Fixed odd multipliers of the hashes.
MIX = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5, 0x85EBCA77C2B2AE63], dtype=np.uint64)
LETTERS = np.random.default_rng(4211).integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)


def worker_cache(key: str) -> dict:
    """A dictionary that outlives the task in this worker process."""
    holder = sys.modules.setdefault("__multiagg_worker_cache__", types.ModuleType("__multiagg_worker_cache__"))
    return holder.__dict__.setdefault(key, {})


def forget_codecs() -> None:
    """Drop what earlier tasks have kept in this worker process and a task without a codec only carries along."""
    held = [worker_cache(key) for key in ("codecs", "word codecs", "memos")]
    if any(held):
        for h in held:
            h.clear()
        give_back()


def lean_slices(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """`slices` for a task without a codec."""
    forget_codecs()
    yield from slices(frames)


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    held = worker_cache("span powers")
    if "size" not in held or held["size"] < n:
        size = max(n, SEGMENT + 4096)
        held.update(size=size, tables=(powers(size, int(MIX[0])), powers(size, pow(int(MIX[0]), -1, 1 << 64))))
    power, back = held["tables"]
    return power[:n], back[:n]


def stretch_hashes(data: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Hashes of the bytes first..last-1 of one stretch."""
    power, back = span_powers(len(data) + 1)
    with np.errstate(over="ignore"):
        sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(LETTERS[data] * power[: len(data)])])
        return mixed((sums[last] - sums[first]) * back[first] + (last - first).astype(np.uint64) * MIX[2])


def span_hashes(data: np.ndarray, first: np.ndarray, last: np.ndarray) -> np.ndarray:
    """Hashes of ascending spans; a span beyond a stretch is hashed by itself."""
    out = np.empty(len(first), dtype=np.uint64)
    long_ = last - first > SEGMENT
    for i in np.flatnonzero(long_).tolist():
        out[i] = int.from_bytes(hashlib.blake2b(data[first[i] : last[i]].tobytes(), digest_size=8).digest(), "little")
    some = np.flatnonzero(~long_)
    k = 0
    while k < len(some):
        at = first[some[k]]
        end = max(k + 1, int(np.searchsorted(last[some], at + 2 * SEGMENT, "right")))
        part = some[k:end]
        out[part] = stretch_hashes(data[at : last[part[-1]]], first[part] - at, last[part] - at)
        k = end
    return out


def spread(starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The places start..start+size-1 of each stretch, end to end."""
    return np.repeat(starts, sizes) + runs(sizes)


class Memo:
    """Ids of the spans that this worker has met, by hash."""

    def __init__(self, limit: int = KEPT):
        self.limit = limit
        self.known, self.start, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.again, self.ids = np.zeros(0, bool), np.zeros(0, np.int32)

    def places(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where each hash stands, and whether it does."""
        if not len(self.known):
            return np.zeros(len(hashes), np.int64), np.zeros(len(hashes), bool)
        at = np.minimum(np.searchsorted(self.known, hashes), len(self.known) - 1)
        return at, self.known[at] == hashes

    def forget(self) -> None:
        if len(self.known) > self.limit:
            keep = np.flatnonzero(self.again)
            keep = keep[:: 1 + 2 * len(keep) // self.limit]
            self.ids = self.ids[spread(self.start[keep], self.size[keep])]
            self.known, self.size = self.known[keep], self.size[keep]
            self.start, self.again = np.cumsum(self.size) - self.size, np.zeros(len(keep), bool)

    def add(self, hashes: np.ndarray, flat: np.ndarray, sizes: np.ndarray) -> None:
        at = np.searchsorted(self.known, hashes)
        start = len(self.ids) + np.cumsum(sizes) - sizes
        self.known, self.start, self.size = np.insert(self.known, at, hashes), np.insert(self.start, at, start), np.insert(self.size, at, sizes)
        self.again = np.insert(self.again, at, False)
        self.ids = np.concatenate([self.ids, flat.astype(np.int32)])

    def encode(self, data: np.ndarray, first: np.ndarray, last: np.ndarray, learn: Callable) -> tuple[np.ndarray, np.ndarray]:
        """(flat ids, ids per span); `learn(first, last)` encodes spans that aren't held."""
        self.forget()
        distinct, where, which = np.unique(span_hashes(data, first, last), return_index=True, return_inverse=True)
        at, hit = self.places(distinct)
        self.again[at[hit]] = True
        new = np.flatnonzero(~hit)
        if new.size:
            order = new[np.argsort(where[new])]
            flat, sizes = learn(first[where[order]], last[where[order]])
            back = np.argsort(distinct[order])
            starts = np.cumsum(sizes) - sizes
            self.add(distinct[order][back], flat[spread(starts[back], sizes[back])], sizes[back])
            at, _ = self.places(distinct)
        sizes = self.size[at][which]
        return self.ids[spread(self.start[at][which], sizes)], sizes


def memo(key: str) -> Memo:
    """This worker's memo of one vocabulary."""
    held = worker_cache("memos")
    if key not in held:
        held[key] = Memo()
    return held[key]


def gathered(texts: list[str | None]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """Texts end to end with a line end between them, up to some size at a time: bytes, starts and ends of the texts."""
    held, size = [], 0
    for i, text in enumerate(texts):
        held.append((text or "").encode("utf-8", "surrogatepass"))
        size += len(held[-1]) + 1
        if size >= TOGETHER or i == len(texts) - 1:
            sizes = np.fromiter(map(len, held), np.int64, len(held))
            starts = np.cumsum(sizes + 1) - sizes - 1
            yield np.frombuffer(b"\n".join(held), dtype=np.uint8), starts, starts + sizes
            held, size = [], 0


def ids_of(texts: list[str | None], key: str, cut: Callable, learn: Callable) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(flat ids, ids per text) of some texts at a time. `cut(data, starts, ends)` gives the spans and the text of each, `learn(data, first, last)` their ids."""
    for data, starts, ends in gathered(texts):
        first, last, of = cut(data, starts, ends)
        if len(first):
            flat, sizes = memo(key).encode(data, first, last, lambda a, b, d=data: learn(d, a, b))
            yield flat, np.bincount(of, weights=sizes, minlength=len(starts)).astype(np.int64)
        else:
            yield np.zeros(0, np.int32), np.zeros(len(starts), np.int64)
