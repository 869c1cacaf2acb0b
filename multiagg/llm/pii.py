"""Personal data by fixed patterns and a linear-chain conditional random field.

The patterns find what is regular. The field reads words by their shape, with the shapes next to
them, and adds what the patterns leave: numbers written otherwise, keys and tokens. A word
without a digit or @ is bound to the tag O, so a text falls apart into runs of the other words,
and decoding each run with O on both sides is exact for the whole text. Runs are decoded by
Viterbi in numpy, many at once, in buckets by length.

The model is trained on the driver, from a small labelled table (`labelled_table`), and broadcast;
its size is fixed by `FEATURES`. Texts are read in one pass without a shuffle.

Defined results: a null text counts as empty and has no spans. Offsets are code points, ends
exclusive. A span of the field that touches one of the patterns' is left out. Repeated rows are
handled each by itself, and an empty table gives no row.
"""

from __future__ import annotations

import hashlib
import random
import re
import zlib
from collections.abc import Iterator
from functools import cache

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from multiagg.llm.common import col, fresh

KINDS = ("email", "ip", "card", "phone", "secret")
TAGS = ("O", "B-email", "I-email", "B-ip", "I-ip", "B-card", "I-card", "B-phone", "I-phone", "B-secret", "I-secret")
FEATURES = 1 << 13
SENTENCES = 500
EPOCHS = 50

IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
ACTIVE = re.compile(r"(?<![^\x20\x09-\x0D])[^\x20\x09-\x0D0-9@]*+[0-9@][^\x20\x09-\x0D]*+")
ANY = re.compile(r"[0-9@]")
NOT_DIGIT = re.compile(r"[^0-9]")
#: What of the tagged words is the span.
CORE = {
    "email": re.compile(r"[^\s\"'<>(),;:]+@[^\s\"'<>(),;:]*[^\s\"'<>(),;:.!?*#$&%]"),
    "ip": re.compile(r"[0-9A-Fa-f]+(?:[.:][0-9A-Fa-f]*){2,7}[0-9A-Fa-f]"),
    "card": re.compile(r"[0-9](?:[\x20.-]?[0-9]){12,18}"),
    "phone": re.compile(r"[+(]?(?:[0-9][\x20()./-]{0,3}){6,14}[0-9]"),
    "secret": re.compile(r"[A-Za-z0-9_+/=-]{16,}"),
}


def emails(text: str) -> list[tuple[int, int]]:
    """Leftmost, not overlapping; each @ looks back over its own run of letters only, so long runs cost no more."""
    out, free, at = [], 0, text.find("@")
    while at >= 0:
        start = at
        while start > free and text[start - 1] in LOCAL:
            start -= 1
        m = DOMAIN.match(text, at + 1) if start < at else None
        if m:
            out.append((start, m.end()))
            free = m.end()
        at = text.find("@", max(free, at + 1))
    return out


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (1 + i % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the fixed patterns, in order."""
    if not ANY.search(text):
        return []
    out = [(a, 0, b) for a, b in emails(text)] if "@" in text else []
    for m in IP.finditer(text):
        if all(len(p) <= 3 and int(p or "0") <= 255 for p in (x.lstrip("0") for x in m.group().split("."))):
            out.append((m.start(), 1, m.end()))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 14 and 14 <= len(d := NOT_DIGIT.sub("", m.group())) <= 19 and luhn(d):
            out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 10 <= len(NOT_DIGIT.sub("", m.group())) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


def shape(word: str) -> str:
    """Letters as x, digits as 9 with their number up to 9 and beyond, other signs as they are, runs of one sign once."""
    out = re.sub(r"[A-Za-z]+", "x", word)
    out = re.sub(r"[0-9]+", lambda m: f"9{min(len(m.group()), 10)}", out)
    out = re.sub(r"[^\x00-\x7f]+", "u", out)
    return re.sub(r"([^9x0-9])\1+", r"\1", out)[:40]


def features(words: list[str], i: int, before: str, after: str) -> list[int]:
    """Places of the word's features; `before` and `after` are the words around the run."""
    w = words[i]
    prev, next_ = (words[i - 1] if i else before), (words[i + 1] if i + 1 < len(words) else after)
    s, n = shape(w), sum(c.isdigit() for c in w)
    p, q = shape(prev), shape(next_)
    hexes = bool(re.search(r"[0-9a-fA-F]{24,}", w))
    run = max((len(x) for x in re.findall(r"[A-Za-z0-9_+/=-]+", w)), default=0)
    mixed = bool(re.search(r"[A-Za-z]", w)) and n > 0
    names = (
        "bias", f"s{s}", f"n{min(n, 20)}", f"p{p}", f"q{q}", f"ps{p}|{s}", f"sq{s}|{q}", f"w-{prev.lower().strip('.,;:()')[:20]}", f"at{'@' in w}",
        f"hex{hexes}", f"run{min(run // 8, 5)}|{mixed}", f"head{s[:2]}", f"tail{s[-2:]}", f"dots{min(w.count('.'), 4)}|{n > 0}", f"colons{min(w.count(':'), 5)}",
    )
    return [zlib.crc32(x.encode("utf-8", "replace")) % FEATURES for x in names]


def labelled_table(seed: int = 7, sentences: int = SENTENCES) -> list[tuple[list[str], list[str]]]:
    """The small labelled table: (words, tags) made from patterns of writing, with unmarked numbers among them."""
    r = random.Random(seed)
    digits = lambda n: "".join(r.choice("0123456789") for _ in range(n))
    plain = ["the", "of", "and", "la", "de", "der", "und", "thention", "ouer", "stand", "on", "call", "see", "at", "in", "from", "is", "para", "que"]
    host = lambda: f"{r.choice(['mail', 'host', 'web', 'corp'])}{r.choice(['', digits(1)])}"

    def whole(kind: str, text: str) -> list[tuple[str, str]]:
        return [(w, ("B-" if i == 0 else "I-") + kind) for i, w in enumerate(text.split())]

    def other(*choices: str) -> list[tuple[str, str]]:
        return [(w, "O") for w in r.choice(choices).split()]

    def entity() -> list[tuple[str, str]]:
        pick = r.randrange(12)
        if pick == 0:
            return whole("email", f"{r.choice(plain)}.{digits(2)}@{host()}.{r.choice(['example.com', 'org', 'net'])}{r.choice(['', '.', ',', '***'])}")
        if pick == 1:
            return whole("ip", ".".join(str(r.randrange(256)) for _ in range(4)) + r.choice(["", ".", ",", ":8080"]))
        if pick == 2:
            return whole("ip", ":".join("".join(r.choice("0123456789abcdef") for _ in range(4)) for _ in range(8)))
        if pick == 3:
            return whole("card", r.choice([" ", "-"]).join(digits(4) for _ in range(4)))
        if pick == 4:
            return whole("phone", f"+{r.choice('1234')} ({digits(3)}) {digits(3)}-{digits(4)}")
        if pick == 5:
            return whole("phone", r.choice([f"({digits(3)}) {digits(3)}-{digits(4)}", f"{digits(3)}-{digits(3)}-{digits(4)}", f"{digits(3)}.{digits(3)}.{digits(4)}"]))
        if pick == 6:
            return whole("phone", f"+{r.choice(['33', '49', '34'])} {digits(1)} {digits(2)} {digits(2)} {digits(2)} {digits(2)}")
        secret = "".join(r.choice("0123456789abcdef") for _ in range(r.choice([32, 40, 64]))) if pick < 10 else "".join(r.choice("0123456789abcdefghijkLMNOPQRSTUVWXYZ") for _ in range(r.choice([20, 32, 40])))
        name = r.choice(["token", "key", "api_key", "secret", "password", "access_token"])
        return [*other(*[f"{name} =", f"{name}:", f"{name} is"]), (r.choice(['"{}"', "'{}'", "{}"]).format(secret) + r.choice(["", "", ".", "***", "###"]), "B-secret")]

    def number() -> list[tuple[str, str]]:
        return other(
            digits(1), digits(2) + ".", digits(4), f"19{digits(2)}", f"20{digits(2)},", f"{digits(1)}.{digits(1)}.", f"{digits(1)}.{digits(1)}.{digits(1)}", f"v{digits(1)}.{digits(1)}",
            f"version {digits(1)}.", f"${digits(3)}.{digits(2)}", f"{digits(2)}%", f"{digits(2)}:{digits(2)}", f"20{digits(2)}-0{r.randrange(1, 10)}-1{r.randrange(10)}", f"{digits(1)},{digits(3)}",
            f"{digits(2)} {digits(2)}", f"no. {digits(3)}", f"{digits(5)}", f"{digits(6)}", f"{digits(3)} {digits(3)}", f"{digits(1)}/{digits(1)}", f"x{digits(2)}", f"a{digits(1)}b", f"{digits(1)}st", f"@{r.choice(plain)}", f"CC BY-NC {digits(1)}.0.",
            f"{digits(4)} {digits(4)}", f"{digits(2)}.{digits(2)}.20{digits(2)}", f"{digits(12)}", f"({digits(4)})", f"({digits(2)})", f"({digits(3)})", "@", f"ISO-{digits(4)}", f"{digits(2)}-{digits(2)}", f"item{digits(3)}_{digits(2)}",
        )

    out = []
    for _ in range(sentences):
        line: list[tuple[str, str]] = []
        for _ in range(r.randrange(2, 6)):
            line += [(r.choice(plain), "O") for _ in range(r.randrange(1, 4))] + (entity() if r.random() < 0.5 else number())
        line += [(r.choice(plain), "O")]
        out.append(([w for w, _ in line], [t for _, t in line]))
    return out


def active_runs(words: list[str]) -> list[tuple[int, int]]:
    out, i = [], 0
    while i < len(words):
        if ANY.search(words[i]):
            j = i
            while j < len(words) and ANY.search(words[j]):
                j += 1
            out.append((i, j))
            i = j
        else:
            i += 1
    return out


class ChainField:
    """Weights of words (features x tags) and of neighbouring tags; sequences stand between two O."""

    def __init__(self, emit: np.ndarray, move: np.ndarray):
        self.emit, self.move = emit, move

    def scores(self, rows: np.ndarray) -> np.ndarray:
        return self.emit[rows].sum(-2)

    def decode(self, sequences: list[np.ndarray]) -> list[np.ndarray]:
        """Best tags of each sequence, given as features (words x places); buckets by length, one matrix step per word."""
        out: list = [None] * len(sequences)
        sizes = np.array([len(s) for s in sequences], dtype=np.int64)
        order, k = np.argsort(sizes, kind="stable"), 0
        while k < len(order):
            most = max(1, int(sizes[order[k]] * 1.3))
            last = min(int(np.searchsorted(sizes[order], most, side="right")), k + 4096)
            group, k = order[k:last], last
            n, longest = sizes[group], int(sizes[group].max())
            scores = np.zeros((longest, len(group), len(TAGS)), dtype=np.float32)
            for g, i in enumerate(group):
                scores[: sizes[i], g] = self.scores(sequences[i])
            back = np.zeros((longest, len(group), len(TAGS)), dtype=np.int8)
            best, final = self.move[0][None, :] + scores[0], np.zeros((len(group), len(TAGS)), dtype=np.float32)
            final[n == 1] = best[n == 1]
            for t in range(1, longest):
                through = best[:, :, None] + self.move[None]
                back[t] = through.argmax(1)
                best = through.max(1) + scores[t]
                final[n == t + 1] = best[n == t + 1]
            tag = (final + self.move[:, 0]).argmax(1)
            path = np.zeros((longest, len(group)), dtype=np.int8)
            for t in range(longest - 1, -1, -1):
                path[t] = tag
                tag = np.where(t < n, back[t][np.arange(len(group)), tag], tag) if t else tag
            for g, i in enumerate(group):
                out[i] = path[: sizes[i], g]
        return out


def _log_sum(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis, keepdims=True)
    return np.squeeze(top, axis) + np.log(np.exp(x - top).sum(axis))


def train(table: list[tuple[list[str], list[str]]], epochs: int = EPOCHS, rate: float = 0.4, shrink: float = 1e-4) -> ChainField:
    """Maximum likelihood by forward-backward over the runs of the table, with adaptive steps."""
    rows, tags = [], []
    for words, marks in table:
        for a, b in active_runs(words):
            rows.append(np.array([features(words[a:b], i, words[a - 1] if a else "", words[b] if b < len(words) else "") for i in range(b - a)]))
            tags.append(np.array([TAGS.index(m) for m in marks[a:b]]))
    n, longest, k, s = len(rows), max(map(len, rows)), rows[0].shape[1], len(TAGS)
    x, y, mask = np.zeros((n, longest, k), np.int64), np.zeros((n, longest), np.int64), np.zeros((n, longest), bool)
    for i, (f, t) in enumerate(zip(rows, tags)):
        x[i, : len(f)], y[i, : len(t)], mask[i, : len(t)] = f, t, True
    size = mask.sum(1)
    emit, move = np.zeros((FEATURES, s)), np.zeros((s, s))
    seen_e, seen_m = np.full_like(emit, 1e-6), np.full_like(move, 1e-6)
    gold_m = np.zeros((s, s))
    full = np.concatenate([np.zeros((n, 1), np.int64), y, np.zeros((n, 1), np.int64)], 1)
    for t in range(longest + 1):
        on = t <= size
        to = np.where(t == size, 0, full[:, t + 1])
        np.add.at(gold_m, (full[on, t], to[on]), 1)
    for _ in range(epochs):
        sc = emit[x].sum(2)
        alpha = np.zeros((longest, n, s))
        alpha[0] = move[0] + sc[:, 0]
        for t in range(1, longest):
            new = _log_sum(alpha[t - 1][:, :, None] + move[None], 1) + sc[:, t]
            alpha[t] = np.where(mask[:, t][:, None], new, alpha[t - 1])
        z = _log_sum(alpha[-1] + move[:, 0], 1)
        beta = np.zeros((longest, n, s))
        beta[-1] = move[:, 0]
        expect_m = np.zeros((s, s))
        for t in range(longest - 2, -1, -1):
            inner = move[None] + (sc[:, t + 1] + beta[t + 1])[:, None, :]
            p = np.exp(alpha[t][:, :, None] + inner - z[:, None, None]) * mask[:, t + 1][:, None, None]
            expect_m += p.sum(0)
            beta[t] = np.where(mask[:, t + 1][:, None], _log_sum(inner, 2), beta[t + 1])
        post = np.exp(alpha.transpose(1, 0, 2) + beta.transpose(1, 0, 2) - z[:, None, None]) * mask[:, :, None]
        expect_m[0] += post[:, 0].sum(0)
        expect_m[:, 0] += post[np.arange(n), size - 1].sum(0)
        error = -post
        np.add.at(error, (np.nonzero(mask)[0], np.nonzero(mask)[1], y[mask]), 1)
        grad = np.zeros_like(emit)
        np.add.at(grad, x[mask], error[mask][:, None, :])
        grad -= shrink * n * emit
        step = gold_m - expect_m - shrink * n * move
        seen_e += grad**2
        seen_m += step**2
        emit += rate * grad / np.sqrt(seen_e)
        move += rate * step / np.sqrt(seen_m)
    return ChainField(emit.astype(np.float32), move.astype(np.float32))


@cache
def model() -> ChainField:
    return train(labelled_table())


def word_runs(text: str) -> list[tuple[list[tuple[int, int]], str, str]]:
    """Runs of words with a digit or @: their places, and the words before and after the run."""
    out: list = []
    for m in ACTIVE.finditer(text):
        if out and text[out[-1][-1][1] : m.start()].isspace():
            out[-1].append(m.span())
        else:
            out.append([m.span()])
    near = lambda t, i: (t.split() or [""])[i]
    return [(r, near(text[max(0, r[0][0] - 40) : r[0][0]], -1), near(text[r[-1][1] : r[-1][1] + 40], 0)) for r in out]


def find_spans(texts: list[str | None], field: ChainField) -> list[tuple[list, list]]:
    """For each text its (start, kind, end): those of the patterns, and all."""
    out, asked, sequences = [], [], []
    for n, text in enumerate(texts):
        base = base_spans(text) if text else []
        out.append((base, list(base)))
        if text and ANY.search(text):
            for places, before, after in word_runs(text):
                words = [text[a:b] for a, b in places]
                asked.append((n, places))
                sequences.append(np.array([features(words, i, before, after) for i in range(len(words))]))
    for (n, places), tags in zip(asked, field.decode(sequences)):
        i = 0
        while i < len(tags):
            if tags[i]:
                kind, j = (tags[i] - 1) // 2, i + 1
                while j < len(tags) and tags[j] == 2 * kind + 2:
                    j += 1
                start, end = places[i][0], places[j - 1][1]
                m = CORE[KINDS[kind]].search(texts[n], start, end)
                if m and not any(a < m.end() and m.start() < b for a, _, b in out[n][0]):
                    out[n][1].append((m.start(), kind, m.end()))
                i = j
            else:
                i += 1
    return [(base, sorted(set(full))) for base, full in out]


def written(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def redacted(text: str, spans: list[tuple[int, int, int]]) -> str:
    """Each span, or run of overlapping spans, becomes the first one's kind in angle brackets."""
    out, at = [], 0
    for a, k, b in spans:
        if a >= at:
            out += [text[at:a], f"<{KINDS[k].upper()}>"]
        at = max(at, b)
    return "".join([*out, text[at:]])


FOUND = "base array<struct<start:long,kind:string,end:long>>, spans array<struct<start:long,kind:string,end:long>>, redacted string"


def pii(docs: DataFrame, text: Column, into: str, batch: int = 512) -> DataFrame:
    """`docs` with a struct column `into`: spans of the patterns, all spans, and the text without them."""
    # Plain arrays: broadcasts pickle classes by reference, and workers need not have this package.
    shared = docs.sparkSession.sparkContext.broadcast((model().emit, model().move))

    def work(texts: pd.Series) -> pd.DataFrame:
        rows, field = [], ChainField(*shared.value)
        for k in range(0, len(texts), batch):
            some = texts.iloc[k : k + batch].tolist()
            for t, (base, full) in zip(some, find_spans(some, field)):
                rows.append((*([{"start": a, "kind": KINDS[k], "end": b} for a, k, b in x] for x in (base, full)), redacted(t, full) if t is not None else None))
        return pd.DataFrame(rows, columns=["base", "spans", "redacted"])

    return docs.withColumn(into, F.pandas_udf(work, FOUND)(text))


def span_digests(docs: DataFrame) -> DataFrame:
    """doc_id, counts of the patterns' spans, their digest, and all spans as written."""
    found = pii(docs.select("doc_id", "text"), F.col("text"), "found")
    line = lambda x: F.array_join(F.transform(x, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    count = lambda kind: F.size(F.filter("found.base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", *map(count, KINDS[:4]), F.sha2(line(F.col("found.base")).cast("binary"), 256).alias("base_sha256"), line(F.col("found.spans")).alias("spans"))


def redact(docs: DataFrame, text_col: str = "text", length_col: str | None = None) -> DataFrame:
    """`docs` with spans in the text replaced by their kinds; `length_col`, if given, counts the new text's code points."""
    x = fresh(docs, "__found")
    out = pii(docs, col(text_col), x).withColumn(text_col, F.col(f"{x}.redacted")).drop(x)
    return out.withColumn(length_col, F.length(col(text_col)).cast(docs.schema[length_col].dataType)) if length_col else out
