"""Jaccard join on word n-grams by token-combination prefixes.

A document is its set of word shingles. Sets are ordered rare tokens first, then the frequent ones
(the `FREQUENT` most common, a table of fixed size) from the least to the most common. A set's
prefix is just long enough that two sets which link must share a signature in their prefixes: a
rare token counts by itself, frequent tokens count in pairs from one group, and each group costs
one more token of prefix. Prefixes are therefore extended where tokens are frequent.

Each signature carries its reach: so many tokens two sets can share at most if this is the first
signature they share. A linking pair passes this bound, and the bound on sizes, in the list of its
first common signature, so every list may drop the pairs that don't.

Only components are asked for. Lists up to `SHORT_LIST` sets are paired out. Of a longer list every
member is compared with the hub, the member with the fewest rare tokens. What then still lies outside
the hub's component is paired with those of the list that sizes and reach leave: it meets the list's
distinct sizes first, and members by (signature, size). Candidates are sifted by sketches, the numbers
of a set's tokens in each of some classes, whose lesser numbers add up to a bound of what two sets
share; what is left is verified on the whole sets.

Equal sets are folded to one before anything else, so copies cost nothing, and they are linked by
definition. Tokens are 64-bit hashes of word sequences; sets are told apart by 128 bits.

Defined results: a null text, or one without words, has an empty set and links with nothing; its
component is itself. With fewer words than `n` the whole sequence is the one shingle. Rows with
one id are one document in the result's components, and each is returned. A null id is returned
with a null component unless a linked row has an id. An empty table gives no row.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator
from math import ceil, floor, log

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from multiagg.llm.common import batches_of, bitmap, bits_for, checkpointed, col, distinct, fresh, in_bitmap, tabled
from multiagg.llm.components import components
from multiagg.llm.spans import MIX, SEGMENT, lean_slices, mixed, stretch_hashes

WORDS = 4
#: A link: PERCENT of the union is shared.
PERCENT = 85
FREQUENT = 1 << 18
#: Tokens counted less often than this are never frequent.
FREQUENT_FROM = 3
SHORT_LIST = 8
CHUNK_TOKENS = 2_000_000
#: Rows that go to Python at once: whole texts, or the sets of both ends of a pair.
BATCH = 1024
#: Ratio of sizes within which frequent tokens are grouped alike.
STEP = 1.6
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
LOWER[9:14] = 32
SPACE = re.compile(rb"[\x20\x09-\x0D]")


def word_hashes(raw: bytes) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the words of some bytes, and where each starts; letters A-Z are lowered, words end at ASCII white space."""
    hashes, starts, at = [], [], 0
    while at < len(raw):
        stop = len(raw)
        if stop - at > SEGMENT:
            cut = SPACE.search(raw, at + SEGMENT)
            stop = cut.end() if cut else stop
        data = LOWER[np.frombuffer(raw, np.uint8, stop - at, at)]
        inside = np.concatenate([[0], data != 32, [0]]).astype(np.int8)
        edge = np.diff(inside)
        first, last = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        hashes.append(stretch_hashes(data, first, last))
        starts.append(first + at)
        at = stop
    return (np.concatenate(hashes), np.concatenate(starts)) if hashes else (np.zeros(0, np.uint64), np.zeros(0, np.int64))


def shingle_sets(texts, n: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct hashes of each text's shingles; many texts are hashed together."""
    out: list[np.ndarray] = []
    held, size = [], 0
    for text in texts:
        raw = (text or "").encode("utf-8", "replace")
        held.append(raw)
        size += len(raw)
        if size >= SEGMENT // 2:
            out += _sets(held, n)
            held, size = [], 0
    return out + (_sets(held, n) if held else [])


def _sets(raws: list[bytes], n: int) -> list[np.ndarray]:
    h, start = word_hashes(b" ".join(raws))
    ends = np.cumsum([len(r) + 1 for r in raws])
    cut = np.searchsorted(start, ends)
    with np.errstate(over="ignore"):
        total = np.full(max(len(h) - n + 1, 0), n, dtype=np.uint64)
        for i in range(n):
            total = (total + h[i : len(h) - n + 1 + i]) * MIX[i % 5] + np.uint64(i + 1)
    whole = mixed(total)
    out, low = [], 0
    for i, high in enumerate(cut.tolist()):
        k = high - low
        if k >= n:
            out.append(distinct(whole[low : high - n + 1]))
        elif k:
            with np.errstate(over="ignore"):
                short = np.array([k], dtype=np.uint64)
                for j in range(k):
                    short = (short + h[low + j]) * MIX[j % 5] + np.uint64(j + 1)
            out.append(mixed(short + MIX[1]))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
        low = high
    return out


def set_name(tokens: np.ndarray) -> bytes:
    return hashlib.blake2b(tokens.tobytes(), digest_size=16).digest()


def needed(n: int, percent: int) -> int:
    """So many tokens can't all be missing from a set that links."""
    return n - ceil(percent * n / 100) + 1


def least_size(percent: int) -> int:
    """The smallest set that can link with a different one."""
    return ceil(percent / (100 - percent))


def scheme(n: int, percent: int) -> int:
    """Sizes in steps that are wider than two linked sets can differ."""
    return floor(log(n) / log(max(STEP, 1.06 * 100 / percent)))


def groups_in(s: int, percent: int) -> int:
    """Groups of frequent tokens for sets of this scheme; three needed tokens to two groups, so few pairs to a token."""
    start = max(STEP, 1.06 * 100 / percent) ** s
    return max(1, floor(start * (100 - percent) / 150))


def ranked(tokens: np.ndarray, frequent: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """The rank of each token among the frequent ones, from the least common; -1 for rare tokens. `frequent`: sorted tokens, their ranks."""
    known, ranks = frequent
    if not len(known):
        return np.full(len(tokens), -1, dtype=np.int64)
    at = np.minimum(np.searchsorted(known, tokens), len(known) - 1)
    return np.where(known[at] == tokens, ranks[at], -1)


def signatures(tokens: np.ndarray, rank: np.ndarray, percent: int = PERCENT) -> tuple[np.ndarray, np.ndarray]:
    """A set's signatures and their reach, given its tokens' ranks: even ones are rare tokens, odd ones pairs of frequent tokens.

    Two linked sets whose prefixes share no rare token have two shared tokens of one group in both
    prefixes: else, in the prefix that ends first, all but the first token of each group were missing
    from the other set. Before the second token of such a pair they share one of each group at most.
    """
    n = len(tokens)
    if n < least_size(percent):
        return np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int32)
    common = rank >= 0
    rare, often, need = tokens[~common], tokens[common], needed(n, percent)
    one, two = np.uint64(1), ~np.uint64(1)
    with np.errstate(over="ignore"):
        out, reach = [mixed(rare[:need] * MIX[4]) & two], [n - np.arange(min(len(rare), need))]
        if len(rare) < need:
            often = often[np.argsort(rank[common])]
            for s in {scheme(n, percent), scheme(ceil(percent * n / 100), percent)}:
                group = (mixed(often ^ MIX[3]) % np.uint64(groups_in(s, percent))).astype(np.int64)
                first = np.zeros(len(often), dtype=bool)
                first[np.unique(group, return_index=True)[1]] = True
                size = int(np.searchsorted(np.cumsum(~first), need - len(rare))) + 1
                chosen, group = often[:size], group[:size]
                past = np.cumsum(first[:size]) - first[:size]
                most = np.minimum(past + n - len(rare) - np.arange(len(chosen)), len(often))
                order = np.argsort(group, kind="stable")
                for part in np.split(order, np.flatnonzero(np.diff(group[order])) + 1):
                    i, j = np.triu_indices(len(part), 1)
                    i, j = part[i], part[j]
                    keep = 100 * most[j] >= percent * n
                    out.append(mixed(chosen[i[keep]] * MIX[0] + chosen[j[keep]] * MIX[1] + np.uint64(s)) | one)
                    reach.append(most[j[keep]])
    return np.concatenate(out).view(np.int64), np.concatenate(reach).astype(np.int32)


def sketch(tokens: np.ndarray) -> bytes:
    """How many tokens are in each of about a third as many classes; nothing if a number takes more than a byte."""
    classes = 1 << max((len(tokens) // 3).bit_length() - 1, 0)
    counts = np.bincount((tokens & np.uint64(classes - 1)).astype(np.int64), minlength=classes)
    return counts.astype(np.uint8).tobytes() if counts.max(initial=0) < 256 else b""


def sketches_allow(a: bytes, b: bytes, percent: int) -> bool:
    """Whether two sets may link: of each class they share the lesser number at most. Classes of the larger set are folded to those of the smaller."""
    if not a or not b:
        return True
    p, q = (np.frombuffer(x, np.uint8).astype(np.int64) for x in (a, b))
    width = min(len(p), len(q))
    most = int(np.minimum(p.reshape(-1, width).sum(0), q.reshape(-1, width).sum(0)).sum())
    return 100 * most >= percent * (int(p.sum()) + int(q.sum()) - most)


def _texts(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(col(id_col).alias("doc_id"), F.xxhash64(col(text_col)).alias("body_key"), col(text_col).alias("text"))


def frequent_tokens(docs: DataFrame, text_col: str = "text", n: int = WORDS, most: int = FREQUENT, least: int = FREQUENT_FROM) -> tuple[np.ndarray, np.ndarray]:
    """The most common tokens of the corpus, at most `most`: sorted, and their ranks by count, the least common first.

    Tasks count tokens over stretches of distinct sets and report those they met twice; so counts
    run low for tokens that are thinly spread, which moves them to the rare ones and loses no link.
    """

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held, size, seen = [], 0, set()

        def counted() -> pd.DataFrame:
            tokens = np.sort(np.concatenate(held)) if held else np.zeros(0, np.uint64)
            again = np.flatnonzero(np.concatenate([[False], tokens[1:] == tokens[:-1]]))
            repeated = distinct(tokens[again])
            return pd.DataFrame({"token": repeated.view(np.int64), "times": np.searchsorted(tokens, repeated, "right") - np.searchsorted(tokens, repeated)})

        for frame in lean_slices(frames):
            for tokens in shingle_sets(frame["text"], n):
                name = set_name(tokens)
                if name in seen:
                    continue
                seen.add(name)
                held.append(tokens)
                size += len(tokens)
                if size >= CHUNK_TOKENS:
                    yield counted()
                    held, size, seen = [], 0, set()
        yield counted()

    counts = docs.select(col(text_col).alias("text")).mapInPandas(work, "token long, times long").groupBy("token").agg(F.sum("times").alias("times"))
    counts = counts.where(F.col("times") >= least).select("token", "times", F.expr("shiftleft(times, 20) | (xxhash64(token) & 1048575L)").alias("key"))
    counts = tabled(counts, "counts")
    found = counts.where(F.col("key") >= _least_key(counts, most)).select("token", "times").toArrow()
    tokens, times = found["token"].to_numpy().view(np.uint64), found["times"].to_numpy()
    ranks = np.empty(len(tokens), dtype=np.int32)
    ranks[np.lexsort((tokens, times))] = np.arange(len(tokens), dtype=np.int32)
    order = np.argsort(tokens)
    return tokens[order], ranks[order]


def _least_key(counts: DataFrame, most: int) -> int:
    """A key that nearly `most` rows reach, and no more; found in ranges that are split again until a hundredth of `most` is left open."""
    low, high, room = 0, 1 + (counts.agg(F.max("key")).first()[0] or 0), most
    while True:
        width = max(1, -(-(high - low) // 256))
        rows = counts.where(F.col("key").between(low, high - 1)).groupBy(F.expr(f"(key - {low}) div {width}").alias("part")).agg(F.count("*").alias("n")).collect()
        for part, n in sorted(((r["part"], r["n"]) for r in rows), reverse=True):
            if n > room:
                break
            room -= n
        else:
            return low
        low, high = low + part * width, min(high, low + (part + 1) * width)
        if width == 1 or 100 * room <= most:
            return high


def profiles(docs: DataFrame, frequent: tuple[np.ndarray, np.ndarray], id_col: str, text_col: str, n: int, percent: int) -> DataFrame:
    """(doc_id, body_key, n_shingles, n_frequent, name, sketch, signatures, reach) of every row; within a task, repeats of a set leave out the last three."""
    kind = docs.select(col(id_col)).schema[0].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(frequent)

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: set[bytes] = set()
        for frame in lean_slices(frames):
            rows = []
            for doc, key, tokens in zip(frame["doc_id"], frame["body_key"], shingle_sets(frame["text"], n)):
                name = set_name(tokens)
                if name in seen:
                    rows.append((doc, key, len(tokens), 0, name, b"", np.zeros(0, np.int64), np.zeros(0, np.int32)))
                    continue
                seen.add(name)
                rank = ranked(tokens, shared.value)
                rows.append((doc, key, len(tokens), int((rank >= 0).sum()), name, sketch(tokens), *signatures(tokens, rank, percent)))
            yield pd.DataFrame(rows, columns=["doc_id", "body_key", "n_shingles", "n_frequent", "name", "sketch", "signatures", "reach"])

    return _texts(docs, id_col, text_col).mapInPandas(work, f"doc_id {kind}, body_key long, n_shingles long, n_frequent long, name binary, sketch binary, signatures array<long>, reach array<int>")


def sets_of(docs: DataFrame, profiled: DataFrame, names: DataFrame, id_col: str, text_col: str, n: int) -> DataFrame:
    """(name, tokens) of the asked sets, from one row each.

    The texts are scanned once more and not shuffled: a bitmap of the asked rows, of fixed size, is broadcast. It lets a few others through, which nothing asks for.
    """
    chosen = profiled.join(names, "name", "left_semi").groupBy("name").agg(F.min(F.struct("doc_id", "body_key")).alias("row"))
    marks = chosen.select(F.xxhash64("row.doc_id", "row.body_key").alias("r"))
    both = checkpointed(marks.select(F.explode(F.array("r", F.xxhash64("r"))).alias("r")))
    shared = docs.sparkSession.sparkContext.broadcast(bitmap(both, "r", bits_for(both.count())))

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in lean_slices(frames):
            asked = frame["text"][in_bitmap(frame["r"].to_numpy(dtype=np.int64), shared.value) & in_bitmap(frame["r2"].to_numpy(dtype=np.int64), shared.value)]
            sets = shingle_sets(asked, n)
            yield pd.DataFrame({"name": [set_name(s) for s in sets], "tokens": [s.tobytes() for s in sets]})

    rows = _texts(docs, id_col, text_col).select(F.xxhash64("doc_id", "body_key").alias("r"), "text").select("r", F.xxhash64("r").alias("r2"), "text")
    made = tabled(rows.mapInPandas(work, "name binary, tokens binary"), "sets")
    # A set that came twice is only compared twice; were many to come often, the bitmap being full, they are folded.
    often = made.groupBy("name").agg(F.count("*").alias("times")).where("times > 4")
    return made if often.isEmpty() else made.dropDuplicates(["name"])


def sifted(pairs: DataFrame, sketches: DataFrame, percent: int) -> DataFrame:
    """The pairs (x, y, c) whose sketches allow a link."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            yield frame.loc[np.array([sketches_allow(a, b, percent) for a, b in zip(frame["sx"], frame["sy"])], dtype=bool), ["x", "y", "c"]]

    left, right = sketches.select(F.col("name").alias("x"), F.col("sketch").alias("sx")), sketches.select(F.col("name").alias("y"), F.col("sketch").alias("sy"))
    return pairs.join(left, "x").join(right, "y").select("x", "y", "c", "sx", "sy").mapInPandas(work, "x binary, y binary, c long")


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (x, y) whose whole sets link."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in lean_slices(frames):
            keep = []
            for a, b in zip(frame["tx"], frame["ty"]):
                p, q = np.frombuffer(a, np.uint64), np.frombuffer(b, np.uint64)
                both = np.concatenate([p, q])
                both.sort()
                shared = int((both[1:] == both[:-1]).sum())
                keep.append(100 * shared >= percent * (len(p) + len(q) - shared))
            yield frame.loc[np.array(keep, dtype=bool), ["x", "y"]]

    left, right = sets.select(F.col("name").alias("x"), F.col("tokens").alias("tx")), sets.select(F.col("name").alias("y"), F.col("tokens").alias("ty"))
    return pairs.join(left, "x").join(right, "y").select("x", "y", "tx", "ty").mapInPandas(work, "x binary, y binary")


def _may_link(percent: int) -> str:
    """On (nx, rx, ny, ry): sizes and reach allow a link."""
    return f"100 * least(nx, ny) >= {percent} * greatest(nx, ny) and 100 * least(rx, ry) >= {percent} * (nx + ny - least(rx, ry))"


def _ordered(pairs: DataFrame) -> DataFrame:
    """(x, y), the greater name as x."""
    return pairs.select(F.greatest("x", "y").alias("x"), F.least("x", "y").alias("y"))


def set_links(docs: DataFrame, profiled: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """Links between different sets that span their components: (x, y) by name."""
    each = profiled.select(F.xxhash64("name").alias("set"), F.explode("signatures").alias("sig"))
    repeated = checkpointed(each.groupBy("sig").agg(F.min("set").alias("a"), F.max("set").alias("b")).where("a <> b").select("sig"))
    sketches = tabled(profiled.where("size(signatures) > 0").groupBy("name").agg(F.first("sketch").alias("sketch")), "sketches")
    shared = docs.sparkSession.sparkContext.broadcast(bitmap(repeated, "sig", bits_for(repeated.count())))

    def again(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in lean_slices(frames):
            hits = [in_bitmap(s, shared.value) for s in frame["signatures"]]
            found = frame.assign(signatures=[s[h] for s, h in zip(frame["signatures"], hits)], reach=[r[h] for r, h in zip(frame["reach"], hits)])
            yield found[[bool(h.any()) for h in hits]]

    may = profiled.where("size(signatures) > 0").select("name", F.col("n_shingles").alias("n"), F.col("n_frequent").alias("f"), "signatures", "reach")
    may = may.mapInPandas(again, "name binary, n long, f long, signatures array<long>, reach array<int>")
    posted = may.select("name", "n", "f", F.explode(F.arrays_zip("signatures", "reach")).alias("s")).select("name", "n", "f", F.col("s.signatures").alias("sig"), F.col("s.reach").cast("long").alias("r"))
    posted = tabled(posted.groupBy("sig", "name").agg(F.first("n").alias("n"), F.first("f").alias("f"), F.max("r").alias("r")), "posted")
    hub = F.min(F.struct((F.col("n") - F.col("f")).alias("rare"), F.col("name").alias("hub"), F.col("n").alias("hub_n")))
    lists = checkpointed(posted.groupBy("sig").agg(F.count("*").alias("members"), hub.alias("h"), F.min("n").alias("smallest")).where("members > 1").select("sig", "members", "h.hub", "h.hub_n", "smallest"))
    listed = tabled(posted.join(lists, "sig"), "listed")
    in_short, in_long = listed.where(f"members <= {SHORT_LIST}"), listed.where(f"members > {SHORT_LIST}")
    pair = "struct(a.name as x, a.n as nx, a.r as rx, b.name as y, b.n as ny, b.r as ry)"
    few = in_short.groupBy("sig").agg(F.collect_list(F.struct("name", "n", "r")).alias("m"))
    few = few.select(F.explode(F.expr(f"flatten(transform(m, a -> transform(filter(m, b -> a.name > b.name), b -> {pair})))")).alias("p")).select("p.*")
    few = tabled(sifted(few.where(_may_link(percent)).groupBy("x", "y").agg(F.count("*").alias("c")), sketches, percent), "few")
    to_hub = in_long.where(f"name <> hub and 100 * least(n, hub_n) >= {percent} * greatest(n, hub_n)").select(F.greatest("name", "hub").alias("x"), F.least("name", "hub").alias("y"))
    to_hub = tabled(sifted(to_hub.groupBy("x", "y").agg(F.count("*").alias("c")), sketches, percent), "to_hub")
    # Each set is first compared with the hubs of its long lists and the one that it shares most lists with; then whatever still joins two components is.
    either = few.union(to_hub)
    both = either.select(F.col("x").alias("name"), F.struct("c", F.col("y").alias("other")).alias("b")).union(either.select("y", F.struct("c", F.col("x").alias("other"))))
    best = both.groupBy("name").agg(F.max("b").alias("b")).select(F.col("name").alias("x"), F.col("b.other").alias("y"))
    first = checkpointed(_ordered(best).union(to_hub.select("x", "y")).distinct())
    ends = lambda pairs: pairs.select(F.col("x").alias("name")).union(pairs.select("y")).distinct()
    named = checkpointed(ends(either))
    sets = sets_of(docs, profiled, named, id_col, text_col, n)

    def apart(pairs: DataFrame, roots: DataFrame) -> DataFrame:
        sides = [roots.select(F.col("node").alias(side + "n"), F.col("root").alias(side + "r")) for side in "xy"]
        joined = pairs.select("x", "y").join(sides[0], F.col("x") == F.col("xn"), "left").join(sides[1], F.col("y") == F.col("yn"), "left")
        return joined.where("coalesce(xr, x) <> coalesce(yr, y)").select("x", "y")

    links = checkpointed(verified(first, sets, percent))
    roots = components(links, "x", "y")
    root_of = lambda side: roots.select(F.col("node").alias(side + "n"), F.col("root").alias(side + "r"))
    member = in_long.select("sig", "name", "n", "r", "hub", "smallest").join(root_of("x"), F.col("name") == F.col("xn"), "left").join(root_of("y"), F.col("hub") == F.col("yn"), "left")
    member = tabled(member.select("sig", "name", "n", "r", "smallest", F.coalesce("xr", "name").alias("root"), F.coalesce("yr", "hub").alias("main")), "members")
    outside = member.where(f"root <> main and 100 * r >= {percent} * (n + smallest - r)").select("sig", F.col("name").alias("x"), F.col("n").alias("nx"), F.col("r").alias("rx"), F.col("root").alias("xr"))
    outside = checkpointed(outside)
    sizes = checkpointed(member.join(outside.select("sig").distinct(), "sig", "left_semi").groupBy("sig", F.col("n").alias("ny")).agg(F.max("r").alias("ry")))
    asked = outside.join(sizes, "sig").where(_may_link(percent)).drop("ry")
    others = member.select("sig", F.col("n").alias("ny"), F.col("name").alias("y"), F.col("r").alias("ry"), F.col("root").alias("yr"))
    more = _ordered(asked.join(others, ["sig", "ny"]).where(f"xr <> yr and {_may_link(percent)}"))
    more = sifted(more.distinct().withColumn("c", F.lit(0).cast("long")), sketches, percent).select("x", "y")
    later = apart(few, roots).union(more).distinct()
    second = checkpointed(later.join(first, ["x", "y"], "left_anti"))
    unknown = checkpointed(ends(second).join(named, "name", "left_anti"))
    if not unknown.isEmpty():
        sets = sets.unionByName(sets_of(docs, profiled, unknown, id_col, text_col, n))
    return links.unionByName(checkpointed(verified(second, sets, percent)))


def rooted_rows(docs: DataFrame, id_col: str, text_col: str, n: int, percent: int, most: int) -> DataFrame:
    """doc_id, n_shingles, component_id, body_key, and the component's root, which no other component has whatever the ids."""
    with batches_of(docs.sparkSession, BATCH):  # all that runs Python is run in here
        profiled = tabled(profiles(docs, frequent_tokens(docs, text_col, n, most), id_col, text_col, n, percent), "profiles")
        roots = components(set_links(docs, profiled, id_col, text_col, n, percent), "x", "y").withColumnRenamed("node", "name")
    rows = profiled.select("doc_id", "body_key", "n_shingles", "name")
    sets = checkpointed(rows.where("n_shingles > 0").groupBy("name").agg(F.min("doc_id").alias("least_id")))
    rooted = sets.join(roots, "name", "left").withColumn("root", F.coalesce("root", "name"))
    least = checkpointed(rooted.groupBy("root").agg(F.min("least_id").alias("component_id")))
    by_name = checkpointed(rooted.select("name", "root").join(least, "root").select("name", "root", "component_id"))
    return rows.join(by_name, "name", "left").select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"), "body_key", "root")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = WORDS, percent: int = PERCENT, most: int = FREQUENT) -> DataFrame:
    """One row per row of `docs`: doc_id, n_shingles, component_id (the least id in reach of links, its own included), body_key."""
    return rooted_rows(docs, id_col, text_col, n, percent, most).drop("root")


def drop_near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = WORDS, percent: int = PERCENT, most: int = FREQUENT) -> DataFrame:
    """`docs` with one row of each component, one with the least id (null comes last) and of that the least body key; rows without a shingle and all columns stay."""
    k, d, r = fresh(docs, "__body_key"), fresh(docs, "__id"), fresh(docs, "__repeats")
    found = rooted_rows(docs, id_col, text_col, n, percent, most)
    alike = found.where("n_shingles > 0").groupBy("root", "doc_id", "body_key").agg(F.count("*").alias("n"))
    best = alike.groupBy("root").agg(F.min(F.struct(F.isnull("doc_id").alias("last"), "doc_id", "body_key", "n")).alias("b"))
    empty = found.where("n_shingles = 0").select("doc_id", "body_key", F.lit(1).cast("long").alias("n")).distinct()
    stay = checkpointed(best.select("b.doc_id", "b.body_key", "b.n").unionByName(empty).select(F.col("doc_id").alias(d), F.col("body_key").alias(k + "2"), F.col("n").alias(r)))
    mine = docs.withColumn(k, F.xxhash64(col(text_col)))
    kept = lambda rows: mine.join(rows, col(id_col).eqNullSafe(F.col(d)) & (F.col(k) == F.col(k + "2")), "left_semi")
    repeated = stay.where(F.col(r) > 1)
    if repeated.isEmpty():
        return kept(stay).drop(k)
    return kept(stay.where(F.col(r) == 1)).unionByName(kept(repeated).dropDuplicates([id_col, k])).drop(k)
