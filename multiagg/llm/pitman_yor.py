"""Language-model scoring with a hierarchical Pitman-Yor model.

Each context is a restaurant whose customers are the tokens that follow it and whose dishes are
token types; a new table there is a customer of the root restaurant, which all contexts share as
parent, and a new table at the root draws from all types evenly, one place being kept for unknown
ones. Contexts are all tokens, each by itself, and the start of a text. Seating is sampled by Gibbs
sweeps: given the numbers of tables of all restaurants, every dish is seated anew, customer by
customer, in blocks of a sixteenth once it has many; then the numbers of tables are counted again.
Predictive probabilities are averaged over the kept sweeps.

Scale: pass 1 finds the `HOT` most common tokens from counts combined in the tasks. Pass 2 reads each
text once. A place whose context and token are both hot stays packed with its document, and the
counts of such pairs make a square of HOT + 2 that all tasks get to know. Every other place goes into
a table keyed by (context, token). There a dish with one customer has one table whatever happens, so
sweeps move only pairs met twice or more; what belongs to a hot context or token is looked up in
small tables, what belongs to any other in shuffled ones, where no key is hot by construction.
Scores return as sums per document.

Tokens in the keyed table go by 64-bit hashes. Defined results: a null text counts as empty: its only
token is the end. A null id counts as the empty text for the fold. Repeated rows are scored, and
learned from, each by itself. With nothing to learn from, every type has the even probability.
"""

from __future__ import annotations

import hashlib
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from multiagg.llm.common import col, tabled

HOT = 512
#: Types that a task counts before it passes them on.
COUNTED = 200_000
FOLDS, HELD_OUT = 5, 1
SWEEPS, BURN_IN = 5, 2
STRENGTH = 1.0
#: A stretch ends with so many tokens, or documents.
STRETCH_TOKENS, STRETCH_DOCS = 1_000_000, 65_000
#: Stands for the end of a text; no word can be white space.
END = b"\n"
ONE_BY_ONE = 24


def tokens_of(text: str | None) -> list[bytes]:
    return [*(text or "").encode("utf-8", "replace").lower().split(), END]


def held_out(doc_id) -> bool:
    text = "" if doc_id is None or doc_id != doc_id else str(int(doc_id)) if isinstance(doc_id, (int, float, np.integer)) else str(doc_id)
    return zlib.crc32(text.encode()) % FOLDS == HELD_OUT


def hot_tokens(docs: DataFrame, id_col: str, text_col: str, most: int = HOT) -> list[bytes]:
    """END and the most common other training tokens; tasks add up what they meet before it is counted as a whole."""

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: Counter = Counter()

        def counted() -> pd.DataFrame:
            seen.pop(END, None)
            return pd.DataFrame(list(seen.items()), columns=["token", "n"])

        for frame in frames:
            for doc, text in zip(frame["doc_id"], frame["text"]):
                if not held_out(doc):
                    seen.update(tokens_of(text))
                if len(seen) >= COUNTED:
                    yield counted()
                    seen.clear()
        yield counted()

    counts = docs.select(col(id_col).alias("doc_id"), col(text_col).alias("text")).mapInPandas(work, "token binary, n long").groupBy("token").agg(F.sum("n").alias("n"))
    return [END, *(bytes(r["token"]) for r in counts.orderBy(F.desc("n"), "token").limit(most - 1).collect())]


READ = "kind int, place long, doc_id {kind}, held_out boolean, n_tokens int, pairs binary, u long, w long, n long"


def named(words: list[bytes]) -> np.ndarray:
    """Below zero, where no number of a hot token is."""
    return np.frombuffer(b"".join(hashlib.blake2b(w, digest_size=8).digest() for w in words), "<i8") | np.int64(-(2**63))


def read_once(docs: DataFrame, hot: list[bytes], id_col: str, text_col: str) -> DataFrame:
    """Pass 2. kind 1: a document with its hot (context, token) pairs; kind 0: a place with another pair, and 1 if it is learned from; kind 2: training counts of hot pairs."""
    kind = docs.select(col(id_col)).schema[0].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(hot)

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        number, first = {w: i for i, w in enumerate(shared.value)}, TaskContext.get().partitionId() << 36
        k = len(number)

        def new() -> tuple:
            return dict(number), [], [], [], []

        types, ids, sizes, names, folds = new()

        def flushed() -> Iterator[pd.DataFrame]:
            nonlocal types, ids, sizes, names, folds, first
            flat, per = np.concatenate(ids).astype(np.int64), np.array(sizes)
            w = np.concatenate([np.arange(k), named(list(types)[k:])])[flat]
            u = np.concatenate([[k + 1], w[:-1]])
            u[np.cumsum(per)[:-1]] = k + 1
            doc, out = np.repeat(np.arange(len(per)), per), np.array(folds)
            training = ~out[doc]
            common = (u >= 0) & (w >= 0)
            pairs = np.stack([u[common], w[common]], 1).astype("<u2")
            cut = np.cumsum(np.bincount(doc[common], minlength=len(per)))
            whole, at = pairs.tobytes(), [0, *(4 * cut).tolist()]
            yield pd.DataFrame({"kind": 1, "place": first + np.arange(len(per)), "doc_id": names, "held_out": out, "n_tokens": per, "pairs": [whole[a:b] for a, b in zip(at, at[1:])]})
            both, n = np.unique(u[common & training] * (k + 2) + w[common & training], return_counts=True)
            yield pd.DataFrame({"kind": 2, "u": both // (k + 2), "w": both % (k + 2), "n": n})
            rest = np.flatnonzero(~common)
            for i in range(0, len(rest), 100_000):
                at = rest[i : i + 100_000]
                yield pd.DataFrame({"kind": 0, "place": first + doc[at], "u": u[at], "w": w[at], "n": training[at].astype(np.int64)})
            types, ids, sizes, names, folds = new()
            first += len(per)

        total = 0
        for frame in frames:
            for doc, text in zip(frame["doc_id"], frame["text"]):
                words = tokens_of(text)
                ids.append(np.fromiter((types.setdefault(w, len(types)) for w in words), np.int32, len(words)))
                sizes.append(len(words))
                names.append(doc)
                folds.append(held_out(doc))
                total += len(words)
                if total >= STRETCH_TOKENS or len(sizes) >= STRETCH_DOCS:
                    yield from map(_complete, flushed())
                    total = 0
        if sizes:
            yield from map(_complete, flushed())

    columns = [c.split()[0] for c in READ.split(", ")]

    def _complete(frame: pd.DataFrame) -> pd.DataFrame:
        for c in columns:
            if c not in frame:
                frame[c] = None
        return frame[columns]

    return docs.select(col(id_col).alias("doc_id"), col(text_col).alias("text")).mapInPandas(work, READ.format(kind=kind))


def blocks_by_type(read: DataFrame) -> DataFrame:
    """(u, w, n, places): each pair that is not in the square, how often it is learned from, and where it stands."""
    return read.where("kind = 0").groupBy("u", "w").agg(F.sum("n").alias("n"), F.collect_list("place").alias("places"))


@dataclass
class Totals:
    """Arrays hold what belongs to hot contexts and tokens, of fixed size; tables hold all others."""

    types: int
    total: int
    customers: np.ndarray
    hot_counts: np.ndarray
    hot_times: np.ndarray
    contexts: DataFrame
    #: u, w, n and the numbers of tables t0, t1, ... of pairs met twice or more
    seated: DataFrame
    #: w, times, ones, customers a0, a1, ... and tables r0, r1, ... at the root
    dishes: DataFrame
    discount: float = 0.75
    root_discount: float = 0.75
    tables: list = field(default_factory=list)
    root_customers: list = field(default_factory=list)
    root_tables: list = field(default_factory=list)
    hot_tables: list = field(default_factory=list)
    hot_root: list = field(default_factory=list)

    def even(self) -> float:
        return 1.0 / (self.types + 1)

    def root(self, i: int, customers: np.ndarray, tables: np.ndarray) -> np.ndarray:
        """Probability of dishes at the root in sweep i."""
        all_, served = self.root_customers[i], self.root_tables[i]
        return (np.maximum(customers - self.root_discount * tables, 0) + (STRENGTH + self.root_discount * served) * self.even()) / (STRENGTH + all_)

    def root_column(self, i: int, customers: Column, tables: Column) -> Column:
        all_, served = float(self.root_customers[i]), float(self.root_tables[i])
        return (F.greatest(customers - self.root_discount * tables, F.lit(0.0)) + (STRENGTH + self.root_discount * served) * self.even()) / (STRENGTH + all_)

    def more(self, i: int, context: np.ndarray) -> np.ndarray:
        """Weight that a context gives to its parent in sweep i."""
        return (STRENGTH + self.discount * self.tables[i][context]) / (STRENGTH + self.customers[context])


def seat(customers: np.ndarray, parent: np.ndarray, weight: np.ndarray, discount: float, rng: np.random.Generator) -> np.ndarray:
    """Numbers of tables after all customers of each dish have sat down: weight * parent against those already seated."""
    tables = np.minimum(customers, 1).astype(np.float64)
    seated, open_ = tables.copy(), np.flatnonzero(customers > 1)
    step = 1
    while open_.size:
        size = np.minimum(np.maximum(1, step // 16) if step > ONE_BY_ONE else 1, customers[open_] - seated[open_])
        new = weight[open_] * parent[open_]
        chance = new / (new + np.maximum(seated[open_] - discount * tables[open_], 1e-9))
        tables[open_] += rng.binomial(size.astype(np.int64), chance) if step > ONE_BY_ONE else rng.random(len(open_)) < chance
        seated[open_] += size
        step += int(size.max())
        open_ = open_[seated[open_] < customers[open_]]
    return tables


def looked_up(pairs: DataFrame, key: str, others: DataFrame, hot: pd.DataFrame, how: str = "inner") -> DataFrame:
    """`pairs` with what `others` or, for hot ones, `hot` knows of `key`."""
    few = F.broadcast(pairs.sparkSession.createDataFrame(hot))
    return pairs.where(f"{key} < 0").join(others, key, how).unionByName(pairs.where(f"{key} >= 0").join(few, key))


def by_number(rows: DataFrame, size: int, *columns: str) -> list[np.ndarray]:
    """Columns of the hot rows as arrays; the first column of `rows` is the number."""
    out = [np.zeros(size, dtype=np.int64) for _ in columns]
    for r in rows.where(F.col(rows.columns[0]) >= 0).collect():
        for x, c in zip(out, columns):
            x[r[0]] = r[c]
    return out


def fit(read: DataFrame, blocks: DataFrame, contexts: int, sweeps: int = SWEEPS) -> Totals:
    """Numbers of tables over `sweeps` sweeps; only those of hot contexts and tokens, and sums, reach the driver."""
    types = contexts - 2
    hot_counts = np.zeros((contexts, types), dtype=np.int64)
    for r in read.where("kind = 2").groupBy("u", "w").agg(F.sum("n").alias("n")).collect():
        hot_counts[r["u"], r["w"]] = r["n"]
    seen = blocks.where("n > 0")
    ones = F.count_if(F.col("n") == 1).alias("ones")
    of_contexts = tabled(seen.groupBy("u").agg(F.sum("n").alias("c"), ones), "contexts")
    of_dishes = tabled(seen.groupBy("w").agg(F.sum("n").alias("times"), ones), "dishes")
    n_places, once, twice = (int(x or 0) for x in seen.agg(F.sum("n"), F.count_if(F.col("n") == 1), F.count_if(F.col("n") == 2)).first())
    customers, u_ones = by_number(of_contexts, contexts, "c", "ones")
    times, w_ones = by_number(of_dishes, types, "times", "ones")
    times = times + hot_counts.sum(0)
    dishes, of_others = of_dishes.where("w < 0"), of_contexts.where("u < 0")
    seated = tabled(seen.where("n > 1").select("u", "w", "n"), "seated")
    totals = Totals(dishes.count() + int((times > 0).sum()), n_places + int(hot_counts.sum()), customers + hot_counts.sum(1), hot_counts, times, of_others, seated, dishes)
    once, twice = once + int((hot_counts == 1).sum()), twice + int((hot_counts == 2).sum())
    totals.discount = float(np.clip(once / max(once + 2 * twice, 1), 0.3, 0.95))
    totals.root_discount = float(np.clip(0.9 * totals.discount, 0.3, 0.9))
    hot_context, hot_kind = np.nonzero(hot_counts)
    hot_n = hot_counts[hot_context, hot_kind]
    for i in range(sweeps):
        t, a, r, discount = f"t{i}", f"a{i}", f"r{i}", totals.discount
        if i:
            weights = STRENGTH + discount * totals.tables[-1]
            parents = totals.root(i - 1, *totals.hot_root[-1])
            u_weights = of_others.join(totals.seated.where("u < 0").groupBy("u").agg(F.sum(f"t{i - 1}").alias("t")), "u").select("u", (STRENGTH + discount * (F.col("ones") + F.col("t"))).alias("weight"))
            w_parents = totals.dishes.select("w", totals.root_column(i - 1, F.col(f"a{i - 1}"), F.col(f"r{i - 1}")).alias("parent"))
        else:
            weights = STRENGTH + discount * 0.5 * totals.customers
            parents = times / max(totals.total, 1)
            u_weights = of_others.select("u", (STRENGTH + discount * 0.5 * F.col("c")).alias("weight"))
            w_parents = dishes.select("w", (F.col("times") / float(max(totals.total, 1))).alias("parent"))
        asked = looked_up(totals.seated, "u", u_weights, pd.DataFrame({"u": np.arange(contexts), "weight": weights.astype(float)}))
        asked = looked_up(asked, "w", w_parents, pd.DataFrame({"w": np.arange(types), "parent": parents.astype(float)}))

        def sat(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                rng = np.random.default_rng([i, zlib.crc32(f["u"].to_numpy().tobytes() + f["w"].to_numpy().tobytes())])
                f[t] = seat(f["n"].to_numpy(), f["parent"].to_numpy(), f["weight"].to_numpy(), discount, rng).astype(np.int64)
                yield f.drop(columns=["weight", "parent"])

        kept = [*totals.seated.columns, t]
        totals.seated = tabled(asked.sortWithinPartitions("u", "w").mapInPandas(sat, ", ".join(f"{c} long" for c in kept)).select(*kept), "seated")
        new = totals.seated.groupBy("w").agg(F.sum(t).alias("t"))
        (u_more,) = by_number(totals.seated.where("u >= 0").groupBy("u").agg(F.sum(t).alias("t")), contexts, "t")
        (w_more,) = by_number(new.where("w >= 0"), types, "t")
        even, served, root_discount = totals.even(), float(totals.root_tables[-1]) if i else 0.5 * totals.types, totals.root_discount
        at_root = lambda n, rng: seat(n, np.full(len(n), even), np.full(len(n), STRENGTH + root_discount * served), root_discount, rng)

        def rooted(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                f[r] = at_root(f[a].to_numpy(), np.random.default_rng([i, zlib.crc32(f["w"].to_numpy().tobytes())])).astype(np.int64)
                yield f

        asking = totals.dishes.join(new.where("w < 0"), "w", "left").withColumn(a, F.col("ones") + F.coalesce("t", F.lit(0))).drop("t").sortWithinPartitions("w")
        totals.dishes = tabled(asking.mapInPandas(rooted, ", ".join(f"{c} long" for c in [*asking.columns, r])), "dishes")
        rng = np.random.default_rng([i, 1])
        tables = seat(hot_n, parents[hot_kind], weights[hot_context], discount, rng)
        hot_customers = np.bincount(hot_kind, weights=tables, minlength=types) + w_ones + w_more
        hot_root = at_root(hot_customers, rng)
        square = np.zeros(hot_counts.shape)
        square[hot_context, hot_kind] = tables
        others = totals.dishes.agg(F.sum(a), F.sum(r)).first()
        totals.tables.append(np.bincount(hot_context, weights=tables, minlength=contexts) + u_ones + u_more)
        totals.root_customers.append((others[0] or 0) + hot_customers.sum())
        totals.root_tables.append((others[1] or 0) + hot_root.sum())
        totals.hot_tables.append(square)
        totals.hot_root.append((hot_customers, hot_root))
    return totals


def kept_sweeps(totals: Totals) -> range:
    return range(min(BURN_IN, len(totals.tables) - 1), len(totals.tables))


def hot_scores(totals: Totals) -> tuple[np.ndarray, np.ndarray]:
    """log10 probability of each hot token after each context, averaged over the kept sweeps; and its training count."""
    contexts = np.arange(len(totals.customers))
    total = 0.0
    for i in kept_sweeps(totals):
        root = totals.root(i, *totals.hot_root[i])
        total = total + np.maximum(totals.hot_counts - totals.discount * totals.hot_tables[i], 0) / (STRENGTH + totals.customers[:, None]) + totals.more(i, contexts)[:, None] * root[None, :]
    return np.log10(total / len(kept_sweeps(totals))), totals.hot_times


def place_scores(blocks: DataFrame, totals: Totals) -> DataFrame:
    """(place, rest, rest_base, rest_known): sums over a document's pairs outside the square."""
    sweeps, d = kept_sweeps(totals), totals.discount
    t, more, root = [f"t{i}" for i in sweeps], [f"more{i}" for i in sweeps], [f"root{i}" for i in sweeps]
    zero = lambda c: F.coalesce(F.col(c), F.lit(0))
    pairs = blocks.where("n < 2").withColumns({c: F.col("n") for c in t}).unionByName(blocks.where("n > 1").join(totals.seated.drop("n").select("u", "w", *t), ["u", "w"]))
    of_contexts = totals.contexts.join(totals.seated.where("u < 0").groupBy("u").agg(*(F.sum(c).alias(c + "s") for c in t)), "u", "left")
    of_contexts = of_contexts.select("u", F.col("c").cast("double").alias("c"), *((STRENGTH + d * (F.col("ones") + zero(c + "s"))).alias(m) for c, m in zip(t, more)))
    hot = {"u": np.arange(len(totals.customers)), "c": totals.customers.astype(float)} | {m: (STRENGTH + d * totals.tables[i]).astype(float) for i, m in zip(sweeps, more)}
    pairs = looked_up(pairs, "u", of_contexts, pd.DataFrame(hot), "left")
    of_dishes = totals.dishes.select("w", "times", *(totals.root_column(i, F.col(f"a{i}"), F.col(f"r{i}")).alias(x) for i, x in zip(sweeps, root)))
    hot = {"w": np.arange(len(totals.hot_times)), "times": totals.hot_times} | {x: totals.root(i, *totals.hot_root[i]).astype(float) for i, x in zip(sweeps, root)}
    pairs = looked_up(pairs, "w", of_dishes, pd.DataFrame(hot), "left")
    p = F.lit(0.0)
    for i, c, m, x in zip(sweeps, t, more, root):
        unknown = totals.root_column(i, F.lit(0), F.lit(0))
        p = p + F.greatest(F.col("n") - d * F.col(c), F.lit(0.0)) + F.coalesce(F.col(m), F.lit(STRENGTH)) * F.coalesce(F.col(x), unknown)
    scored = pairs.select("places", F.log10(p / (STRENGTH + zero("c")) / len(sweeps)).alias("score"), F.log10(zero("times") + 0.5).alias("base"), (zero("times") > 0).cast("long").alias("known"))
    return scored.select(F.explode("places").alias("place"), "score", "base", "known").groupBy("place").agg(F.sum("score").alias("rest"), F.sum("base").alias("rest_base"), F.sum("known").alias("rest_known"))


def score_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", most: int = HOT, sweeps: int = SWEEPS) -> DataFrame:
    """One row per row of `docs`: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score, perplexity."""
    hot = hot_tokens(docs, id_col, text_col, most)
    read = tabled(read_once(docs, hot, id_col, text_col), "read")
    blocks = tabled(blocks_by_type(read), "pairs")
    totals = fit(read, blocks, len(hot) + 2, sweeps)
    rest = place_scores(blocks, totals)
    shared = docs.sparkSession.sparkContext.broadcast((*hot_scores(totals), len(hot)))
    kind = read.schema["doc_id"].dataType.simpleString()

    def work(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        table, counts, _ = shared.value
        for frame in frames:
            pairs = [np.frombuffer(p, "<u2").reshape(-1, 2) for p in frame["pairs"]]
            frame["score"] = [float(table[p[:, 0], p[:, 1]].sum()) for p in pairs]
            frame["base"] = [float(np.log10(counts[p[:, 1]] + 0.5).sum()) for p in pairs]
            frame["known"] = [int((counts[p[:, 1]] > 0).sum()) for p in pairs]
            yield frame.drop(columns="pairs")

    own = read.where("kind = 1").select("place", "doc_id", "held_out", F.col("n_tokens").cast("long").alias("n_tokens"), "pairs")
    own = own.mapInPandas(work, f"place long, doc_id {kind}, held_out boolean, n_tokens long, score double, base double, known long")
    zero = lambda c: F.coalesce(F.col(c), F.lit(0))
    norm = float(np.log10(totals.total + 0.5 * (totals.types + 1)))
    out = own.join(rest, "place", "left").select(
        "doc_id", "held_out", "n_tokens", (F.col("known") + zero("rest_known")).alias("n_known"), F.lit(totals.total).cast("long").alias("train_tokens"),
        (F.col("base") + zero("rest_base") - F.col("n_tokens") * norm).alias("base_score"), (F.col("score") + zero("rest")).alias("score"),
    )
    return out.withColumn("perplexity", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")))

