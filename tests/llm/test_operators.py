"""Each operator against a brute-force version on small tables with nulls, repeats, ties and odd columns."""

import base64
import hashlib
import math
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from multiagg.llm.common import vocabulary_file

RANDOM = random.Random(11)
WORDS = "the of and la de der und stand ring over tion ether blue".split()


def words(n):
    return " ".join(RANDOM.choice(WORDS) + str(RANDOM.randrange(40)) for _ in range(n))


PASSAGE = words(60)
BASE = words(120)
NEAR = BASE.replace(BASE.split()[50], "changed", 1)
TEXTS = [
    (1, BASE), (2, NEAR), (3, BASE), (4, None), (5, ""), (6, " \n\t"), (7, "one two"), (8, "one two"), (9, words(80) + " " + PASSAGE), (10, PASSAGE + "\n" + words(90)), (11, "x" * 3000),
    (12, "call +1 (415) 555-0134 or mail a.b@mail.example.com, card 4111 1111 1111 1111, host 10.0.0.1, v1.2.3"), (13, "A" * 700 + " naïve été 漢字 😀 <|endoftext|> it's  two  spaces "), (None, "null id " + words(20)),
    (14, words(30) + "\r\n" + words(5) * 40), (14, words(12)), (15, "Z z Z z " * 30), (15, "Z z Z z " * 30), (16, "éé " * 200), (17, ("|| ## " * 50)), (18, words(40).upper()),
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "s", len(t or ""), 1, "k") for i, t in TEXTS]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, `__id` int, `body.key` string")
    return df.repartition(3).persist()


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("false")


def got(df, *cols):
    return Counter(tuple(r) for r in df.select(*cols).collect())


def test_exact_groups(docs, none):
    from multiagg.llm.exact_dedup import drop_exact_copies, exact_groups

    groups = defaultdict(list)
    for i, t in TEXTS:
        groups[t or ""].append(i)
    key = lambda i: -1 if i is None else i
    want = Counter((i, max(groups[t or ""], key=key), len(groups[t or ""]), hashlib.sha256((t or "").encode()).hexdigest()) for i, t in TEXTS)
    for size in (16, 1024):
        out = exact_groups(docs, block_bytes=size)
        assert got(out, "doc_id", "keep_id", "group_size", "text_sha256") == want
        assert out.where("kept").count() == len(groups)
    kept = drop_exact_copies(docs)
    assert kept.columns == docs.columns and kept.count() == len(groups)
    assert exact_groups(none).count() == 0 and drop_exact_copies(none).count() == 0


def test_block_names_stay_apart_when_fingerprints_meet(docs):
    from pyspark.sql import functions as F

    from multiagg.llm.exact_dedup import identities, keyed

    rows = keyed(docs, "doc_id", "text")
    meet = identities(rows, 16, fingerprint=lambda b: F.crc32(b) % 3)
    free = identities(rows, 16)
    classes = lambda df: sorted(sorted((str(x) for x in r["d"])) for r in df.groupBy("level", "name").agg(F.collect_list(F.struct("doc_id", "body_key")).alias("d")).collect())
    assert classes(meet) == classes(free)


def test_quality_measures(docs):
    from multiagg.llm.quality_rules import ablations, drop_low_quality, ledger

    for row in ledger(docs.drop("n_chars")).select("text", "ledger.*").collect():
        raw = (row["text"] or "").encode()
        w = raw.split()
        grams = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        inside = {j for i in range(len(w) - 4) if grams[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        lines = (row["text"] or "").split("\n")
        dup = sum(1 for i, x in enumerate(lines) if x.encode().split() and x in lines[:i])
        assert (row["n_words"], row["n_repeat_words"], row["n_dup_lines"]) == (len(w), len(inside), dup)
        assert row["word_chars"] == sum(len(x.decode()) for x in w) and row["n_symbols"] == sum((row["text"] or "").count(c) for c in "#*$%&|<>")
    kept = {r["doc_id"] for r in drop_low_quality(docs).collect()}
    assert {1, 2, 3, 9} <= kept and not kept & {4, 5, 6, 15, 17}
    table = ablations(ledger(docs).select("ledger.failed"))
    assert table.where("policy = 'v1' and rule = 'few_words'").first()["n_docs"] == len(TEXTS)


def test_near_duplicates(docs, none):
    from multiagg.llm.ngram_join import drop_near_copies, near_duplicates

    def brute(rows, n, percent):
        sets = {}
        for i, t in rows:
            w = (t or "").encode().lower().split()
            sets.setdefault(i, []).append(frozenset(tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))) if w else frozenset())
        nodes = [(i, s) for i, ss in sets.items() for s in ss]
        link = lambda a, b: a and b and 100 * len(a & b) >= percent * len(a | b)
        root = list(range(len(nodes)))
        for _ in nodes:
            for a in range(len(nodes)):
                for b in range(len(nodes)):
                    if link(nodes[a][1], nodes[b][1]):
                        root[a] = root[b] = min(root[a], root[b])
        least = defaultdict(list)
        for a, (i, _) in enumerate(nodes):
            least[root[a]].append(i)
        return Counter((i, len(s), min((x for x in least[root[a]] if x is not None), default=None)) for a, (i, s) in enumerate(nodes))

    for n, percent in ((4, 85), (5, 80), (1, 60)):
        out = near_duplicates(docs, n=n, percent=percent)
        assert got(out, "doc_id", "n_shingles", "component_id") == brute(TEXTS, n, percent), (n, percent)
    assert near_duplicates(none).count() == 0
    kept = {r["doc_id"] for r in drop_near_copies(docs).collect()}
    assert 1 in kept and not kept & {2, 3, 8} and drop_near_copies(docs).columns == docs.columns


def test_one_row_of_each_component_whatever_the_ids(spark):
    from multiagg.llm.ngram_join import drop_near_copies

    one, two = words(80), words(80)
    near = lambda t: t.replace(t.split()[40], "changed", 1)
    rows = [(7, one, "a"), (7, near(one), "b"), (7, one, "c"), (None, two, "d"), (None, near(two), "e"), (None, two, "f"), (9, "", "g"), (9, "", "h"), (10, words(60), "i"), (None, one, "j")]
    kept = drop_near_copies(spark.createDataFrame(rows, "doc_id long, text string, `body.key` string").repartition(3)).collect()
    assert [len({r["body.key"] for r in kept} & set(x)) for x in ("abcj", "def", "gh", "i")] == [1, 1, 2, 1] and len(kept) == 5
    assert {r["doc_id"] for r in kept if r["body.key"] in "abcj"} == {7}


def test_large_group_of_near_copies(spark, monkeypatch):
    from multiagg.llm import ngram_join

    base, rows = words(100).split(), []
    for i in range(60):
        w = list(base)
        for _ in range(RANDOM.randrange(0, 7)):
            w[RANDOM.randrange(len(w))] = f"n{RANDOM.randrange(10**6)}"
        rows.append((i, " ".join(w)))
    rows += [(100 + i, words(100)) for i in range(20)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(2)
    sets = {i: {tuple(t.split()[k : k + 4]) for k in range(97)} for i, t in rows}
    root = {i: i for i in sets}
    for _ in range(8):
        for a in sets:
            for b in sets:
                if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b]):
                    root[a] = root[b] = min(root[a], root[b])
    for most in (0, 40, ngram_join.FREQUENT):
        found = {r["doc_id"]: r["component_id"] for r in ngram_join.near_duplicates(df, most=most).collect()}
        assert found == root, most


def test_near_duplicates_hand_few_rows_at_a_time_to_python(spark, docs, monkeypatch):
    from multiagg.llm import ngram_join

    key, most, inner = "spark.sql.execution.arrow.maxRecordsPerBatch", [], ngram_join.set_links
    before = spark.conf.get(key)

    def watched(*args):
        sizes = spark.range(5000).coalesce(1).mapInPandas(lambda frames: (f.head(1).assign(id=len(f)) for f in frames), "id long")
        most.append(max(r["id"] for r in sizes.collect()))
        return inner(*args)

    monkeypatch.setattr(ngram_join, "set_links", watched)
    ngram_join.near_duplicates(docs).count()
    assert most == [ngram_join.BATCH] and spark.conf.get(key) == before


def test_tasks_without_a_codec_drop_those_kept():
    from multiagg.llm.quality_rules import _measure_batch
    from multiagg.llm.spans import lean_slices, worker_cache

    import pandas as pd

    for run in (lambda: list(lean_slices(iter([pd.DataFrame({"a": range(3000)})]))), lambda: _measure_batch(pd.Series(["one two"]))):
        worker_cache("word codecs")["x"] = worker_cache("codecs")["y"] = object()
        made = run()
        assert not worker_cache("word codecs") and not worker_cache("codecs")
        assert [len(x) for x in made] == [1024, 1024, 952] if isinstance(made, list) else len(made) == 1


def test_byte_bpe(docs, none):
    import public_tokenizers
    import tiktoken

    from multiagg.llm.byte_bpe import decode, digests, encode

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(vocabulary_file("byte_bpe_50k.tiktoken"), "rb"))}
    ref = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    ids = {(i, t): ref.encode_ordinary(t or "") for i, t in TEXTS}
    want = Counter((i, len(x), hashlib.sha256(" ".join(map(str, x)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()) for (i, t), x in [((i, t), ids[i, t]) for i, t in TEXTS])
    assert got(digests(docs), "doc_id", "n_tokens", "ids_sha256", "decoded_sha256") == want
    back = decode(encode(docs))
    assert Counter(bytes(r["decoded"]).decode() for r in back.collect()) == Counter(t or "" for _, t in TEXTS)
    assert digests(none).count() == 0


def test_packing(docs, none):
    from tokenizers import Tokenizer

    from multiagg.llm.packing import pack, sequences

    t = Tokenizer.from_file(vocabulary_file("word_bpe_49k.json"))
    want = Counter((i, np.array([*t.encode(x or "", add_special_tokens=False).ids, 1], dtype="<u4").tobytes()) for i, x in TEXTS)
    pieces = pack(docs, window=64)
    rows = sorted(pieces.collect(), key=lambda r: (r["sequence_id"], r["offset"]))
    place, streams, now = 0, [], b""
    for r in rows:
        assert r["sequence_id"] * 64 + r["offset"] == place and r["offset"] + r["length"] <= 64
        place += r["length"]
        now = now + bytes(r["ids"]) if r["start"] else bytes(r["ids"])
        if r["start"] + r["length"] == r["doc_tokens"]:
            streams.append((r["doc_id"], now))
    assert Counter(streams) == want
    assert {r["n_ids"] for r in sequences(pieces).orderBy("sequence_id").collect()[:-1]} == {64}
    assert pack(none).count() == 0


def test_rules_on_empty_repeated_and_long_texts(spark, none):
    from multiagg.llm.quality_rules import ablations, drop_low_quality, ledger

    assert ledger(none.drop("n_chars")).count() == 0 and drop_low_quality(none).count() == 0
    assert all(r["n_docs"] == 0 for r in ablations(ledger(none).select("ledger.failed")).collect())
    long_ = " ".join(f"word{i}" for i in range(60_000))
    rows = spark.createDataFrame([(1, long_, 5), (2, "few", 6), (2, "few", 6)], "doc_id long, text string, failed int")
    found = ledger(rows).select("doc_id", "failed", "ledger.n_words", "ledger.n_repeat_words")
    assert got(found, "doc_id", "failed", "n_words", "n_repeat_words") == Counter({(1, 5, 60_000, 0): 1, (2, 6, 1, 0): 2})


def test_audit_of_pages_with_other_columns(spark):
    from multiagg.llm.warc import damaged, fixity

    pages = spark.createDataFrame([(i % 9, f"http://a/{i % 9}", "<p>x</p>", "s", b"r", 7) for i in range(30)], "page_id long, url string, html string, state string, record binary, seq long")
    plain = pages.select("page_id", "url", "html")
    assert got(fixity(pages, damaged(pages)), "record_id", "state") == got(fixity(plain, damaged(plain)), "record_id", "state")
    assert fixity(pages, pages).count() == 30 and fixity(pages.where("false"), pages.where("false")).count() == 0


def test_pii(docs, none):
    from multiagg.llm.pii import TAGS, active_runs, features, labelled_table, model, redact, span_digests

    row = span_digests(docs).where("doc_id = 12").first()
    assert (row["n_email"], row["n_ip"], row["n_card"], row["n_phone"]) == (1, 1, 1, 1)
    assert hashlib.sha256(row["spans"].encode()).hexdigest() == row["base_sha256"]
    assert span_digests(docs).count() == len(TEXTS) and span_digests(none).count() == 0
    text = redact(docs, length_col="n_chars").where("doc_id = 12").first()
    assert text["text"] == "call <PHONE> or mail <EMAIL>, card <CARD>, host <IP>, v1.2.3" and text["n_chars"] == len(text["text"])
    right = total = 0
    for w, tags in labelled_table(seed=5, sentences=100):
        for a, b in active_runs(w):
            run = np.array([features(w[a:b], i, w[a - 1] if a else "", w[b] if b < len(w) else "") for i in range(b - a)])
            found = [TAGS[k] for k in model().decode([run])[0]]
            right, total = right + sum(x == y for x, y in zip(found, tags[a:b])), total + b - a
    assert right / total > 0.97


def test_base_patterns_by_brute_force():
    import re

    from multiagg.llm.pii import KINDS, base_spans

    digits = lambda x: [int(c) for c in x if c in "0123456789"]
    luhn = lambda d: sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(reversed(d))) % 10 == 0
    # fixed values: the patterns of the contract
    kinds = (
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda x: True),
        ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda x: all(int(p) <= 255 for p in x.split("."))),
        ("card", r"[0-9]([\x20-]?[0-9])+", lambda x: 14 <= len(digits(x)) <= 19 and luhn(digits(x))),
        ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda x: 10 <= len(digits(x)) <= 15),
    )
    rng = random.Random(9)
    texts = ["".join(rng.choice(letters) for _ in range(rng.randrange(60))) for letters in ("a1@.-", "12.5 ", "0123456789 -", "+12 ().-", "é٣a@.1+ -\n") for _ in range(1500)]
    texts += ["4111 1111 1111 1111", "41111111111111 +1 415 555 0134", "a@b.c.d-e@f.g", "1.2.3.4.5.6.7.8", "256.1.1.1 01.002.3.255"]
    seen = Counter()
    for text in texts:
        want = sorted((m.start(), k, m.end()) for k, (_, pattern, good) in enumerate(kinds) for m in re.finditer(pattern, text) if good(m[0]))
        assert sorted(tuple(x) for x in base_spans(text)) == want, text
        seen.update(KINDS[k] for _, k, _ in want)
    assert set(seen) == {"email", "ip", "card", "phone"}


def test_decoding_is_the_best_path():
    from itertools import product

    from multiagg.llm.pii import TAGS, ChainField

    rng = np.random.default_rng(3)
    field = ChainField(rng.normal(size=(20, len(TAGS))).astype(np.float32), rng.normal(size=(len(TAGS), len(TAGS))).astype(np.float32))
    sequences = [rng.integers(0, 20, (n, 3)) for n in (1, 2, 3, 1, 3)]
    for rows, path in zip(sequences, field.decode(sequences)):
        score = lambda p, rows=rows: field.move[0, p[0]] + sum(field.scores(rows)[i, k] for i, k in enumerate(p)) + sum(field.move[a, b] for a, b in zip(p, p[1:])) + field.move[p[-1], 0]
        assert math.isclose(score(tuple(path)), max(map(score, product(range(len(TAGS)), repeat=len(rows)))), rel_tol=1e-4)


def test_removal_of_repeats(docs, none):
    from multiagg.llm.suffix_dedup import removal_digests

    texts = [(i, (t or "").encode()) for i, t in TEXTS]
    seen = Counter(b[k : k + 200] for _, b in texts for k in range(len(b) - 199))
    want = Counter()
    for i, b in texts:
        gone = {p for k in range(len(b) - 199) if seen[b[k : k + 200]] > 1 for p in range(k, k + 200)}
        kept = bytes(c for p, c in enumerate(b) if p not in gone)
        spans = sum(1 for p in gone if p - 1 not in gone)
        want[i, len(b), len(gone), spans, hashlib.sha256(kept).hexdigest()] += 1
    assert got(removal_digests(docs), "doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256") == want
    assert removal_digests(none).count() == 0


def test_long_text_is_parsed_as_a_whole(monkeypatch):
    from multiagg.llm import suffix_dedup as s

    raw = bytes(np.random.default_rng(1).integers(97, 123, 20_000, dtype=np.uint8))

    def windows(bodies):
        found = set()
        for p in s.parsed(bodies):
            n = np.arange(len(p.first))
            which, offset, hashes = p.windows(n, p.place - p.first - p.count + 1, p.place - p.first)
            found |= set(zip(p.number[which].tolist(), (p.place[which] - offset - p.low[p.doc[which]]).tolist(), p.gram[which].tolist(), p.phrase[which].tolist(), hashes.tolist()))
        return found

    whole = windows([raw, b"", raw[:300]])
    monkeypatch.setattr(s, "STRETCH", 2000)
    assert windows([raw, b"", raw[:300]]) == whole and len(whole) == 19_801 + 101


def test_warc_audit(spark):
    from multiagg.llm.warc import archived, audit, damaged, fixity, parse_warc, records

    pages = spark.createDataFrame([(i, f"http://a/{i}" if i % 7 else None, "<p>é</p>" * i if i % 5 else None) for i in range(200)], "page_id long, url string, html string").repartition(3).persist()
    bad = {r["page_id"] for r in pages.exceptAll(damaged(pages)).collect()}
    found = fixity(pages, damaged(pages))
    assert {r["record_id"] for r in found.where("state = 'changed'").collect()} == bad and bad and found.count() == 200
    assert fixity(pages, pages).where("state <> 'intact'").count() == 0
    ours = archived(records(pages).coalesce(1)).persist()
    lost = audit(ours, ours.where("seq < 190"), 4)
    assert lost.where("state = 'missing there'").count() == 10 and lost.count() == 10
    raw = b"".join(bytes(r["record"]) for r in records(pages).collect())
    parsed = list(parse_warc(raw))
    assert len(parsed) == 200 and sum(p[1] for p in parsed) == len(raw)
    assert audit(ours.where("false"), ours.where("false")).count() == 0


def test_token_counts(spark, docs, none):
    import public_tokenizers
    import tiktoken

    from multiagg.llm.token_counts import blocks_of_files, count_tokens, document_counts, token_files

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(vocabulary_file("byte_bpe_50k.tiktoken"), "rb"))}
    ref = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    assert got(document_counts(docs), "doc_id", "n_tokens") == Counter((i, len(ref.encode_ordinary(t or ""))) for i, t in TEXTS)
    small = token_files(docs.coalesce(1), block_tokens=7).where("data is not null").select("file", "block", "data").persist()
    for group in (1, 2, 5, 1024):
        counts = sorted((r["ordinal"], r["n_tokens"]) for r in count_tokens(small, group=group).collect())
        assert [n for _, n in counts] == [len(ref.encode_ordinary(r["text"] or "")) for r in docs.coalesce(1).collect()]
    assert document_counts(none).count() == 0
    assert blocks_of_files


def test_flat_files_without_a_last_separator(spark, tmp_path):
    from multiagg.llm.token_counts import blocks_of_files, count_tokens

    ids = [5, 6, 50256, 50256, 7, 8, 9, 50256, 1, 2, 3]
    (tmp_path / "a.bin").write_bytes(np.array(ids, dtype="<u2").tobytes())
    (tmp_path / "b.bin").write_bytes(b"")
    out = sorted(tuple(r) for r in count_tokens(blocks_of_files(spark, str(tmp_path), 4), group=2).select("ordinal", "start", "n_tokens", "closed").collect())
    assert out == [(0, 0, 2, True), (1, 3, 0, True), (2, 4, 3, True), (3, 8, 3, False)]


def test_language_model(docs, none):
    from multiagg.llm.pitman_yor import score_documents

    tokens = [(i, [*(t or "").encode().lower().split(), b"\n"]) for i, t in TEXTS]
    out = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 5 == 1
    counts = Counter(w for i, ws in tokens if not out(i) for w in ws)
    n, v = sum(counts.values()), len(counts)
    want = Counter((i, out(i), len(ws), sum(counts[w] > 0 for w in ws), n, round(sum(math.log10((counts[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws), 6)) for i, ws in tokens)
    rows = score_documents(docs, most=12, sweeps=3).collect()
    assert Counter((r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in rows) == want
    assert all(r["score"] < 0 and r["perplexity"] > 1 for r in rows)
    assert score_documents(none).count() == 0


def test_predictions_sum_to_one(docs):
    from multiagg.llm import pitman_yor as p

    hot = p.hot_tokens(docs, "doc_id", "text", 4096)
    words = {w for i, t in TEXTS if not p.held_out(i) for w in p.tokens_of(t)}
    hot = [p.END, *sorted(words - {p.END})]
    read = p.read_once(docs, hot, "doc_id", "text").persist()
    totals = p.fit(read, p.blocks_by_type(read).persist(), len(hot) + 2, 2)
    table, _ = p.hot_scores(totals)
    unknown = sum(totals.more(i, np.arange(len(hot) + 2)) * (p.STRENGTH + totals.root_discount * totals.root_tables[i]) * totals.even() / (p.STRENGTH + totals.root_customers[i]) for i in p.kept_sweeps(totals)) / len(p.kept_sweeps(totals))
    assert np.allclose((10**table).sum(1) + unknown, 1, atol=0.02)


def test_hot_tokens_by_all_counts(spark):
    from multiagg.llm import pitman_yor as p

    rows = [(i, f"common{i % 7} rare{i} rare{i + 1} end") for i in range(60)]
    counts = Counter(w for i, t in rows if not p.held_out(i) for w in t.encode().split())
    want = [p.END, *sorted(counts, key=lambda w: (-counts[w], w))[:5]]
    for parts in (1, 20):
        assert p.hot_tokens(spark.createDataFrame(rows, "doc_id long, text string").repartition(parts), "doc_id", "text", 6) == want


def test_every_context_has_its_restaurant(spark):
    from multiagg.llm import pitman_yor as p

    r = random.Random(3)
    pair = lambda: "left{0} right{0}".format(r.randrange(200))
    df = spark.createDataFrame([(i, " ".join(pair() for _ in range(40))) for i in range(150)], "doc_id long, text string").repartition(2)
    hot = p.hot_tokens(df, "doc_id", "text", 4)
    read = p.read_once(df, hot, "doc_id", "text").persist()
    totals = p.fit(read, p.blocks_by_type(read).persist(), len(hot) + 2, 2)
    assert totals.customers[len(hot)] == 0 and totals.customers.sum() + totals.contexts.agg({"c": "sum"}).first()[0] == totals.total
    mean = lambda most: np.mean([x["perplexity"] for x in p.score_documents(df, most=most).where("held_out").collect()])
    few, all_ = mean(4), mean(4096)
    assert abs(few / all_ - 1) < 0.03 and few < 40


def test_pipeline_keeps_columns_and_acts(spark, docs):
    import corpus_pipeline

    now = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, "").persist()
        assert now.columns == docs.columns, name
    left = {r["doc_id"]: r["text"] for r in now.collect()}
    assert not {4, 5, 7, 8, 15, 17} & set(left) and len({1, 2, 3} & set(left)) == 1 and "<PHONE>" in left[12]
    assert corpus_pipeline.STAGES[-1][1](spark, now, "").count() >= len(left)
