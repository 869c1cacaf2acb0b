"""Quality rules as a bitmask ledger.

Each rule is evaluated once for each text. The ledger keeps the measurements and one bit per
failed rule; policies are versioned sets of rules, so a change of policy or an ablation reads
the bits only, never the text.

Defined results: a null text has no words and fails `few_words`. Lines are split at \\n alone
and words at ASCII white space alone. Other columns of the table pass through untouched.
Repeated rows are judged each by itself, a long text as a whole; an empty table gives an empty ledger.
"""

from __future__ import annotations

import re
from operator import eq

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from multiagg.llm.common import col, fresh
from multiagg.llm.spans import forget_codecs

SPACES = " \t\n\r\x0b\x0c"
SYMBOLS = b"#*$%&|<>"
WINDOW = 5
#: Rules by the place of their bit; each is a condition on the measurements.
RULES = {
    "few_words": "n_words < 10",
    "repeated_windows": "100 * n_repeat_words > 20 * n_words",
    "symbols": "100 * n_symbols > 25 * n_words",
    "duplicate_lines": "n_dup_lines >= 3 and 100 * n_dup_lines > 30 * n_lines",
    "capitals": "100 * n_upper > 40 * n_letters",
    "shouting": "100 * n_bangs > 25 * n_words",
    "few_letters": "100 * n_letters < 30 * word_chars",
    "doubled_words": "100 * n_doubled > 20 * n_words",
    "word_length": "word_chars < 2 * n_words or word_chars > 20 * n_words",
}
#: Versioned policies: the rules that count.
POLICIES = {
    "v1": ("few_words", "repeated_windows"),
    "v2": tuple(RULES),
}
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_upper", "n_letters", "n_bangs", "n_doubled")
_UPPER = bytes(range(65, 91))
_CONTINUED = bytes(range(0x80, 0xC0))
#: What is left without these: ASCII letters, and one byte for each other code point beyond ASCII.
_NOT_LETTER = bytes(set(range(128)) - set(range(65, 91)) - set(range(97, 123))) + _CONTINUED


def repeat_words(words: list[bytes], window: int = WINDOW) -> int:
    """Words that stand in a window of so many words found twice or more in the text."""
    if len(words) <= window:
        return 0
    names: dict[bytes, int] = {}
    ids = np.array([names.setdefault(w, len(names)) for w in words], dtype=np.int64)
    if len(names) == len(words):
        return 0
    code = ids
    for k in range(1, window):  # a window's name: its start's name and its next word, named anew before they outgrow 63 bits
        base = len(names)
        if int(code.max()) >= 2**62 // base:
            code = np.unique(code, return_inverse=True)[1]
        code = code[:-1] * base + ids[k:]
    order = np.argsort(code, kind="stable")
    same = code[order][1:] == code[order][:-1]
    twice = np.zeros(len(code), dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    edge = np.zeros(len(words) + 1, dtype=np.int64)
    at = np.flatnonzero(twice)
    np.add.at(edge, at, 1)
    np.add.at(edge, at + window, -1)
    return int((np.cumsum(edge) > 0).sum())


def measure_text(text: str | None) -> tuple:
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = raw.split()
    packed = b"".join(words)
    lines, seen, dup = raw.split(b"\n"), set(), 0
    for line in lines:
        if line in seen:
            dup += 1
        elif not line.isspace() and line:
            seen.add(line)
    letters = packed.translate(None, _NOT_LETTER)
    return (
        len(words), len(packed.translate(None, _CONTINUED)), len(packed) - len(packed.translate(None, SYMBOLS)), dup, repeat_words(words),
        len(seen) + dup, len(packed) - len(packed.translate(None, _UPPER)), len(letters), packed.count(b"!"), sum(map(eq, words, words[1:])),
    )


def _measure_batch(texts: pd.Series) -> pd.DataFrame:
    forget_codecs()
    return pd.DataFrame([measure_text(t) for t in texts], columns=list(MEASURES), dtype="int64")


def policy_mask(policy: str) -> int:
    return sum(1 << i for i, rule in enumerate(RULES) if rule in POLICIES[policy])


def ledger(docs: DataFrame, text_col: str = "text", into: str = "ledger") -> DataFrame:
    """`docs` with a struct column `into`: the measurements and `failed`, one bit per failed rule."""
    m = fresh(docs, "__measured")
    measured = F.pandas_udf(_measure_batch, ", ".join(f"{x} long" for x in MEASURES))
    wide = docs.withColumn(m, measured(col(text_col)))
    bits = "|".join(f"if({_on(rule, m)}, {1 << i}L, 0L)" for i, rule in enumerate(RULES.values()))
    return wide.withColumn(into, F.struct(*(F.col(f"{m}.{x}").alias(x) for x in MEASURES), F.expr(bits).alias("failed"))).drop(m)


def _on(rule: str, holder: str) -> str:
    return re.sub(r"\b(" + "|".join(MEASURES) + r")\b", rf"`{holder}`.\1", rule)


def passes(failed: Column, policy: str) -> Column:
    return failed.bitwiseAND(F.lit(policy_mask(policy))) == 0


def ablations(failed: DataFrame, policies=tuple(POLICIES)) -> DataFrame:
    """From a table with a column `failed`: for each policy and rule of it, rows that fail the policy, and those that would pass without the rule.

    The bits are first counted by their value, at most 2^rules rows; all policies and rules read those counts.
    """
    rules = [(p, r, policy_mask(p), 1 << i) for p in policies for i, r in enumerate(RULES) if r in POLICIES[p]]
    counts = failed.groupBy("failed").agg(F.count("*").alias("n"))
    each = F.explode(F.array(*(F.struct(F.lit(p).alias("policy"), F.lit(r).alias("rule"), F.lit(mask).alias("mask"), F.lit(bit).alias("bit")) for p, r, mask, bit in rules)))
    return (
        counts.withColumn("x", each)
        .groupBy("x.policy", "x.rule")
        .agg(
            F.sum("n").alias("n_docs"),
            F.sum(F.expr("if((failed & x.mask) != 0, n, 0)")).alias("n_failed"),
            F.sum(F.expr("if((failed & x.bit) != 0, n, 0)")).alias("n_rule_failed"),
            F.sum(F.expr("if((failed & x.mask) = x.bit, n, 0)")).alias("n_only_rule"),
        )
    )


def drop_low_quality(docs: DataFrame, text_col: str = "text", policy: str = "v2") -> DataFrame:
    """The rows of `docs` that pass the policy, all columns as they were."""
    x = fresh(docs, "__ledger")
    return ledger(docs, text_col, x).where(passes(F.col(f"{x}.failed"), policy)).drop(x)
