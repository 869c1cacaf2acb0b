"""The corpus pipeline: quality rules, exact dedup, n-gram Jaccard join, personal data, packing.

Each stage takes (spark, docs, sf_dir) and returns a table; all but the last return the columns of
`docs`. `run` writes each stage's result to the shared folder and reads it again for the next.

Defined results: a null text is an empty one. Quality rules reject it, as they do a text of under ten
words; of equal texts the row with the largest doc_id stays, of near copies one row of each component;
personal data replaces spans and leaves other texts alone; packing places each token of what is left
once. Rows that repeat are equal texts. An empty table gives an empty one at each stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from multiagg.llm.common import load, tabled
from multiagg.llm.exact_dedup import drop_exact_copies
from multiagg.llm.ngram_join import drop_near_copies
from multiagg.llm.packing import pack
from multiagg.llm.pii import redact
from multiagg.llm.quality_rules import drop_low_quality

#: Near duplicates within the pipeline: five words, a similarity of 0.8 or more.
NEAR_WORDS, NEAR_PERCENT = 5, 80


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_low_quality(docs)


def exact_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_exact_copies(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return drop_near_copies(docs, n=NEAR_WORDS, percent=NEAR_PERCENT)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return redact(docs, length_col="n_chars" if "n_chars" in docs.columns else None)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    pieces = pack(docs)
    return pieces.select("doc_id", "start", "length", F.crc32("ids").alias("ids_crc32"), "doc_tokens", "sequence_id", "offset")


STAGES = [("quality_rules", quality_rules), ("exact_dedup", exact_dedup), ("near_dedup", near_dedup), ("personal_data", personal_data), ("packing", packing)]

#: Shingle components, the chain field and the tokenizer are beyond SQL. Tests hold the operators against brute-force versions, and the stages by what they keep.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = tabled(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
