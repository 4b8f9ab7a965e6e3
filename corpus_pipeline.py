"""A training-corpus pipeline of the text operators: each stage's rows are written and read again by the next one.

All stages but the last return the columns of their input, whatever their names and number; an empty table passes all
of them.  A null or empty text is a document without words: the first stage rejects it.  Rows that repeat a doc_id are
judged one by one, but for near copies: there they go or stay together.  Very long texts are whole rows everywhere.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from tilemine.llm import decontaminate, lines, pieces, quality, simhash
from tilemine.llm.common import park_only, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that a rule rejects go, among them those with fewer than ten words (null, empty); rows with equal texts
    have equal verdicts, and every other row stays as it is."""
    return quality.keep_good(docs)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later runs of three equal lines, and shorter ones of ten words or more, are deleted; a document that so loses its last line
    with words goes.  Null and empty texts stay; what repeats only between rows of one id stays in both."""
    return lines.deduplicate(docs, long_words=lines.LONG_WORDS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies the rows of the smallest doc_id stay (null is the smallest); rows without words are
    near copies of each other."""
    return simhash.keep_one(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Contaminated documents go; benchmark passages in others are cut out.  Null and empty texts stay; an empty benchmark
    changes nothing."""
    return decontaminate.clean(docs, table(spark, sf_dir, "benchmark"))


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The training data: doc_id and token ids of each row, their number, and the round trip's digests.  A null or empty text
    has no ids."""
    return pieces.digests(docs, with_ids=True)


STAGES = [
    ("quality_rules", quality_rules),
    ("line_dedup", line_dedup),
    ("simhash_near_dedup", near_dedup),
    ("decontamination", decontamination),
    ("sentencepiece", encoding),
]

#: The last stage needs the tokenizer and the third its fingerprints, which SQL has not.
ORACLE_SQL = None


def _chain(spark: SparkSession, sf_dir: str, stages: list) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in stages:
        docs = park_only(spark, lambda docs=docs, stage=stage: stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rows of the last stage over the table of documents.  Each stage's rows stay in the shared folder; what it parked on its way goes."""
    return _chain(spark, sf_dir, STAGES)
