"""A corpus pipeline of five stages: language, exact copies, near copies, source weights, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from orthant.llm import exact_dedup, langid, mixing, packing, simhash
from orthant.llm.common import table, written
from orthant.llm.tokens import vocabulary


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is recognised.

    Null texts, empty ones and those without a letter go; a null label isn't learned from; a null id is an id like any other;
    without any label to learn from no language is recognised, and all go; repeated rows stay together; no rows give none.
    """
    return langid.keep_identified(docs)


def without_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the document with the largest id.

    Null text equals empty text; a null id loses to any other; of rows that repeat id and text one stays; no rows give none.
    """
    return exact_dedup.keep_one(docs)


def without_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of near copies the document with the smallest id.

    Texts without words, null ones too, are near copies of each other; a null id loses to any other; of rows with the same
    id and fingerprint one stays; no rows give none.
    """
    return simhash.keep_first(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the weighted mix of the sources takes them.

    A null source is a source, the last one; texts without words have size 0, and a source of such texts only has target 0 and
    goes; null and repeated ids are rows like any other, and equal rows share their copies; no rows give none.
    """
    return mixing.copies(docs)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents in sequences of at most 2048 tokens.

    Null text is an empty document, its closing id alone; repeated rows are packed each; long texts are cut, never dropped;
    null ids stay null; no rows give none.
    """
    return packing.pack(docs, vocabulary("byte_bpe_50k.json"))


STAGES = [
    ("language", identified),
    ("exact_dedup", without_copies),
    ("near_dedup", without_near_copies),
    ("mix", mixed),
    ("pack", packed),
]

#: The mix and the packing can't be written in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
