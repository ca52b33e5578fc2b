"""Shared plumbing: tables, lineage cuts, the word pattern."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from orthant.functions.shipping import ship
from orthant.sources import tables
from orthant.sources.tables import fresh_path, written

__all__ = ["WORD", "distinct_sample", "fresh_path", "let", "n_words", "shuffle_partitions", "table", "whole_text", "written"]

#: A word is a maximal run of characters other than space and the five ASCII controls tab to CR.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return tables.table(spark, sf_dir, name)


def whole_text(name: str = "text") -> Column:
    return F.coalesce(F.col(name), F.lit(""))


def n_words(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body of a value that is computed once, however often body names it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def distinct_sample(rows: DataFrame, most: int, n: int, seed: int) -> DataFrame:
    """At most so many of the distinct rows, chosen by a hash of the whole row; n: how many rows there are, about.

    Rows, not ids, are chosen, and a repeated row counts once, so neither an id nor a row that is everywhere enlarges it.
    """
    keyed = rows.withColumn("_key", F.xxhash64(F.lit(seed), *rows.columns))
    keyed = keyed.where(F.pmod("_key", F.lit(1 << 30)) < int(min(1.0, 8 * most / max(1, n)) * (1 << 30)))
    chosen = keyed.select("_key").distinct().orderBy("_key").limit(most)
    return keyed.join(F.broadcast(chosen), "_key").groupBy("_key").agg(*(F.first(c).alias(c) for c in rows.columns)).drop("_key")
