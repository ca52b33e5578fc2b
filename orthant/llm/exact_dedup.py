"""Exact dedup with a heavy-hitter split.

One scan turns each text into its SHA-256. A bounded Misra-Gries style frequent-items sketch proposes
heavy digests; their counts and winners are verified by an exact, map-side combined aggregate and then
broadcast (at most ``max_heavy`` rows), so copies of a heavy text never meet in one task. All other
digests go through an ordinary shuffle.

Defined results: null text counts as empty; of equal texts the row with the largest id stays; rows that
repeat the winning id count as copies too, and only one of them stays; a null id loses to any other.
An empty table gives no rows. Columns other than id and text are ignored, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import whole_text, written

#: Bound of the broadcast side and of the sketch; digests above a share of 1 / (3/4 * SKETCH_ITEMS) can't be missed, and there
#: are no more than MAX_HEAVY of those, so no group of the shuffled rest is larger.
MAX_HEAVY, SKETCH_ITEMS, MIN_HEAVY_ROWS = 3072, 4096, 64


def heavy_digests(keyed: DataFrame, max_heavy: int = MAX_HEAVY, sketch_items: int = SKETCH_ITEMS, min_rows: int = MIN_HEAVY_ROWS) -> DataFrame:
    """At most max_heavy rows (_hex, _keep, _n): verified winner and count of the frequent digests."""
    sketch = keyed.agg(F.expr(f"approx_top_k(_hex, {max_heavy}, {sketch_items})").alias("top"))
    proposed = sketch.select(F.explode("top").alias("t")).where(F.col("t.count") >= min_rows).select(F.col("t.item").alias("_hex"))
    return (
        keyed.join(F.broadcast(proposed), "_hex")
        .groupBy("_hex")
        .agg(F.max("_id").alias("_keep"), F.count(F.lit(1)).alias("_n"))
    )


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **bounds: int) -> DataFrame:
    """One row per document: id, keep_id, group_size, kept, text_sha256."""
    keyed = written(docs.select(F.col(id_col).alias("_id"), F.sha2(whole_text(text_col).cast("binary"), 256).alias("_hex")), "digests")
    heavy = written(heavy_digests(keyed, **bounds), "heavy")
    found = keyed.join(F.broadcast(heavy), "_hex", "left")
    # map side: a heavy row's fate is known without a shuffle; only rows with the winning id are ranked
    copies = found.where("_n is not null and not (_id <=> _keep)").select("_id", "_hex", "_keep", "_n", F.lit(False).alias("_kept"))
    winners = found.where("_n is not null and _id <=> _keep").withColumn("_kept", F.row_number().over(Window.partitionBy("_hex").orderBy("_id")) == 1)
    group = Window.partitionBy("_hex")
    rest = (
        keyed.join(F.broadcast(heavy), "_hex", "left_anti")
        .withColumn("_rank", F.row_number().over(group.orderBy(F.col("_id").desc_nulls_last())))
        .select("_id", "_hex", F.max("_id").over(group).alias("_keep"), F.count(F.lit(1)).over(group).alias("_n"), (F.col("_rank") == 1).alias("_kept"))
    )
    every = copies.unionByName(winners.select(copies.columns)).unionByName(rest)
    return every.select(F.col("_id").alias(id_col), F.col("_keep").alias("keep_id"), F.col("_n").alias("group_size"), F.col("_kept").alias("kept"), F.col("_hex").alias("text_sha256"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **bounds: int) -> DataFrame:
    """docs without the copies, all columns kept.

    Copies of heavy digests end in the map tasks; what is left is shuffled once, by digest. No join by id, so null and
    repeated ids are safe: of rows that repeat id and text one stays.
    """
    # all columns travel as one, so their names can't clash with ours
    rows = docs.select(F.struct("*").alias("_all"), F.col(id_col).alias("_id"), F.sha2(whole_text(text_col).cast("binary"), 256).alias("_hex"))
    heavy = written(heavy_digests(written(rows.select("_id", "_hex"), "digests"), **bounds), "heavy")
    left = rows.join(F.broadcast(heavy), "_hex", "left").where(F.col("_n").isNull() | F.col("_id").eqNullSafe(F.col("_keep")))
    ranked = left.withColumn("_rank", F.row_number().over(Window.partitionBy("_hex").orderBy(F.col("_id").desc_nulls_last())))
    return ranked.where("_rank = 1").select("_all.*")


OP4_SQL = """
SELECT doc_id,
       max(doc_id) OVER (PARTITION BY text_sha256) AS keep_id,
       count(*) OVER (PARTITION BY text_sha256) AS group_size,
       row_number() OVER (PARTITION BY text_sha256 ORDER BY doc_id DESC NULLS LAST) = 1 AS kept,
       text_sha256
FROM (SELECT doc_id, sha256(coalesce(text, '')) AS text_sha256 FROM documents) AS digests
"""
