"""Mixing sources to target weights by the cube method.

A source's target over its size gives every one of its documents an expected multiplicity r: floor(r) whole
copies and an inclusion probability pi = r - floor(r). The flight phase moves the pi of a few documents at a
time along a null vector of the balancing constraints (documents and words of the mix), so both totals stay
exactly where they were, until all but two documents are decided. It runs in bounded chunks of a source; the
two documents that each chunk leaves meet in the next round, and a source that fits into one chunk lands: of
the ways to round the last two documents the one nearest to the word total wins, and at most three exchanges
of a taken for a left document close the gap that long documents leave in a small source.

Defined results: null text has size 0; a null source is a source of its own, last in the order; a source of
size 0 has target 0; an empty table gives no rows; rows that repeat a doc_id are separate documents. The random
choices are seeded by source and chunk and taken in the order of hashed ids, so reruns agree.
"""

from __future__ import annotations

import random
import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant.functions.shipping import ship

from .common import n_words, whole_text, written

CHUNK, CAP, WEIGHTS, SEED = 2048, 3.0, (5.0, 2.0, 1.0), 42
#: Most exchanges of a taken for a left document after a source's landing.
EXCHANGES = 3
#: Most sources that are broadcast; beyond, the join shuffles and adaptive execution splits hot sources.
BROADCAST_SOURCES = 50_000
EPS = 1e-9


def null_vector(columns: list[tuple[float, ...]]) -> list[float]:
    """A non-zero u with sum_j u_j * columns[j] = 0, for one column more than it has entries."""
    p, n = len(columns[0]), len(columns)
    rows, pivots = [[c[i] for c in columns] for i in range(p)], []
    for row in range(p):
        at = max(((abs(rows[i][j]), i, j) for i in range(row, p) for j in range(n) if j not in pivots), default=(0, 0, 0))
        if at[0] <= 1e-12:
            break
        _, i, j = at
        rows[row], rows[i] = rows[i], rows[row]
        pivots.append(j)
        top = rows[row][j]
        rows[row] = [x / top for x in rows[row]]
        for k in range(p):
            if k != row and rows[k][j]:
                f = rows[k][j]
                rows[k] = [x - f * y for x, y in zip(rows[k], rows[row], strict=True)]
    free = next(j for j in range(n) if j not in pivots)
    u = [0.0] * n
    u[free] = 1.0
    for row, j in enumerate(pivots):
        u[j] = -rows[row][free]
    return u


def flight(pi: list[float], balance: list[tuple[float, ...]], rng: random.Random) -> list[float]:
    """Move pi inside the unit cube with all balancing totals kept, until at most len(balance[0]) entries are fractional."""
    pi = list(pi)
    p = len(balance[0]) if balance else 0
    active: list[int] = []
    for k, x in enumerate(pi):
        if EPS < x < 1 - EPS:
            active.append(k)
        while len(active) > p:
            u = null_vector([balance[j] for j in active])
            up = min((1 - pi[j]) / v if v > 0 else pi[j] / -v for j, v in zip(active, u, strict=True) if abs(v) > 1e-15)
            down = min(pi[j] / v if v > 0 else (1 - pi[j]) / -v for j, v in zip(active, u, strict=True) if abs(v) > 1e-15)
            step = up if rng.random() * (up + down) < down else -down
            for j, v in zip(active, u, strict=True):
                pi[j] = min(1.0, max(0.0, pi[j] + step * v))
            active = [j for j in active if EPS < pi[j] < 1 - EPS]
    return [0.0 if x <= EPS else 1.0 if x >= 1 - EPS else x for x in pi]


def landing(pi: list[float], sizes: list[float]) -> list[float]:
    """Round the last few fractional entries: the rounding with the word total, then the count, nearest to the expected one."""
    left = [k for k, x in enumerate(pi) if 0 < x < 1]
    want, want_n = sum(pi[k] * sizes[k] for k in left), sum(pi[k] for k in left)
    best = min(range(1 << len(left)), key=lambda b: (abs(sum(sizes[k] for i, k in enumerate(left) if b >> i & 1) - want), abs(bin(b).count("1") - want_n), b))
    out = list(pi)
    for i, k in enumerate(left):
        out[k] = float(best >> i & 1)
    return out


def settle(pi: list[float], sizes: list[float], want: float) -> list[float]:
    """Exchange a taken for a left document, at most EXCHANGES times, while that brings the word total nearer."""
    pi, size = np.array(pi), np.array(sizes)
    for _ in range(EXCHANGES):
        gap, taken, left = want - float(pi @ size), np.flatnonzero(pi == 1), np.flatnonzero(pi == 0)
        if not len(taken) or not len(left):
            break
        off = np.abs(size[left][None, :] - size[taken][:, None] - gap)
        i, j = np.unravel_index(off.argmin(), off.shape)
        if off[i, j] >= abs(gap):
            break
        pi[taken[i]], pi[left[j]] = 0.0, 1.0
    return pi.tolist()


def source_targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: float = CAP) -> DataFrame:
    """(source, source_size, n_docs, source_no, target) from (source, size): shares by weight, none above cap times its size.

    One row per source, and one task for all of them: filling up by weight needs their order. It stops at the level that spends
    the total, found in the order of saturation.
    """
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"), F.count(F.lit(1)).alias("n_docs"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    per = per.withColumn("source_no", F.row_number().over(order))
    per = per.withColumn("_w", F.element_at(F.array(*map(F.lit, weights)), ((F.col("source_no") - 1) % len(weights) + 1).cast("int")))
    per = per.withColumn("_cap", F.col("source_size") * F.lit(cap))
    fill = Window.orderBy(F.col("_cap") / F.col("_w"), "source_no")
    every = fill.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = fill.rowsBetween(Window.unboundedPreceding, -1)
    level = (F.sum("source_size").over(every) - F.coalesce(F.sum("_cap").over(before), F.lit(0.0))) / F.sum("_w").over(fill.rowsBetween(Window.currentRow, Window.unboundedFollowing))
    per = per.withColumn("_level", level)
    open_level = F.when(F.col("_level") < F.col("_cap") / F.col("_w"), F.struct((F.col("_cap") / F.col("_w")).alias("r"), "source_no", F.col("_level").alias("l")))
    per = per.withColumn("_stop", F.min(open_level).over(every)["l"])
    return per.select("source", "source_size", "n_docs", "source_no", F.least(F.col("_cap"), F.coalesce(F.col("_stop") * F.col("_w"), F.col("_cap"))).alias("target"))


def _decide(land: bool):
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["size", "_h", "doc_id"], ascending=[False, True, True], kind="stable") if land else pdf.sort_values(["_h", "doc_id", "size"], kind="stable")
        sizes = pdf["size"].astype(float).tolist()
        rng = random.Random(f"{SEED}/{pdf['source_no'].iloc[0]}/{pdf['_chunk'].iloc[0]}/{len(pdf)}/{land}")
        start, balance = pdf["pi"].tolist(), [(1.0, s) for s in sizes]
        if land:
            want = sum(p * s for p, s in zip(start, sizes, strict=True))
            pi = settle(landing(flight(start, balance, rng), sizes), sizes, want)
        else:
            pi = flight(start, balance, rng)
        return pdf.assign(pi=pi).drop(columns=["_h", "_chunk", "_land"])

    return run


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: float = CAP, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", chunk: int = CHUNK, with_row: bool = False) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken (size times the copies that the mix takes).

    with_row: also _row, a hash of all columns of docs, and _times, the copies.
    """
    ship(docs.sparkSession)
    sizes = written(docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), n_words(whole_text(text_col)).alias("size"), F.xxhash64(*docs.columns).alias("_row")), "sizes")
    targets = written(source_targets(sizes, weights, cap), "targets")
    side = F.broadcast(targets) if targets.count() <= BROADCAST_SOURCES else targets
    rows = sizes.alias("d").join(side.alias("s"), F.expr("d.source <=> s.source")).select("doc_id", "size", "_row", "source_no", "source_size", "target", (F.col("target") / F.nullif("source_size", F.lit(0))).alias("_r"))
    rows = rows.withColumn("base", F.coalesce(F.floor(F.col("_r") + EPS), F.lit(0)).cast("long"))
    rows = rows.withColumn("pi", F.greatest(F.lit(0.0), F.coalesce(F.col("_r"), F.lit(0.0)) - F.col("base"))).drop("_r")
    rows = rows.withColumn("pi", F.when(F.col("pi") <= EPS, 0.0).otherwise(F.col("pi")))
    schema = rows.schema
    decided, state, n, at = rows.where("pi = 0"), rows.where("pi > 0"), None, 0
    done = [decided]
    while True:
        # the number of chunks of a source follows its undecided rows; one chunk is the last
        need = state.groupBy("source_no").agg(F.ceil(F.count(F.lit(1)) / chunk).alias("_chunks"))
        need = written(need, f"chunks{at}")
        side = F.broadcast(need) if need.count() <= BROADCAST_SOURCES else need
        dealt = state.join(side, "source_no").withColumn("_h", F.xxhash64("doc_id", "_row", F.lit(SEED + at)))  # rows, not ids: a null or repeated id doesn't gather
        dealt = dealt.withColumn("_chunk", F.pmod("_h", F.col("_chunks"))).withColumn("_land", F.col("_chunks") == 1).drop("_chunks").select(*schema.names, "_h", "_chunk", "_land")
        parts = [dealt.where(F.col("_land") == land).groupBy("source_no", "_chunk").applyInPandas(_decide(land), schema) for land in (False, True)]
        after = written(parts[0].unionByName(parts[1]), f"round{at}")
        done.append(after.where("pi in (0, 1)"))
        state, at = after.where("pi not in (0, 1)"), at + 1
        if state.isEmpty():
            break
    every = done[0]
    for x in done[1:]:
        every = every.unionByName(x)
    times = F.col("base") + F.col("pi").cast("long")
    told = every.select("doc_id", "size", "source_size", "target", (F.col("size") * times).alias("taken"), "_row", times.alias("_times"))
    return told if with_row else told.drop("_row", "_times")


def copies(docs: DataFrame, **kw) -> DataFrame:
    """docs as the mix takes them: each row as often as it is taken, all columns kept.

    Rows are matched by a 64-bit hash of all columns; equal rows share their copies. Documents of sources of size 0 add no
    words and are left out.
    """
    taken = mix(docs, with_row=True, **kw).groupBy("_row").agg(F.sum("_times").cast("int").alias("_times")).where("_times > 0")
    # all columns travel as one, so their names can't clash with ours
    rows = docs.select(F.struct("*").alias("_all"), F.xxhash64(*docs.columns).alias("_row")).join(written(taken, "taken"), "_row")
    first = rows.withColumn("_rank", F.row_number().over(Window.partitionBy("_row").orderBy("_times"))).where("_rank = 1")
    return first.withColumn("_copy", F.explode(F.sequence(F.lit(1), F.col("_times")))).select("_all.*")
