"""Choice of a strategy from counts that are cheap to get."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from orthant import kernel as K
from orthant.operators.knn import BROADCAST_BYTES, Knn, knn_brute, knn_replicated
from orthant.operators.layout import SpatialLayout, build_layout, collapse_colocated
from orthant.points import PointSet

CELL_BYTES = 128 << 20
#: A largest cell of so many times the mean calls for collapsing co-located points.
HOT = 4.0


@dataclass(frozen=True)
class Choice:
    strategy: str
    cells: int
    why: str


def choose(n: int, q: int, dims: int, cores: int, broadcast_bytes: int = BROADCAST_BYTES) -> Choice:
    """brute for few pairs, replicate for small point sets, tree else; many dimensions leave nothing to prune."""
    size = n * 8 * (dims + 1)
    cells = max(1, min(10 * cores, -(-n // 256)), -(-size // CELL_BYTES))
    if n * q <= 20_000_000:
        return Choice("brute", 1, f"{n} x {q} pairs are few")
    if size <= broadcast_bytes // 4 and q >= n // 10:
        return Choice("replicate", 1, f"{size} bytes of points fit into every worker")
    if dims > 15 and n * q <= 10**12:
        return Choice("brute", 1, f"boxes in {dims} dimensions prune next to nothing")
    return Choice("tree", cells, f"{size} bytes of points in {cells} cells")


def fan_out(layout: SpatialLayout, queries: DataFrame, k: int, size: int = 1000) -> float:
    """Mean number of remote cells of a few queries, measured."""
    few = queries.orderBy("qid").limit(size)
    r = Knn(layout, few, k).stats().agg({"remote_cells": "avg"}).first()[0]
    return float(r or 0)


def knn_join(points: PointSet, queries: DataFrame, k: int = 5, strategy: str = "auto", cells: int | None = None, policy: K.SplitPolicy = K.SplitPolicy(), max_radius: float | None = None, exclude_self: bool = False) -> DataFrame:
    """neighbors of every query by the chosen strategy, or by the one that the counts suggest."""
    spark = points.df.sparkSession
    if strategy == "auto":
        plan = choose(points.df.count(), queries.count(), points.dims, spark.sparkContext.defaultParallelism)
        strategy, cells = plan.strategy, cells or plan.cells
    options = {"max_radius": max_radius, "exclude_self": exclude_self}
    if strategy == "brute":
        return knn_brute(points, queries, k, **options)
    if strategy == "replicate":
        return knn_replicated(points, queries, k, policy=policy, **options)
    layout = build_layout(points, cells or 10 * spark.sparkContext.defaultParallelism, policy)
    if layout.cells > 1 and layout.balance() > HOT:
        # no split separates points in one spot; of those only the first k can answer (one more where a query is one of them)
        layout = build_layout(PointSet(collapse_colocated(points, k + exclude_self), points.dims), layout.cells, policy)
    return Knn(layout, queries, k, **options).neighbors()
