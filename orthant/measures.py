"""Times, phase shares, work counts, depth and balance."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orthant import kernel as K
from orthant.functions.shipping import ship
from orthant.operators.knn import Knn, merge_topk, remote_requests, search_cells
from orthant.operators.layout import SpatialLayout, pack_cells
from orthant.plans.global_tree import build_global_tree
from orthant.points import PointSet
from orthant.sources.tables import written


class Phases:
    """Seconds by phase, each made real before the next begins."""

    def __init__(self) -> None:
        self.seconds: dict[str, float] = {}

    def run(self, name: str, f: Callable):
        began = time.perf_counter()
        out = f()
        if isinstance(out, DataFrame):
            out = written(out, name)
        self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began
        return out

    def to_df(self, spark: SparkSession) -> DataFrame:
        total = sum(self.seconds.values()) or 1.0
        return spark.createDataFrame([(n, s, s / total) for n, s in self.seconds.items()], "phase string, seconds double, share double")


def build_phases(points: PointSet, cells: int, policy: K.SplitPolicy = K.SplitPolicy(), bucket_size: int = 32) -> tuple[SpatialLayout, Phases]:
    """Global tree, redistribution, local trees, packing: the exchange alone, then trees that are only counted, then the whole."""
    p, spark = Phases(), points.df.sparkSession
    tree = p.run("global_tree", lambda: build_global_tree(points, cells, policy))
    n = max(1, min(tree.cells, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    routed = p.run("redistribution", lambda: tree.routed(points.positions()).repartition(n, "cell"))
    p.run("local_trees", lambda: local_shapes(routed, tree.dims, bucket_size, policy))
    layout = p.run("packing", lambda: pack_cells(routed, tree, policy, bucket_size))
    p.seconds["packing"] = max(0.0, p.seconds["packing"] - p.seconds["local_trees"])  # it built the trees once more
    return layout, p


def query_phases(layout: SpatialLayout, queries: DataFrame, k: int = 5, prune: str = "mbr") -> tuple[DataFrame, Phases]:
    """Owner lookup, sending queries, local search, finding remote cells, sending requests, remote search, merge.

    The two sending phases are the exchanges alone: the share of communication.
    """
    p, coords = Phases(), [f"c{i}" for i in range(layout.dims)]
    asked = p.run("owner_lookup", lambda: layout.tree.routed(queries.select("qid", *coords)).withColumn("r2", F.lit(float("inf"))))
    sent = p.run("send_queries", lambda: asked.repartition(layout.parts, "cell"))
    owner = p.run("local_knn", lambda: search_cells(layout, sent, k, 0))

    def requests() -> DataFrame:
        radius = owner.where("pid is not null").groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("m"))
        bound = asked.withColumnRenamed("cell", "owner").join(radius, "qid", "left").withColumn("r2", F.when(F.col("n") >= k, F.col("m")).otherwise(F.col("r2")))
        return remote_requests(layout, bound, prune)

    requested = p.run("identify_remote", requests)
    moved = p.run("send_requests", lambda: requested.repartition(layout.parts, "cell"))
    remote = p.run("remote_knn", lambda: search_cells(layout, moved, k, 1))
    answer = p.run("merge", lambda: merge_topk(owner.unionByName(remote), k))
    return answer, p


def query_work(search: Knn) -> DataFrame:
    """One row: shares and means over the queries."""
    s = search.stats()
    return s.agg(
        F.count(F.lit(1)).alias("queries"), F.round(F.avg((F.col("remote_cells") > 0).cast("double")), 6).alias("remote_share"), F.round(F.avg("remote_cells"), 6).alias("remote_cells"),
        F.round(F.avg("remote_in_answer"), 6).alias("remote_in_answer"), F.round(F.avg("nodes_visited"), 6).alias("nodes_visited"), F.round(F.avg("points_compared"), 6).alias("points_compared"),
    )


def tree_shape(layout: SpatialLayout) -> DataFrame:
    """One row: cells, depth with the local trees, buckets, balance of the cells; facts that the build left."""
    f, g = layout.facts, layout.tree.depth
    row = (layout.cells, g, f["tree_depth"], g + f["tree_depth"], f["buckets"], f["largest"], round(layout.balance(), 6))
    return layout.packed.sparkSession.createDataFrame([row], "cells int, global_depth int, local_depth int, depth int, buckets long, largest_bucket int, balance double")


def median_error(layout: SpatialLayout) -> float:
    """Mean distance of the global splits' shares from those wanted."""
    n, tree = np.zeros(len(layout.tree.left)), layout.tree
    for i, leaf in enumerate(tree.leaves()):
        n[leaf] = layout.n[i]
    off = []
    for node in range(len(tree.left) - 1, -1, -1):
        if tree.left[node] >= 0:
            n[node] = n[tree.left[node]] + n[tree.right[node]]
            if n[node]:
                off.append(abs(n[tree.left[node]] / n[node] - tree.want[tree.left[node]] / tree.want[node]))
    return float(np.mean(off)) if off else 0.0


def local_shapes(routed: DataFrame, dims: int, bucket_size: int = 32, policy: K.SplitPolicy = K.SplitPolicy()) -> DataFrame:
    """(cell, buckets, depth) of trees that are built and not kept."""
    ship(routed.sparkSession)

    def run(part: pa.Table) -> pa.Table:
        tree = K.build(np.stack([part.column(f"c{i}").to_numpy() for i in range(dims)], axis=1), part.column("pid").to_numpy(), bucket_size, policy)
        return pa.table({"cell": pa.array([part.column("cell")[0].as_py()], pa.int32()), "buckets": pa.array([len(tree.leaves)], pa.int32()), "depth": pa.array([int(tree.depth.max())], pa.int32())})

    return routed.groupBy("cell").applyInArrow(run, "cell int, buckets int, depth int")
