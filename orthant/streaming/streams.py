"""Queries as a stream, points as a stream with rebuilds, windows over cells, running answers."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from orthant import kernel as K
from orthant.functions.shipping import ship
from orthant.operators.knn import BROADCAST_BYTES, Knn, knn_brute, local_brute, merge_topk
from orthant.operators.layout import SpatialLayout, place
from orthant.plans.global_tree import GlobalTree, build_global_tree
from orthant.points import PointSet
from orthant.sources.tables import fresh_path


def stream_route(queries: DataFrame, tree: GlobalTree) -> DataFrame:
    """Owner lookup alone: a stateless projection."""
    return tree.routed(queries)


def stream_knn(queries: DataFrame, layout: SpatialLayout, k: int, path: str, checkpoint: str) -> StreamingQuery:
    """Answers of every micro-batch, in a folder of its own: a batch that runs again replaces its rows."""

    def answer(batch: DataFrame, number: int) -> None:
        Knn(layout, batch, k).neighbors().write.mode("overwrite").parquet(f"{path}/batch={number}")

    return queries.writeStream.foreachBatch(answer).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


@dataclass(frozen=True)
class RebuildPolicy:
    """A new tree after so many batches, or when the largest cell exceeds the mean so many times."""

    every: int = 5
    max_imbalance: float = 4.0


class RebuildingIndex:
    """All points seen so far under a tree of an earlier state, and the points since then beside it.

    Answers stay exact between rebuilds: the tree's answer and that of the exhaustive search over the delta are merged.
    Everything is in the store: a batch's points, then a line of the log that says so; a version's cells, then its line, with
    the batches it holds. So an index opened again at the same path goes on where the log ends: a batch number is taken
    once, whatever was restarted, and what was written without its line is written again.
    """

    LOG = "kind string, number int, version int, batches string, points long, balance double"

    def __init__(self, spark: SparkSession, dims: int, cells: int, path: str, policy: RebuildPolicy = RebuildPolicy(), split: K.SplitPolicy = K.SplitPolicy()) -> None:
        self.spark, self.dims, self.cells, self.path, self.policy, self.split = spark, dims, cells, path, policy, split
        self.layout: SpatialLayout | None = None
        lines = self._lines()
        self.versions = [(r["version"], r["number"], r["points"], r["balance"]) for r in sorted((r for r in lines if r["kind"] == "version"), key=lambda r: r["version"])]
        held = [r for r in lines if r["kind"] == "version" and r["version"] == len(self.versions)]
        self.done = {r["number"] for r in lines if r["kind"] == "batch"}
        self.inside = set(json.loads(held[0]["batches"])) if held else set()
        if held:
            self.layout = SpatialLayout.load(spark, f"{path}/tree", len(self.versions))

    def _lines(self) -> list:
        try:
            return self.spark.read.schema(self.LOG).parquet(f"{self.path}/log").collect()  # a line for each batch and version
        except AnalysisException as e:
            if "PATH_NOT_FOUND" not in str(e):
                raise
            return []

    def _log(self, *line) -> None:
        self.spark.createDataFrame([line], self.LOG).coalesce(1).write.mode("append").parquet(f"{self.path}/log")

    @property
    def delta(self) -> list[int]:
        """Batches that came after the tree."""
        return sorted(self.done - self.inside)

    def add(self, batch: DataFrame, number: int) -> None:
        if number in self.done:
            return
        batch.select("pid", *(f"c{i}" for i in range(self.dims))).write.mode("overwrite").parquet(f"{self.path}/delta/{number}")
        self._log("batch", number, None, None, None, None)
        self.done.add(number)
        # a tree that a rebuild left uneven, as of points in one spot, isn't rebuilt for that again before it has grown by half
        uneven = self.layout is not None and self.layout.balance() > self.policy.max_imbalance and 2 * self.delta_df().count() >= int(self.layout.n.sum())
        if self.layout is None or len(self.delta) >= self.policy.every or uneven:
            self.rebuild(number)

    def rebuild(self, number: int) -> None:
        every = self.delta_df()
        if self.layout is not None:
            every = self.layout.points.drop("cell").unionByName(every)
        points = PointSet(every, self.dims)
        version = len(self.versions) + 1
        layout = place(points, build_global_tree(points, self.cells, self.split), self.split, version=version)
        layout.save(f"{self.path}/tree")
        line = (version, number, int(layout.n.sum()), layout.balance())
        self._log("version", number, version, json.dumps(sorted(self.done)), *line[2:])
        self.layout, self.inside = layout, set(self.done)
        self.versions.append(line)

    def delta_df(self) -> DataFrame:
        columns = ", ".join(f"c{i} double" for i in range(self.dims))
        return self.spark.read.schema(f"pid long, {columns}").parquet(*(f"{self.path}/delta/{n}" for n in self.delta))

    def knn(self, queries: DataFrame, k: int) -> DataFrame:
        found = Knn(self.layout, queries, k).neighbors().select("qid", "pid", "d2")
        if self.delta:
            found = found.unionByName(knn_brute(PointSet(self.delta_df(), self.dims), queries, k).select("qid", "pid", "d2"))
        return merge_topk(found, k).select("qid", "rank", "pid", "d2", "dist")

    def consume(self, points: DataFrame, checkpoint: str) -> StreamingQuery:
        return points.writeStream.foreachBatch(self.add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def event_time(ts: str = "ts") -> Column:
    """Watermarks want an instant; stored times have no zone and are taken as UTC."""
    return F.to_utc_timestamp(F.col(ts).cast("timestamp"), F.current_timezone())


def windowed_counts(points: DataFrame, by: list[str | Column], window: Column, late: str = "1 hour", time: str = "time") -> DataFrame:
    """Counts by window and key; rows later than the watermark are left out of windows that are closed."""
    return points.withWatermark(time, late).groupBy(window.alias("w"), *by).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *by, "n")


def windowed_cell_counts(points: DataFrame, tree: GlobalTree, duration: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    return windowed_counts(tree.routed(points), ["cell"], F.window("time", duration, slide), late)


def distinct_requests(queries: DataFrame, late: str = "1 hour", time: str = "time") -> DataFrame:
    return queries.withWatermark(time, late).dropDuplicatesWithinWatermark(["qid"])


def best_pairs(k: int) -> StatefulProcessor:
    """Keeps the k best pairs of a query. A local class: the planner's own Python process gets it by value."""

    class Best(StatefulProcessor):
        def init(self, handle: StatefulProcessorHandle) -> None:
            self.best = handle.getListState("best", "d2 double, pid long")

        def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
            have = [(r[0], r[1]) for r in self.best.get()]
            for part in rows:
                have += list(zip(part["d2"].tolist(), part["pid"].tolist(), strict=True))
                have = sorted(set(have))[:k]
            self.best.put(have)
            yield pd.DataFrame({"qid": [key[0]] * len(have), "rank": range(1, len(have) + 1), "pid": [p for _, p in have], "d2": [d for d, _ in have]})

        def close(self) -> None:
            pass

    return Best()


def continuous_knn(points: DataFrame, queries: DataFrame, dims: int, k: int) -> DataFrame:
    """The running answer of standing queries as points arrive: an update of every query that a batch touches.

    The queries go to every worker, which is for a checked number of them; a worker passes on k pairs a query of its points,
    and state holds k pairs for each query.
    """
    spark = points.sparkSession
    ship(spark)
    coords = [f"c{i}" for i in range(dims)]
    n = queries.count()
    if n * 8 * (dims + 1) > BROADCAST_BYTES:
        raise ValueError(f"{n} standing queries are too many to ship")
    rows = queries.select("qid", *coords).toPandas()
    shared = spark.sparkContext.broadcast((rows["qid"].to_numpy(), rows[coords].to_numpy(dtype=float).reshape(-1, dims)))
    pairs = points.select("pid", *coords).mapInArrow(local_brute(shared, dims, k, float("inf"), False), "qid long, pid long, d2 double")
    return pairs.groupBy("qid").transformWithStateInPandas(best_pairs(k), "qid long, rank int, pid long, d2 double", "Update", "none")


#: State of streams lies in RocksDB, on the executors' disks, and not as objects in their heaps.
STATE_STORE = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def run_to_store(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there and give its result table, which goes to the shared folder and not to the driver.

    A batch has a folder of its own, so one that runs again replaces its rows; in complete mode the last batch is the result.
    """
    spark: SparkSession = df.sparkSession
    out, last = fresh_path(spark, "result"), [-1]

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{out}/{number}")
        last[0] = max(last[0], number)

    before = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", STATE_STORE)
    try:
        query = df.writeStream.foreachBatch(keep).outputMode(mode).option("checkpointLocation", fresh_path(spark, "checkpoint")).trigger(availableNow=True).start()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", before)
    query.awaitTermination()
    if last[0] < 0:
        return spark.createDataFrame([], df.schema)
    numbers = [last[0]] if mode == "complete" else range(last[0] + 1)
    return spark.read.schema(df.schema).parquet(*(f"{out}/{n}" for n in numbers))
