"""Exact k nearest neighbours of a query set, distributed.

Queries go to the cell that owns their place; its answer bounds the radius; only cells whose box comes within that radius are
asked again, with the radius as their bound; the best k of all lists win. Both searches join the packed cells, read where they
lie, with the queries sent to them, packed likewise; what is exchanged are queries, requests and at most k rows per request.
The owner's pass finds the remote cells too, while it has the radius at hand.
"""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant import kernel as K
from orthant.functions.shipping import ship
from orthant.operators.layout import SpatialLayout, array_at, build_layout, collapse_colocated, tree_at
from orthant.points import PointSet
from orthant.sources.tables import written

#: Rows of a search: hop 0 and 1 are candidates of the owner and of remote cells; hop -1 asks cell for a query's place (at) and r2.
FOUND = "qid long, pid long, d2 double, cell int, hop int, visited long, compared long, r2 double, at array<double>"
_NAMES = [x.split()[0] for x in FOUND.split(", ")]
ASK = -1
#: Points, or boxes of cells, shipped to every worker at most, in bytes; queries of a cell that are searched together.
BROADCAST_BYTES, BATCH_ROWS = 256 << 20, 131_072


def _matrix(part: pa.Table | pa.RecordBatch, dims: int) -> np.ndarray:
    return np.stack([part.column(f"c{i}").to_numpy(zero_copy_only=False) for i in range(dims)], axis=1) if part.num_rows else np.zeros((0, dims))


def _answers(found: K.Found, qid: np.ndarray, cell: int, hop: int) -> pa.RecordBatch:
    row, rank = np.nonzero(found.ids != K.NO_ID)
    # a query without any answer keeps a row, for its counters
    none = np.flatnonzero((found.ids == K.NO_ID).all(axis=1))
    row, rank = np.concatenate([row, none]), np.concatenate([rank, np.zeros(len(none), dtype=np.int64)])
    lacks, n = found.ids[row, rank] == K.NO_ID, len(row)
    columns = [
        pa.array(qid[row]), pa.array(found.ids[row, rank], mask=lacks), pa.array(found.d2[row, rank], mask=lacks), pa.array(np.full(n, cell, dtype=np.int32)), pa.array(np.full(n, hop, dtype=np.int32)),
        pa.array(found.visited[row]), pa.array(found.compared[row]), pa.nulls(n, pa.float64()), pa.nulls(n, pa.list_(pa.float64())),
    ]
    return pa.RecordBatch.from_arrays(columns, _NAMES)


def _asks(qid: np.ndarray, q: np.ndarray, r2: np.ndarray, cell: np.ndarray) -> pa.RecordBatch:
    n, dims = q.shape
    at = pa.ListArray.from_arrays(pa.array(np.arange(0, (n + 1) * dims, dims, dtype=np.int32)[: n + 1]), pa.array(q.ravel()))
    columns = [pa.array(qid), pa.nulls(n, pa.int64()), pa.nulls(n, pa.float64()), pa.array(cell.astype(np.int32)), pa.array(np.full(n, ASK, dtype=np.int32)), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.array(r2), at]
    return pa.RecordBatch.from_arrays(columns, _NAMES)


def _search_rows(dims: int, k: int, exclude_self: bool, hop: int, order: str, shared, metric: str, chunk: int):
    """Rows of packed cells joined with packed queries; with shared boxes, also the asks of the queries' remote cells."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                asked = batch.column("_asked").slice(row, 1).flatten()
                column = lambda name: asked.field(name).to_numpy(zero_copy_only=False)  # noqa: B023, E731
                qid, r2, cell = column("qid"), column("r2"), batch.column("cell")[row].as_py()
                q = np.stack([column(f"c{i}") for i in range(dims)], axis=1)
                found = K.search(tree_at(batch, row, dims), q, k, r2, qid if exclude_self else None, order, chunk, metric)
                yield _answers(found, qid, cell, hop)
                if shared is not None and batch.column("piece")[row].as_py() == 0:
                    r2 = np.minimum(r2, found.d2[:, -1])  # k answers bound the radius, fewer are padded by infinity
                    at, far = shared.value.within(q, r2)
                    at, far = at[far != cell], far[far != cell]
                    yield _asks(qid[at], q[at], r2[at], far)

    return run


def packed_queries(layout: SpatialLayout, queries: DataFrame, n: int, batch_rows: int | None = None) -> DataFrame:
    """(cell, batch, _asked): the queries (qid, coordinates, r2, cell) of a cell as one value, or as several of about BATCH_ROWS.

    Only more than BATCH_ROWS queries can fill a cell beyond it; then one count by cell tells which cells are dealt. Smaller
    batches are cut inside the value, since each value meets a copy of the whole packed cell.
    """
    coords, most = [f"c{i}" for i in range(layout.dims)], max(batch_rows or 0, BATCH_ROWS)
    own = queries.select(*(F.col(c).alias(c) for c in ("qid", *coords, "r2", "cell"))).withColumn("_batch", F.lit(0))
    if n > most:
        need = own.groupBy("cell").count().where(F.col("count") > most).select("cell", F.ceil(F.col("count") / most).cast("int").alias("_batches"))
        own = own.join(F.broadcast(need), "cell", "left").withColumn("_batch", F.coalesce(F.pmod(F.xxhash64("qid"), "_batches"), F.lit(0)).cast("int")).drop("_batches")
    return own.repartition(layout.parts, "cell").groupBy("cell", "_batch").agg(F.collect_list(F.struct("qid", *coords, "r2")).alias("_asked"))


def search_cells(layout: SpatialLayout, queries: DataFrame, k: int, hop: int, exclude_self: bool = False, order: str = "near_first", batch_rows: int | None = None, n: int | None = None, boxes: Boxes | None = None, metric: str = "l2") -> DataFrame:
    """Rows of FOUND for n queries (qid, coordinates, r2, cell), from the stored trees. The packed cells aren't exchanged."""
    spark = layout.packed.sparkSession
    ship(spark)
    asked = packed_queries(layout, queries, queries.count() if n is None else n, batch_rows)
    names = ["pid", *(f"c{i}" for i in range(layout.dims)), *(c for c in layout.packed.columns if c.startswith("node_"))]
    met = layout.packed.select("cell", "piece", *names).join(asked.hint("shuffle_hash"), "cell").drop("_batch")
    shared = None if boxes is None else spark.sparkContext.broadcast(boxes)
    return met.mapInArrow(_search_rows(layout.dims, k, exclude_self, hop, order, shared, metric, min(batch_rows or 2048, 2048)), FOUND)


class Boxes:
    """Boxes of the cells under the nodes of the tree, for finding those within a radius; as large as the tree, which is checked."""

    def __init__(self, layout: SpatialLayout, prune: str, metric: str = "l2") -> None:
        self.metric = metric
        if layout.cells * layout.dims * 32 > BROADCAST_BYTES:
            raise ValueError(f"{layout.cells} boxes of {layout.dims} dimensions are too many to ship; build larger cells")
        lo, hi = layout.tree.regions() if prune == "region" else (layout.lo, layout.hi)
        if prune == "none":
            lo, hi = np.full_like(layout.lo, -np.inf), np.full_like(layout.hi, np.inf)
        self.left, self.right, self.cell = np.array(layout.tree.left), np.array(layout.tree.right), layout.tree.cell_of_node()
        self.lo, self.hi = np.full((len(self.left), layout.dims), np.inf), np.full((len(self.left), layout.dims), -np.inf)
        for n in range(len(self.left) - 1, -1, -1):
            if self.left[n] < 0:
                self.lo[n], self.hi[n] = lo[self.cell[n]], hi[self.cell[n]]
            else:
                self.lo[n] = np.minimum(self.lo[self.left[n]], self.lo[self.right[n]])
                self.hi[n] = np.maximum(self.hi[self.left[n]], self.hi[self.right[n]])

    def within(self, q: np.ndarray, r2: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(query, cell) of all boxes within the radius, found by descending the tree."""
        at, node, out = np.arange(len(q)), np.zeros(len(q), dtype=np.int64), []
        while len(at):
            keep = K.box_distance(q[at], self.lo[node], self.hi[node], self.metric) <= r2[at]
            at, node = at[keep], node[keep]
            leaf = self.left[node] < 0
            out.append((at[leaf], self.cell[node[leaf]]))
            at, node = np.repeat(at[~leaf], 2), np.stack([self.left[node[~leaf]], self.right[node[~leaf]]], axis=1).ravel()
        return np.concatenate([np.zeros(0, dtype=np.int64), *(a for a, _ in out)]), np.concatenate([np.zeros(0, dtype=np.int64), *(c for _, c in out)])


def _requests(shared, dims: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        boxes = shared.value
        for batch in batches:
            owner, r2, q = batch.column("owner").to_numpy(), batch.column("r2").to_numpy(zero_copy_only=False), _matrix(batch, dims)
            at, cell = boxes.within(q, r2)
            far = cell != owner[at]
            at, cell = at[far], cell[far]
            yield _asks(batch.column("qid").to_numpy()[at], q[at], r2[at], cell)

    return run


def as_queries(asks: DataFrame, dims: int) -> DataFrame:
    """(qid, coordinates, r2, cell) of rows that ask."""
    return asks.select("qid", *(F.get("at", F.lit(i)).alias(f"c{i}") for i in range(dims)), "r2", "cell")


def remote_requests(layout: SpatialLayout, queries: DataFrame, prune: str = "mbr") -> DataFrame:
    """(qid, coordinates, r2, cell) for every cell within r2 of a query (qid, coordinates, r2, owner), but not its owner."""
    ship(queries.sparkSession)
    shared = queries.sparkSession.sparkContext.broadcast(Boxes(layout, prune))
    read = queries.select("qid", *(f"c{i}" for i in range(layout.dims)), "r2", "owner")
    return as_queries(read.mapInArrow(_requests(shared, layout.dims), FOUND), layout.dims)


def radius_bound(radius: float, metric: str = "l2") -> float:
    return float(radius) ** 2 if metric == "l2" else float(radius)


def merge_topk(found: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """neighbors(qid, rank, pid, d2, dist) from candidate rows (qid, pid, d2); only k rows per task and query are exchanged."""
    best = found.where("pid is not null").withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy("d2", "pid"))).where(F.col("rank") <= k)
    return best.withColumn("dist", F.sqrt("d2") if metric == "l2" else F.col("d2"))


class Knn:
    """The passes of one search, for those who want more than the answer.

    Building it runs the owners' pass and stores what that found: candidates, and the requests to remote cells.
    """

    def __init__(self, layout: SpatialLayout, queries: DataFrame, k: int = 5, max_radius: float | None = None, prune: str = "mbr", exclude_self: bool = False, order: str = "near_first", batch_rows: int | None = None, metric: str = "l2") -> None:
        if k < 1:
            raise ValueError("k must be at least 1")
        self.layout, self.k, self.metric = layout, k, metric
        coords = [f"c{i}" for i in range(layout.dims)]
        r2 = F.lit(float("inf") if max_radius is None else radius_bound(max_radius, metric))
        own = queries.select("qid", *coords)
        self.asked = layout.tree.routed(own).withColumn("r2", r2)
        boxes, empty = Boxes(layout, prune, metric), layout.n == 0
        first = search_cells(layout, self.asked, k, 0, exclude_self, order, batch_rows, boxes=boxes, metric=metric)
        if empty.any() and layout.n.sum():  # queries whose own cell has no points ask all cells in reach at once
            shared = queries.sparkSession.sparkContext.broadcast(boxes)
            alone = self.asked.where(F.col("cell").isin(np.flatnonzero(empty).tolist())).withColumnRenamed("cell", "owner")
            first = first.unionByName(alone.select("qid", *coords, "r2", "owner").mapInArrow(_requests(shared, layout.dims), FOUND))
        stored = written(first, "owner")
        self.owner = stored.where(F.col("hop") != ASK)
        self.requests = as_queries(stored.where(F.col("hop") == ASK), layout.dims)
        self.remote = search_cells(layout, self.requests, k, 1, exclude_self, order, batch_rows, metric=metric)
        self.found = self.owner.unionByName(self.remote).drop("r2", "at")

    @property
    def bounded(self) -> DataFrame:
        """(qid, coordinates, owner, r2): the queries with the radius that their owner gave them."""
        radius = self.owner.where("pid is not null").groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("m"))
        bound = self.asked.withColumnRenamed("cell", "owner").join(radius, "qid", "left")
        return bound.withColumn("r2", F.when(F.col("n") >= self.k, F.col("m")).otherwise(F.col("r2"))).drop("n", "m")

    def neighbors(self) -> DataFrame:
        return merge_topk(self.found, self.k, self.metric).select("qid", "rank", "pid", "d2", "dist")

    def stats(self) -> DataFrame:
        """Per query: cells contacted, remote cells, nodes visited, points compared, remote rows in the answer."""
        found = written(self.found, "found")  # looked at twice
        per_cell = found.groupBy("qid", "cell").agg(F.max("visited").alias("v"), F.max("compared").alias("c"), F.max("hop").alias("hop"))
        told = per_cell.groupBy("qid").agg(F.count(F.lit(1)).cast("int").alias("cells_contacted"), F.sum("hop").cast("int").alias("remote_cells"), F.sum("v").alias("nodes_visited"), F.sum("c").alias("points_compared"))
        won = merge_topk(found, self.k).groupBy("qid").agg(F.sum("hop").cast("int").alias("remote_in_answer"))
        counts = ["cells_contacted", "remote_cells", "nodes_visited", "points_compared", "remote_in_answer"]
        return self.asked.select("qid").join(told, "qid", "left").join(won, "qid", "left").fillna(0, counts)


def knn(layout: SpatialLayout, queries: DataFrame, k: int = 5, **options) -> DataFrame:
    """neighbors(qid, rank, pid, d2, dist), exact: ordered by distance, then id.

    metric: l2, l1 or linf; for the latter two d2 is the distance itself. Boxes bound all three, so the tree serves any.
    """
    return Knn(layout, queries, k, **options).neighbors()


def knn_pipelined(layout: SpatialLayout, queries: DataFrame, k: int = 5, batches: int = 4, ahead: int = 2, **options) -> DataFrame:
    """The same answer in batches of queries of which so many are under way at a time: one batch's owners' pass runs while the
    remote pass of the batch before it waits for its last tasks, and each batch's requests are shorter lived."""

    def one(i: int) -> DataFrame:
        part = queries.where(F.pmod(F.xxhash64("qid"), F.lit(batches)) == i)
        return written(Knn(layout, part, k, **options).neighbors(), f"answers{i}")

    with ThreadPoolExecutor(ahead) as pool:
        parts = list(pool.map(one, range(batches)))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def found_in_all(layout: SpatialLayout, queries: DataFrame, k: int = 5, max_radius: float | None = None, exclude_self: bool = False) -> DataFrame:
    """Candidates of every query from every cell: k rows from each."""
    coords = [f"c{i}" for i in range(layout.dims)]
    asked = queries.select("qid", *coords).withColumn("r2", F.lit(float("inf") if max_radius is None else max_radius**2))
    asked = asked.withColumn("cell", F.explode(F.sequence(F.lit(0), F.lit(layout.cells - 1)).cast("array<int>")))
    return search_cells(layout, asked, k, 0, exclude_self).drop("r2", "at")


def knn_all_nodes(layout: SpatialLayout, queries: DataFrame, k: int = 5, max_radius: float | None = None, exclude_self: bool = False) -> DataFrame:
    """Every query in every part, k rows from each: the strategy without a global tree."""
    return merge_topk(found_in_all(layout, queries, k, max_radius, exclude_self), k).select("qid", "rank", "pid", "d2", "dist")


def local_brute(shared, dims: int, k: int, r2: float, exclude_self: bool, metric: str = "l2"):
    """k pairs of each shared query (ids, places) from the points of a task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        qid, q = shared.value
        best = K.Nearest(q, k, r2, qid if exclude_self else None, metric)
        for batch in batches:
            best.meet(_matrix(batch, dims), batch.column("pid").to_numpy())
        d2, ids = best.answers()
        row, rank = np.nonzero(ids != K.NO_ID)
        yield pa.RecordBatch.from_arrays([pa.array(qid[row]), pa.array(ids[row, rank]), pa.array(d2[row, rank])], ["qid", "pid", "d2"])

    return run


def knn_brute(points: PointSet, queries: DataFrame, k: int = 5, max_radius: float | None = None, exclude_self: bool = False, block: int = 100_000, metric: str = "l2") -> DataFrame:
    """Exhaustive search: blocks of queries meet every partition of the points, k rows per query and task come back.

    Of points in one spot, which all have the same distances, only those with the smallest ids can answer and are met. There are
    as many partitions as keep all cores busy, as each of them sends k rows for every query, and the more points a task meets
    the fewer come near its queries' best so far.
    """
    spark = points.df.sparkSession
    ship(spark)
    coords, r2 = points.coords, float("inf") if max_radius is None else radius_bound(max_radius, metric)
    asked = every_query = queries.select("qid", *coords)
    if not exclude_self:  # queries from one spot have one answer: the least of them asks for all
        asked = asked.groupBy(*coords).agg(F.min("qid").alias("qid"))
    asked = written(asked, "asked")  # looked at for each block
    n, cores = asked.count(), spark.sparkContext.defaultParallelism
    blocks = max(1, -(-n // block))
    every = collapse_colocated(points, k + exclude_self).repartition(min(cores, max(2, -(-2 * cores // blocks))))
    found = None
    for b in range(blocks):
        own = asked if blocks == 1 else asked.where(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == b)
        rows = own.toPandas()  # at most about a block
        shared = spark.sparkContext.broadcast((rows["qid"].to_numpy(), rows[coords].to_numpy(dtype=float)))
        part = every.mapInArrow(local_brute(shared, points.dims, k, r2, exclude_self, metric), "qid long, pid long, d2 double")
        found = part if found is None else found.unionByName(part)
    best = merge_topk(found, k, metric).select("qid", "rank", "pid", "d2", "dist")
    if exclude_self:
        return best
    at = asked.withColumnRenamed("qid", "_asks").join(every_query, coords).select("qid", "_asks")
    return best.withColumnRenamed("qid", "_asks").join(at, "_asks").select("qid", "rank", "pid", "d2", "dist")


def _replicated(shared: list, dims: int, k: int, r2: float, exclude_self: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trees = [tree_at(part, row, dims) for one in shared for part in pa.ipc.open_stream(one.value).read_all().combine_chunks().to_batches() for row in range(part.num_rows)]
        for batch in batches:
            qid, q = batch.column("qid").to_numpy(), _matrix(batch, dims)
            away = np.stack([K.box_distance(q, t.lo[0], t.hi[0]) for t in trees], axis=1) if trees else np.zeros((len(q), 0))
            d2, ids, bound = np.full((len(q), k), np.inf), np.full((len(q), k), K.NO_ID), np.full(len(q), r2)
            home = away.argmin(axis=1) if trees else None
            for first in (True, False):  # the nearest box gives a radius, the others are asked within it
                for i, tree in enumerate(trees):
                    at = np.flatnonzero((home == i) if first else (home != i) & (away[:, i] <= bound))
                    if len(at):
                        found = K.search(tree, q[at], k, bound[at], qid[at] if exclude_self else None)
                        d2[at], ids[at] = K.top_k(np.concatenate([d2[at], found.d2], axis=1), np.concatenate([ids[at], found.ids], axis=1), k)
                        bound[at] = np.minimum(bound[at], d2[at, -1])
            row, rank = np.nonzero(ids != K.NO_ID)
            yield pa.RecordBatch.from_arrays([pa.array(qid[row]), pa.array((rank + 1).astype(np.int32)), pa.array(ids[row, rank]), pa.array(d2[row, rank]), pa.array(np.sqrt(d2[row, rank]))], ["qid", "rank", "pid", "d2", "dist"])

    return run


#: Points of a cell of the replicated tree: what passes through the driver at a time.
REPLICA_POINTS = 1 << 19


def knn_replicated(points: PointSet, queries: DataFrame, k: int = 5, max_radius: float | None = None, exclude_self: bool = False, policy: K.SplitPolicy = K.SplitPolicy(), bucket_size: int = 32) -> DataFrame:
    """The same tree in every worker: queries are dealt once and meet all points, for point sets of a checked size.

    The tree is built once, on the executors, and shipped cell by cell, so the driver never holds all points.
    """
    spark = points.df.sparkSession
    ship(spark)
    n = points.df.count()
    if n * 8 * (points.dims + 1) > BROADCAST_BYTES:
        raise ValueError(f"{n} points of {points.dims} dimensions are too many to replicate; use the partition tree")
    layout = build_layout(points, -(-n // REPLICA_POINTS), policy, bucket_size)
    names = ["pid", *points.coords, *(c for c in layout.packed.columns if c.startswith("node_"))]
    shared = [spark.sparkContext.broadcast(_stream(layout.packed.where(F.col("cell") == c).select(*names).toArrow())) for c in np.flatnonzero(layout.n).tolist()]
    r2 = float("inf") if max_radius is None else max_radius**2
    dealt = queries.select("qid", *points.coords).repartition(4 * spark.sparkContext.defaultParallelism)
    return dealt.mapInArrow(_replicated(shared, points.dims, k, r2, exclude_self), "qid long, rank int, pid long, d2 double, dist double")


def _stream(part: pa.Table) -> bytes:
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, part.schema) as to:
        to.write_table(part)
    return out.getvalue().to_pybytes()


def squared_distance(dims: int, a: str = "p", b: str = "q"):
    total = None
    for i in range(dims):
        gap = F.col(f"{a}.c{i}") - F.col(f"{b}.c{i}")
        total = gap * gap if total is None else total + gap * gap
    return total


def _distance_to(dims: int, p: Column) -> Column:
    """The same of a point (a struct) to the row's place."""
    total = None
    for i in range(dims):
        gap = p[f"c{i}"] - F.col(f"c{i}")
        total = gap * gap if total is None else total + gap * gap
    return total


#: Cells that every query may meet in the purely relational search; levels of a cell's tree it looks at, and levels apart they are at least.
RELATIONAL_CELLS, LOOKS, APART = 1024, 6, 4
_NODE_KEY = ["cell", "piece", "unit"]


def _box_distance(dims: int, b: Column, far: bool = False) -> Column:
    """Squared distance of the row's place to the nearest or farthest corner of a box (a struct); sums run as in squared_distance."""
    total = None
    for i in range(dims):
        q, lo, hi = F.col(f"c{i}"), b[f"l{i}"], b[f"h{i}"]
        gap = F.greatest(F.abs(q - lo), F.abs(q - hi)) if far else F.greatest(lo - q, F.lit(0.0), q - hi)
        total = gap * gap if total is None else total + gap * gap
    return total


def _units(layout: SpatialLayout, k: int, depths: list[int]) -> DataFrame:
    """(cell, piece, unit, n, box, points, up0 ..): the buckets with their points, of a spot only the k smallest ids.

    unit is where the bucket begins in its piece, up{j} where the node above it at that depth does: of the nodes there, and of
    the buckets that are less deep, the last one that begins no later.
    """
    coords = [f"c{i}" for i in range(layout.dims)]
    nodes = layout.packed.select("cell", "piece", F.inline(F.arrays_zip(*(F.col(f"node_{c}").alias(c) for c in ("left", "start", "depth")))))
    order, leaf = Window.partitionBy("cell", "piece").orderBy("start"), F.col("left") < 0
    up = [F.max(F.when((F.col("depth") == d) | (leaf & (F.col("depth") < d)), F.col("start"))).over(order).alias(f"up{j}") for j, d in enumerate(depths)]
    above = nodes.select("cell", "piece", "left", F.col("start").alias("unit"), *up).where(leaf).drop("left")
    spans = F.sort_array(F.filter(F.transform(F.arrays_zip("node_start", "node_end", "node_left"), lambda x: F.when(x["node_left"] < 0, F.struct(x["node_start"].alias("s"), x["node_end"].alias("e")))), lambda x: x.isNotNull()))
    unit = F.flatten(F.transform(spans, lambda x: F.array_repeat(x["s"], x["e"] - x["s"])))
    rows = layout.packed.select("cell", "piece", F.inline(F.arrays_zip("pid", *coords, unit.alias("unit"))))
    few = rows.withColumn("_r", F.row_number().over(Window.partitionBy(*coords).orderBy("pid"))).where(F.col("_r") <= k)
    box = [f(c).alias(f"{n}{i}") for i, c in enumerate(coords) for n, f in (("l", F.min), ("h", F.max))]
    return few.groupBy(*_NODE_KEY).agg(F.count(F.lit(1)).alias("n"), *box, F.collect_list(F.struct("pid", *coords)).alias("points")).join(above, _NODE_KEY)


def knn_relational(layout: SpatialLayout, queries: DataFrame, k: int = 5) -> DataFrame:
    """The same answer from joins and windows alone, down the boxes of the cells' trees, some levels at a time.

    Each query goes down to one near bucket, whose k-th distance bounds its radius, then to all boxes within that; only points
    within the radius are ranked. A join meets a box once for each query and brings the boxes under it. Queries meet all cells,
    so it is for layouts of few cells (RELATIONAL_CELLS); the tree search is for more.
    """
    if layout.cells > RELATIONAL_CELLS:
        raise ValueError(f"{layout.cells} cells: every query would meet each of them; use the tree search")
    dims, coords = layout.dims, [f"c{i}" for i in range(layout.dims)]
    sides, deep = [f"{n}{i}" for i in range(dims) for n in "lh"], layout.facts["tree_depth"]
    depths = list(range(0, deep, max(APART, -(-deep // LOOKS))))
    units = written(_units(layout, k, depths), "units")
    boxes, under = units.drop("points"), [units.select(*_NODE_KEY, "points")]
    for j in reversed(range(len(depths))):
        hull = [(F.min if c[0] == "l" else F.max)(c).alias(c) for c in sides]
        kids = boxes.withColumn("_kid", F.struct(*_NODE_KEY, "n", *sides)).withColumn("unit", F.col(f"up{j}"))
        made = written(kids.groupBy(*_NODE_KEY).agg(F.sum("n").alias("n"), *hull, *(F.min(f"up{i}").alias(f"up{i}") for i in range(j)), F.collect_list("_kid").alias("kids")), "boxes")
        boxes = made.drop("kids")
        under.append(made.select(*_NODE_KEY, "kids"))
    top = F.broadcast(boxes.agg(F.collect_list(F.struct(*_NODE_KEY, "n", *sides)).alias("kids")))

    asked = queries.select("qid", *coords).repartition(4 * queries.sparkSession.sparkContext.defaultParallelism)
    at = asked.withColumn("r2", F.lit(float("inf"))).crossJoin(top)
    for beneath in reversed(under):  # to the nearest box of those with k points, whose far corner bounds the radius too
        met = F.transform("kids", lambda b: F.struct((b["n"] < k).alias("lacks"), _box_distance(dims, b).alias("near"), b.alias("b")))
        b = F.col("_m.b")
        seen = at.select("qid", *coords, "r2", F.array_min(met).alias("_m")).withColumn("r2", F.when(F.col("_m.lacks"), F.col("r2")).otherwise(F.least("r2", _box_distance(dims, b, True))))
        at = seen.select("qid", *coords, "r2", *(b[c].alias(c) for c in _NODE_KEY)).join(beneath, _NODE_KEY)
    away = F.sort_array(F.transform("points", lambda p: _distance_to(dims, p)))
    bounded = written(at.select("qid", *coords, F.least("r2", F.get(away, F.lit(k - 1))).alias("r2")), "bounded")

    reach = bounded.crossJoin(top)
    for beneath in reversed(under):
        near = reach.select("qid", *coords, "r2", F.explode("kids").alias("b")).where(_box_distance(dims, F.col("b")) <= F.col("r2"))
        reach = near.select("qid", *coords, "r2", *(F.col("b")[c].alias(c) for c in _NODE_KEY)).join(beneath, _NODE_KEY)
    met = reach.select("qid", *coords, "r2", F.explode("points").alias("p")).select("qid", F.col("p.pid").alias("pid"), "r2", _distance_to(dims, F.col("p")).alias("d2"))
    return merge_topk(met.where(F.col("d2") <= F.col("r2")).drop("r2"), k).select("qid", "rank", "pid", "d2", "dist")


def radius_search(points: PointSet, queries: DataFrame, radius: float) -> DataFrame:
    """All (qid, pid, d2) within the radius: an equi-join on grid cells of that width in the first three dimensions."""
    dims = min(points.dims, 3)
    grid = [F.floor(F.col(f"c{i}") / radius).alias(f"g{i}") for i in range(dims)]
    p = points.positions().select("*", *grid)
    q = queries.select("qid", *points.coords)
    for i in range(dims):
        q = q.withColumn(f"g{i}", F.explode(F.array(*(F.floor(F.col(f"c{i}") / radius) + s for s in (-1, 0, 1)))))
    same = [F.col(f"p.g{i}") == F.col(f"q.g{i}") for i in range(dims)]
    d2 = squared_distance(points.dims)
    return p.alias("p").join(q.alias("q"), same).where(d2 <= F.lit(float(radius) ** 2)).select("qid", "pid", d2.alias("d2"))
