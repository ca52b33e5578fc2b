"""Points in their cells: the one exchange of the build, local trees packed beside their points, boxes, and the stored form.

A cell is stored as one row: its points in bucket order and the arrays of its tree, both made once, when the layout is
built. The rows lie bucketed by cell, so a search exchanges queries and reads cells where they are. A cell too large for a
task is first split further by data-parallel passes; what no plane can split, points in one spot, is dealt into pieces by id,
each a row with a tree of its own under the same cell.
"""

from __future__ import annotations

import json
import uuid
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant import kernel as K
from orthant.functions.shipping import ship
from orthant.plans.global_tree import GlobalTree, build_global_tree, split_heavy
from orthant.points import PointSet
from orthant.sources.tables import fresh_path

#: Points of a cell, or of a piece of it, that one task builds and searches at most.
PIECE_POINTS = 4_000_000
_NODE = {"dim": pa.int32(), "left": pa.int32(), "right": pa.int32(), "start": pa.int32(), "end": pa.int32(), "depth": pa.int32(), "split": pa.float64(), "lo": pa.float64(), "hi": pa.float64()}
_SQL_TYPE = {pa.int32(): "int", pa.int64(): "bigint", pa.float64(): "double"}
FACTS = ("n", "buckets", "largest", "tree_depth")


def packed_schema(dims: int) -> str:
    """cell, piece; facts; box; points by bucket; nodes of the tree (boxes of nodes flattened)."""
    arrays = {"pid": "bigint"} | {f"c{i}": "double" for i in range(dims)} | {f"node_{k}": _SQL_TYPE[t] for k, t in _NODE.items()}
    return "cell int, piece int, " + ", ".join(f"{f} int" for f in FACTS) + ", box_lo array<double>, box_hi array<double>, " + ", ".join(f"{k} array<{t}>" for k, t in arrays.items())


def array_at(batch: pa.RecordBatch | pa.Table, name: str, row: int) -> np.ndarray:
    """One row's array of a column, without a copy where Arrow allows."""
    return batch.column(name).slice(row, 1).flatten().to_numpy(zero_copy_only=False)


def tree_at(batch: pa.RecordBatch, row: int, dims: int) -> K.Tree:
    """The stored tree of one row."""
    node = {k: array_at(batch, f"node_{k}", row) for k in _NODE}
    points = np.stack([array_at(batch, f"c{i}", row) for i in range(dims)], axis=1)
    return K.Tree(points, array_at(batch, "pid", row), node["dim"], node["split"], node["left"], node["right"], node["start"], node["end"], node["lo"].reshape(-1, dims), node["hi"].reshape(-1, dims), node["depth"])


@dataclass
class SpatialLayout:
    """packed: a row for each piece of a cell, bucketed by cell; boxes and facts of the cells are on the driver."""

    packed: DataFrame
    tree: GlobalTree
    n: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    facts: dict[str, int]  # buckets, largest bucket, depth of the local trees
    policy: K.SplitPolicy = K.SplitPolicy()
    bucket_size: int = 32
    version: int = 0
    parts: int = 1  # buckets of the stored rows
    path: str = ""
    whole: list[int] | None = None  # of each cell the one that was asked for, where those too large for a task were split further

    @property
    def dims(self) -> int:
        return self.tree.dims

    @property
    def cells(self) -> int:
        return len(self.n)

    @property
    def points(self) -> DataFrame:
        """pid, coordinates, cell: the stored points, one row each."""
        names = ["pid", *(f"c{i}" for i in range(self.dims))]
        return self.packed.select("cell", F.inline(F.arrays_zip(*names))).select(*names, "cell")

    def cells_df(self, spark: SparkSession) -> DataFrame:
        lo, hi = self.tree.regions()
        rows = [(i, lo[i].tolist(), hi[i].tolist(), self.lo[i].tolist(), self.hi[i].tolist(), int(self.n[i])) for i in range(self.cells)]
        return spark.createDataFrame(rows, "cell_id int, lo array<double>, hi array<double>, mbr_lo array<double>, mbr_hi array<double>, n long")

    def asked_cell(self) -> Column:
        """Of a row's cell the one that was asked for."""
        return F.col("cell") if self.whole is None else F.get(F.lit(self.whole), F.col("cell"))

    def balance(self) -> float:
        """Points of the largest cell over the mean."""
        return float(self.n.max() / self.n.mean()) if self.n.sum() else 1.0

    def buckets(self) -> DataFrame:
        """cell, piece, bucket, n, depth, box of every bucket, read from the stored trees."""
        ship(self.packed.sparkSession)
        nodes = self.packed.select("cell", "piece", *(f"node_{k}" for k in ("left", "start", "end", "depth", "lo", "hi")))
        return nodes.mapInArrow(_buckets(self.dims), "cell int, piece int, bucket int, n int, depth int, mbr_lo array<double>, mbr_hi array<double>")

    # -- storage --

    def save(self, path: str) -> None:
        """The packed rows, bucketed by cell, tree and boxes beside them, and a manifest last."""
        spark = self.packed.sparkSession
        at = f"{path}/v{self.version}"
        store(self.packed.repartition(self.parts, "cell"), f"{at}/packed", self.parts)
        self.tree.to_df(spark).coalesce(1).write.parquet(f"{at}/tree")
        self.cells_df(spark).coalesce(1).write.parquet(f"{at}/cells")
        facts = json.dumps({"version": self.version, "dims": self.dims, "bucket_size": self.bucket_size, "policy": self.policy.__dict__, "parts": self.parts, "facts": self.facts})
        spark.createDataFrame([(self.version, facts)], "version int, facts string").coalesce(1).write.mode("append").parquet(f"{path}/manifest")

    @classmethod
    def load(cls, spark: SparkSession, path: str, version: int | None = None) -> SpatialLayout:
        rows = spark.read.parquet(f"{path}/manifest").collect()
        facts = json.loads(max((r for r in rows if version in (None, r["version"])), key=lambda r: r["version"])["facts"])
        at, dims = f"{path}/v{facts['version']}", facts["dims"]
        tree = GlobalTree.from_df(spark.read.parquet(f"{at}/tree"), dims)
        cells = sorted(spark.read.parquet(f"{at}/cells").collect(), key=lambda r: r["cell_id"])
        box = lambda c: np.array([r[c] for r in cells], dtype=float)
        name = _name()
        spark.sql(f"CREATE TABLE {name} ({packed_schema(dims)}) USING parquet CLUSTERED BY (cell) INTO {facts['parts']} BUCKETS LOCATION '{at}/packed'")
        return cls(spark.table(name), tree, np.array([r["n"] for r in cells]), box("mbr_lo"), box("mbr_hi"), facts["facts"], K.SplitPolicy(**facts["policy"]), facts["bucket_size"], facts["version"], facts["parts"], f"{at}/packed")


def _name() -> str:
    return f"orthant_{uuid.uuid4().hex}"


def store(packed: DataFrame, path: str, parts: int) -> DataFrame:
    """Rows that lie hashed by cell into so many partitions, written as a table of as many buckets in the given folder."""
    name = _name()
    packed.write.bucketBy(parts, "cell").option("path", path).saveAsTable(name)
    return packed.sparkSession.table(name)


def _pack(dims: int, bucket_size: int, policy: K.SplitPolicy):
    def run(part: pa.Table) -> pa.Table:
        x = np.stack([part.column(f"c{i}").to_numpy() for i in range(dims)], axis=1)
        # in order of ids, so that the tree doesn't depend on the order of arrival
        by = np.argsort(part.column("pid").to_numpy(), kind="stable")
        tree = K.build(x[by], part.column("pid").to_numpy()[by], bucket_size or max(1, len(x)), policy)
        leaf = tree.leaves
        whole = lambda v: pa.array([v], pa.int32())
        own = {"cell": whole(part.column("cell")[0].as_py()), "piece": whole(part.column("piece")[0].as_py()), "n": whole(len(x)), "buckets": whole(len(leaf)), "largest": whole(int((tree.end - tree.start)[leaf].max())), "tree_depth": whole(int(tree.depth.max()))}
        doubles = lambda a: _one_list(a, pa.float64())
        own |= {"box_lo": doubles(tree.lo[0]), "box_hi": doubles(tree.hi[0]), "pid": _one_list(tree.ids, pa.int64())} | {f"c{i}": doubles(tree.points[:, i]) for i in range(dims)}
        own |= {f"node_{k}": _one_list(np.asarray(getattr(tree, k)).ravel(), t) for k, t in _NODE.items()}
        return pa.table(own)

    return run


def _one_list(values: np.ndarray, kind: pa.DataType) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), pa.array(values, kind))


def _buckets(dims: int):
    def run(batches):
        for batch in batches:
            for row in range(batch.num_rows):
                node = {k: array_at(batch, f"node_{k}", row) for k in ("left", "start", "end", "depth", "lo", "hi")}
                leaf = np.flatnonzero(node["left"] < 0)
                leaf = leaf[np.argsort(node["start"][leaf], kind="stable")]
                same = lambda c: pa.array(np.full(len(leaf), batch.column(c)[row].as_py()), pa.int32())  # noqa: B023, E731
                yield pa.RecordBatch.from_arrays(
                    [same("cell"), same("piece"), pa.array(np.arange(len(leaf)), pa.int32()), pa.array((node["end"] - node["start"])[leaf], pa.int32()), pa.array(node["depth"][leaf], pa.int32()),
                     *(pa.array(node[k].reshape(-1, dims)[leaf].tolist(), pa.list_(pa.float64())) for k in ("lo", "hi"))],
                    ["cell", "piece", "bucket", "n", "depth", "mbr_lo", "mbr_hi"],
                )

    return run


def build_layout(points: PointSet, cells: int, policy: K.SplitPolicy = K.SplitPolicy(), bucket_size: int = 32, mode: str = "level", seed: int = 0, piece_points: int = PIECE_POINTS) -> SpatialLayout:
    """Tree, routing, one exchange of the points into packed cells, and the boxes of the cells as facts of what was written.

    Cells of more than piece_points points are split further before the exchange, or dealt into pieces.
    """
    return place(points, build_global_tree(points, cells, policy, mode, seed), policy, bucket_size, refine=True, piece_points=piece_points)


def place(points: PointSet, tree: GlobalTree, policy: K.SplitPolicy = K.SplitPolicy(), bucket_size: int = 32, version: int = 0, refine: bool = False, piece_points: int = PIECE_POINTS) -> SpatialLayout:
    """refine: cells too large for a task are split further before the exchange."""
    total = points.df.count()
    counts: dict[int, int] = {}
    asked = tree.leaves()
    if total > piece_points:  # or else no cell can be too large
        if refine:
            tree = split_heavy(points, tree, policy, piece_points)
        counts = {r["cell"]: -(-r["count"] // piece_points) for r in tree.routed(points.positions()).groupBy("cell").count().where(F.col("count") > piece_points).collect()}  # at most total / piece_points rows
    layout = pack_cells(tree.routed(points.positions()), tree, policy, bucket_size, version, counts)
    if layout.cells > len(asked):
        layout.whole = tree.within(asked)
    return layout


def in_pieces(routed: DataFrame, large: dict[int, int]) -> DataFrame:
    """routed with piece: ids of large cells are dealt by their hash into so many pieces."""
    if not large:
        return routed.withColumn("piece", F.lit(0))
    need = routed.sparkSession.createDataFrame(list(large.items()), "cell int, _pieces int")
    return routed.join(F.broadcast(need), "cell", "left").withColumn("piece", F.coalesce(F.pmod(F.xxhash64("pid"), "_pieces"), F.lit(0)).cast("int")).drop("_pieces")


def pack_cells(routed: DataFrame, tree: GlobalTree, policy: K.SplitPolicy, bucket_size: int, version: int = 0, large: dict[int, int] | None = None) -> SpatialLayout:
    """Exchange rows (pid, coordinates, cell) by cell, build and pack every cell's tree, write them, and read their facts."""
    spark, dims = routed.sparkSession, tree.dims
    ship(spark)
    parts = max(1, min(max(tree.cells, 1), int(spark.conf.get("spark.sql.shuffle.partitions"))))
    path = fresh_path(spark, "layout")
    # pieces of one cell go to tasks of their own before they come to lie in the cell's bucket
    dealt = in_pieces(routed, large or {}).repartition(parts, *(["cell", "piece"] if large else ["cell"]))
    made = dealt.groupBy("cell", "piece").applyInArrow(_pack(dims, bucket_size, policy), packed_schema(dims))
    packed = store(made.repartition(parts, "cell") if large else made, path, parts)
    found = packed.select("cell", *FACTS, "box_lo", "box_hi").collect()  # a row for each piece
    n, lo, hi = np.zeros(tree.cells, dtype=np.int64), np.full((tree.cells, dims), np.inf), np.full((tree.cells, dims), -np.inf)
    for r in found:
        c = r["cell"]
        n[c] += r["n"]
        lo[c], hi[c] = np.minimum(lo[c], r["box_lo"]), np.maximum(hi[c], r["box_hi"])
    facts = {"buckets": sum(r["buckets"] for r in found), "largest": max((r["largest"] for r in found), default=0), "tree_depth": max((r["tree_depth"] for r in found), default=0)}
    return SpatialLayout(packed, tree, n, lo, hi, facts, policy, bucket_size, version, parts, path)


def independent_layout(points: PointSet, parts: int, policy: K.SplitPolicy = K.SplitPolicy(), bucket_size: int = 32) -> SpatialLayout:
    """The other strategy: points stay where their ids put them, each part has its own tree, and no region says who owns a query."""
    tree = GlobalTree(points.dims)
    tree.add(0, parts)
    for _ in range(parts - 1):  # a chain whose cells all span the space: only the count of cells is used
        tree.cut(max(tree.leaves()), 0, float("-inf"))
    dealt = points.positions().withColumn("cell", F.pmod("pid", F.lit(parts)).cast("int"))
    return pack_cells(dealt, tree, policy, bucket_size)


def pack(layout: SpatialLayout) -> DataFrame:
    """Points in bucket order, cell by cell: rows of a bucket are contiguous. Read from the packed rows: nothing is rebuilt."""
    names = ["pid", *(f"c{i}" for i in range(layout.dims))]
    starts = F.filter(F.transform(F.arrays_zip(F.col("node_left").alias("l"), F.col("node_start").alias("s")), lambda x: F.when(x["l"] < 0, x["s"])), lambda s: s.isNotNull())
    rows = layout.packed.select("cell", "piece", F.array_sort(starts).alias("_starts"), F.posexplode(F.arrays_zip(*names)).alias("_at", "_p"))
    # the bucket of a place: how many buckets begin at or before it
    return rows.select("_p.*", "cell", "piece", (F.size(F.filter("_starts", lambda s: s <= F.col("_at"))) - 1).alias("bucket"))


def collapse_colocated(points: PointSet, k: int, with_copies: bool = False) -> DataFrame:
    """Of the points in one spot the k with the smallest ids: enough for any k-nearest answer.

    The rank limit works inside the map tasks, so a spot that holds a third of all points sends k rows a task. with_copies adds
    the multiplicity of the spot, from a map-side combined count.
    """
    spot = Window.partitionBy(*points.coords).orderBy("pid")
    few = points.positions().withColumn("_r", F.row_number().over(spot)).where(F.col("_r") <= k).drop("_r")
    if not with_copies:
        return few
    return few.join(points.positions().groupBy(*points.coords).agg(F.count(F.lit(1)).alias("copies")), points.coords)
