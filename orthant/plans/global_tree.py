"""The partition tree over all points: built level by level, kept on the driver, and evaluated where the rows are.

Points aren't moved while the tree grows. A row's node is a function of the tree so far, so a level costs one scan with a
map-side histogram per open node, and the only exchange of points comes when the tree is final.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant import kernel as K
from orthant.functions.shipping import ship
from orthant.points import PointSet, hash32

#: Most cells that are routed by a nested CASE.
CASE_CELLS = 64
#: Histograms of all tasks together that come to the driver as they are; larger ones are added up on the way.
DIRECT_BYTES = 32 << 20
#: Cells that are made by full histograms, from samples on the driver; more of them grow inside these, on the executors.
GROUPS = 1024


@dataclass
class GlobalTree:
    """Inner nodes and leaves as arrays; leaf i of the traversal from left to right is cell i."""

    dims: int
    dim: list[int] = field(default_factory=list)
    split: list[float] = field(default_factory=list)
    left: list[int] = field(default_factory=list)
    right: list[int] = field(default_factory=list)
    level: list[int] = field(default_factory=list)
    want: list[int] = field(default_factory=list)  # cells below the node

    def add(self, level: int, want: int) -> int:
        for a, v in ((self.dim, -1), (self.split, 0.0), (self.left, -1), (self.right, -1), (self.level, level), (self.want, want)):
            a.append(v)
        return len(self.dim) - 1

    def cut(self, node: int, dim: int, value: float) -> tuple[int, int]:
        more = -(-self.want[node] // 2)
        a, b = self.add(self.level[node] + 1, more), self.add(self.level[node] + 1, self.want[node] - more)
        self.dim[node], self.split[node], self.left[node], self.right[node] = dim, value, a, b
        return a, b

    def arrays(self) -> tuple[np.ndarray, ...]:
        return np.array(self.dim), np.array(self.split), np.array(self.left), np.array(self.right)

    def leaves(self) -> list[int]:
        out, stack = [], [0]
        while stack:
            n = stack.pop()
            if self.left[n] < 0:
                out.append(n)
            else:
                stack += [self.right[n], self.left[n]]
        return out

    @property
    def cells(self) -> int:
        return len(self.leaves())

    @property
    def depth(self) -> int:
        return max(self.level)

    def cell_of_node(self) -> np.ndarray:
        out = np.full(len(self.dim), -1)
        for i, n in enumerate(self.leaves()):
            out[n] = i
        return out

    def within(self, nodes: list[int]) -> list[int]:
        """Of each cell the place in the list of the node that it lies under."""
        under = np.full(len(self.dim), -1)
        under[nodes] = np.arange(len(nodes))
        for n in range(len(self.dim)):  # parents come before their children
            for child in (self.left[n], self.right[n]):
                if child >= 0 and under[child] < 0:
                    under[child] = under[n]
        return under[self.leaves()].tolist()

    def regions(self) -> tuple[np.ndarray, np.ndarray]:
        """Half-open boxes of all cells; open at the outside."""
        lo, hi = np.full((len(self.dim), self.dims), -np.inf), np.full((len(self.dim), self.dims), np.inf)
        for n in range(len(self.dim)):  # parents come before their children
            for child in (self.left[n], self.right[n]):
                if child >= 0:
                    lo[child], hi[child] = lo[n], hi[n]
            if self.left[n] >= 0:
                hi[self.left[n], self.dim[n]] = self.split[n]
                lo[self.right[n], self.dim[n]] = self.split[n]
        own = self.leaves()
        return lo[own], hi[own]

    def route_column(self, coords: list[str] | None = None) -> Column:
        """The cell of a row as a nested CASE: code grows with the cells, work with the depth."""
        coords = coords or [f"c{i}" for i in range(self.dims)]
        cell = self.cell_of_node()

        def go(n: int) -> Column:
            if self.left[n] < 0:
                return F.lit(int(cell[n]))
            return F.when(F.col(coords[self.dim[n]]) < F.lit(float(self.split[n])), go(self.left[n])).otherwise(go(self.right[n]))

        return go(0)

    def route_reduce(self, coords: list[str] | None = None) -> Column:
        """The same as a fold over literal arrays: a plan of constant size."""
        coords = coords or [f"c{i}" for i in range(self.dims)]
        dim, split, left, right = (F.array(*(F.lit(x.item()) for x in a)) for a in self.arrays())
        cell, point = F.array(*(F.lit(int(x)) for x in self.cell_of_node())), F.array(*(F.col(c) for c in coords))
        at = lambda a, n: F.get(a, n)
        step = lambda n, _: F.when(at(left, n) < 0, n).when(at(point, at(dim, n)) < at(split, n), at(left, n)).otherwise(at(right, n))
        return at(cell, F.reduce(F.sequence(F.lit(1), F.lit(max(1, self.depth))), F.lit(0).cast("bigint"), step).cast("int"))

    def routed(self, df: DataFrame) -> DataFrame:
        """df with cell INT: in generated code for few cells, by a shipped tree in Arrow batches for many."""
        if self.cells <= CASE_CELLS:
            return df.withColumn("cell", self.route_column())
        ship(df.sparkSession)
        shared, dims = df.sparkSession.sparkContext.broadcast((self.arrays(), self.cell_of_node())), self.dims

        @F.arrow_udf("int")
        def cell(*columns: pa.Array) -> pa.Array:
            arrays, of = shared.value
            return pa.array(of[descend(arrays, np.stack([c.to_numpy(zero_copy_only=False) for c in columns], axis=1))].astype(np.int32))

        return df.withColumn("cell", cell(*(F.col(f"c{i}") for i in range(dims))))

    def to_df(self, spark: SparkSession) -> DataFrame:
        cell = self.cell_of_node()
        rows = [(n, self.level[n], self.dim[n], float(self.split[n]), self.left[n], self.right[n], self.left[n] < 0, int(cell[n]), self.want[n]) for n in range(len(self.dim))]
        return spark.createDataFrame(rows, "node_id long, level int, dim int, split double, left long, right long, is_leaf boolean, cell_id int, cells int")

    @classmethod
    def from_df(cls, df: DataFrame, dims: int) -> GlobalTree:
        rows = sorted(df.collect(), key=lambda r: r["node_id"])
        return cls(dims, *([r[c] for r in rows] for c in ("dim", "split", "left", "right", "level", "cells")))


def descend(arrays: tuple[np.ndarray, ...], x: np.ndarray) -> np.ndarray:
    """The leaf of each point."""
    dim, split, left, right = arrays
    node, at = np.zeros(len(x), dtype=np.int64), np.arange(len(x))
    while len(at):
        at = at[left[node[at]] >= 0]
        n = node[at]
        node[at] = np.where(x[at, dim[n]] < split[n], left[n], right[n])
    return node


def _histograms(shared, dims: int):
    """(node, bin, n) of the rows' values in their open node's edges, folded in the task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        arrays, open_nodes, two_level, stride = shared.value
        counts = {n: np.zeros(len(edges) + 1, dtype=np.int64) for n, (_, edges) in open_nodes.items()}
        for batch in batches:
            x = np.stack([batch.column(i).to_numpy(zero_copy_only=False) for i in range(dims)], axis=1)
            node = descend(arrays, x)
            by = np.argsort(node, kind="stable")  # each open node's rows in a run
            first = np.flatnonzero(np.r_[True, node[by][1:] != node[by][:-1]]) if len(by) else by
            for s, e in zip(first, np.r_[first[1:], len(by)], strict=True):
                n = int(node[by[s]])
                if n in open_nodes:
                    dim, edges = open_nodes[n]
                    counts[n] += K.histogram(x[by[s:e], dim], edges, two_level, stride)
        for n, c in counts.items():
            at = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), n)), pa.array(at), pa.array(c[at])], ["node", "bin", "n"])

    return run


def sample(points: PointSet, size: int, seed: int = 0) -> np.ndarray:
    """The points whose hashed ids are smallest, in that order: the same whatever the partitions are."""
    top = points.positions().withColumn("_h", hash32(F.col("pid") + seed)).orderBy("_h", "pid").limit(size)
    return top.select(*points.coords).toPandas().to_numpy(dtype=float).reshape(-1, points.dims)


def best_cut(x: np.ndarray, policy: K.SplitPolicy, level: int, share: float, order: np.ndarray | None = None) -> tuple[int, float, np.ndarray] | None:
    """(dimension, value, edges) of a node from its sample: the first dimension that splits it evenly enough, or else the evenest."""
    best = None
    for dim in K.dimension_order(x, policy, level) if order is None else order:
        v = x[:, dim]
        edges, n_of = np.unique(v, return_counts=True)
        if policy.value_rule in ("midrange", "first100"):
            value = K.split_value(v, policy)
            if value is not None:
                return int(dim), float(value), edges
            continue
        found = K.edge_nearest(edges, np.concatenate([[0], n_of]), share)
        if found is None:
            continue
        off = abs(found[1] - share)
        if best is None or off < best[0]:
            best = (off, int(dim), found[0], edges)
        if off <= 0.5 - policy.min_balance:
            break
    return best and best[1:]


def _share(tree: GlobalTree, node: int) -> float:
    return -(-tree.want[node] // 2) / tree.want[node]


def grow_from_sample(x: np.ndarray, cells: int, policy: K.SplitPolicy) -> GlobalTree:
    """A tree whose dimensions and values all come from these points."""
    tree = GlobalTree(x.shape[1])
    stack = [(tree.add(0, max(1, cells)), x)]
    while stack:
        node, x = stack.pop()
        if tree.want[node] < 2 or len(x) < 2 or not (found := best_cut(x, policy, tree.level[node], _share(tree, node))):
            continue
        left = x[:, found[0]] < found[1]
        a, b = tree.cut(node, *found[:2])
        stack += [(a, x[left]), (b, x[~left])]
    return tree


def build_global_tree(points: PointSet, cells: int, policy: K.SplitPolicy = K.SplitPolicy(), mode: str = "level", seed: int = 0) -> GlobalTree:
    """Halve the space until there are so many cells (any number; fewer where points coincide).

    mode 'level': every value comes from a histogram of all points between sampled edges, or from whatever the policy says; of
    more than GROUPS cells that holds for the first GROUPS, and inside each of those the tree grows on the executors, from a
    sample of its own, so that every cell has its sample_per_part points in a sample however many cells there are;
    mode 'sample': dimensions and values come from a sample alone, for few passes over very many points; then all points are
    counted once, and only cells that the sample made too large are split again.
    """
    ship(points.df.sparkSession)
    if cells > GROUPS:
        return _in_groups(points, cells, policy, seed)
    tree = GlobalTree(points.dims)
    tree.add(0, max(1, cells))
    if cells <= 1:
        return tree
    drawn = sample(points, policy.sample_per_part * cells, seed)
    if not len(drawn):
        return tree
    if mode == "sample":
        return repaired(points, grow_from_sample(drawn, cells, policy), cells, policy)
    return _grow(points, tree, {0: drawn}, policy)


#: A cell of a tree from a sample is split again beyond so many times its due.
OVERWEIGHT = 2.0


def repaired(points: PointSet, tree: GlobalTree, cells: int, policy: K.SplitPolicy) -> GlobalTree:
    """The tree after one count of all points; cells beyond OVERWEIGHT times the mean are split further."""
    total = points.df.count()
    return split_heavy(points, tree, policy, max(1, int(OVERWEIGHT * total / cells)))


def split_heavy(points: PointSet, tree: GlobalTree, policy: K.SplitPolicy, limit: int, seed: int = 0) -> GlobalTree:
    """The tree with cells of more than limit points grown on by passes over all points, as far as planes can split them.

    What is to become more than GROUPS cells becomes about so many by passes; their insides grow on the executors.
    """
    counts = _heavy(points, tree, limit)
    if sum(-(-n // limit) for n in counts.values()) > GROUPS:
        coarse = max(limit, -(-sum(counts.values()) // GROUPS))
        tree = _split_by_passes(points, tree, policy, {c: n for c, n in counts.items() if n > coarse}, coarse, seed)
        return _grafted(points, tree, {c: -(-n // limit) for c, n in _heavy(points, tree, limit).items()}, policy, seed)
    return _split_by_passes(points, tree, policy, counts, limit, seed)


def _heavy(points: PointSet, tree: GlobalTree, limit: int) -> dict[int, int]:
    """Points of the cells of more than limit."""
    return {r["cell"]: r["count"] for r in tree.routed(points.positions()).groupBy("cell").count().where(F.col("count") > limit).collect()}


def _split_by_passes(points: PointSet, tree: GlobalTree, policy: K.SplitPolicy, counts: dict[int, int], limit: int, seed: int) -> GlobalTree:
    if not counts:
        return tree
    leaves, want = tree.leaves(), {}
    for c, n in counts.items():
        want[leaves[c]] = -(-n // limit)
    # samples of the heavy cells only, each of the size that its parts are due
    size = max(want.values()) * policy.sample_per_part
    inside = tree.routed(points.positions()).where(F.col("cell").isin(list(counts))).withColumn("_h", hash32(F.col("pid") + seed))
    drawn = inside.withColumn("_r", F.row_number().over(Window.partitionBy("cell").orderBy("_h", "pid"))).where(F.col("_r") <= size)
    rows = drawn.orderBy("cell", "_r").select("cell", *points.coords).toPandas()
    members = {}
    for c, part in rows.groupby("cell"):
        tree.want[leaves[c]] = want[leaves[c]]
        members[leaves[c]] = part[points.coords].to_numpy(dtype=float).reshape(-1, points.dims)
    for n in range(len(tree.want) - 1, -1, -1):
        if tree.left[n] >= 0:
            tree.want[n] = tree.want[tree.left[n]] + tree.want[tree.right[n]]
    return _grow(points, tree, members, policy)


def _grow(points: PointSet, tree: GlobalTree, members: dict[int, np.ndarray], policy: K.SplitPolicy) -> GlobalTree:
    """Split open nodes, given a sample of each, level by level: one pass over all points decides all values of a level."""
    while members:
        ready: dict[int, tuple[int, float]] = {}
        edges_of: dict[int, tuple[int, np.ndarray]] = {}
        full = _full_stats(points, tree, members, policy)
        for n, x in members.items():
            order, own = _dimensions(x, full.get(n), policy, tree.level[n]), full.get(n)
            if policy.value_rule == "hist":
                if found := best_cut(x, policy, tree.level[n], _share(tree, n), order):
                    edges_of[n] = (found[0], found[2])
                continue
            for dim in order:
                if policy.value_rule in ("exact", "sketch"):
                    value = own["median"][dim] if own["min"][dim] < own["median"][dim] else None
                elif policy.value_rule == "midrange":
                    value = K.split_value(np.array([own["min"][dim], own["max"][dim]]), policy)
                else:
                    value = K.split_value(x[:, dim], policy)
                if value is not None:
                    ready[n] = (int(dim), float(value))
                    break
        if edges_of:
            ready |= _by_histogram(points, tree, edges_of, policy)
        after = {}
        for n, (dim, value) in ready.items():
            x = members[n]
            side = x[:, dim] < value
            for child, own in zip(tree.cut(n, dim, value), (x[side], x[~side]), strict=True):
                if tree.want[child] > 1 and len(own) > 1:
                    after[child] = own
        members = after
    return tree


_NODES = "cell int, node int, level int, want int, dim int, split double, left int, right int"


def _subtree(want: dict[int, int], dims: int, policy: K.SplitPolicy):
    def run(part: pa.Table) -> pa.Table:
        x = np.stack([part.column(f"c{i}").to_numpy() for i in range(dims)], axis=1)
        # in hashed order, as the rules expect a sample
        x = x[np.lexsort((part.column("pid").to_numpy(), part.column("_h").to_numpy()))]
        cell = part.column("cell")[0].as_py()
        t = grow_from_sample(x, want[cell], policy)
        n = len(t.dim)
        whole = lambda a: pa.array(a, pa.int32())
        return pa.table([whole([cell] * n), whole(range(n)), whole(t.level), whole(t.want), whole(t.dim), pa.array(t.split, pa.float64()), whole(t.left), whole(t.right)], names=["cell", "node", "level", "want", "dim", "split", "left", "right"])

    return run


def _in_groups(points: PointSet, cells: int, policy: K.SplitPolicy, seed: int) -> GlobalTree:
    """First GROUPS cells by full histograms; their insides in parallel, each from its own sample; the driver grafts nodes only."""
    tree = build_global_tree(points, GROUPS, policy, "level", seed)
    leaves = tree.leaves()
    each, more = divmod(cells, len(leaves))
    want = {i: each + (i < more) for i in range(len(leaves))}
    for n in range(len(tree.want)):
        tree.want[n] = 0
    return _grafted(points, tree, want, policy, seed)


def _grafted(points: PointSet, tree: GlobalTree, want: dict[int, int], policy: K.SplitPolicy, seed: int) -> GlobalTree:
    """The tree with so many cells inside each of these cells, as trees from samples made on the executors have them."""
    if not want:
        return tree
    leaves, size = tree.leaves(), policy.sample_per_part * max(want.values())
    routed = tree.routed(points.positions()).withColumn("_h", hash32(F.col("pid") + seed))
    if len(want) < len(leaves):
        routed = routed.where(F.col("cell").isin(list(want)))
    drawn = routed.withColumn("_r", F.row_number().over(Window.partitionBy("cell").orderBy("_h", "pid"))).where(F.col("_r") <= size).drop("_r")
    rows = drawn.groupBy("cell").applyInArrow(_subtree(want, points.dims, policy), _NODES).toArrow().to_pylist()  # two rows for each cell
    by: dict[int, list] = {}
    for r in rows:
        by.setdefault(r["cell"], []).append(r)
    for i, n in want.items():
        at = {0: leaves[i]}
        tree.want[leaves[i]] = n
        for r in sorted(by.get(i, []), key=lambda r: r["node"]):
            if r["left"] >= 0:
                at[r["left"]], at[r["right"]] = tree.cut(at[r["node"]], r["dim"], r["split"])
    for n in range(len(tree.want) - 1, -1, -1):
        if tree.left[n] >= 0:
            tree.want[n] = tree.want[tree.left[n]] + tree.want[tree.right[n]]
    return tree


def _dimensions(x: np.ndarray, full: dict | None, policy: K.SplitPolicy, level: int) -> np.ndarray:
    if full and policy.dim_rule in ("variance_full", "range"):
        extent = full["max"] - full["min"]
        order = np.argsort(-(full["var"] if policy.dim_rule == "variance_full" else extent), kind="stable")
        return order[extent[order] > 0]
    return K.dimension_order(x, policy, level)


def _full_stats(points: PointSet, tree: GlobalTree, members: dict, policy: K.SplitPolicy) -> dict[int, dict]:
    """Aggregates of all points by open node, where the policy needs them: one job a level."""
    if policy.dim_rule not in ("variance_full", "range") and policy.value_rule not in ("exact", "midrange", "sketch"):
        return {}
    own = tree.cell_of_node()
    nodes = {int(own[n]): n for n in members}
    aggs = []
    for c in points.coords:
        aggs += [F.min(c).alias(f"min_{c}"), F.max(c).alias(f"max_{c}"), F.var_pop(c).alias(f"var_{c}")]
        if policy.value_rule == "exact":
            aggs.append(F.expr(f"percentile_disc(0.5) WITHIN GROUP (ORDER BY {c})").alias(f"median_{c}"))
        elif policy.value_rule == "sketch":
            aggs.append(F.percentile_approx(c, 0.5, 10_000).alias(f"median_{c}"))
    rows = tree.routed(points.positions()).where(F.col("cell").isin(*nodes)).groupBy("cell").agg(*aggs).collect()
    kinds = ("min", "max", "var", *(("median",) if policy.value_rule in ("exact", "sketch") else ()))
    return {nodes[r["cell"]]: {k: np.array([r[f"{k}_{c}"] for c in points.coords]) for k in kinds} for r in rows}


def _by_histogram(points: PointSet, tree: GlobalTree, edges_of: dict, policy: K.SplitPolicy) -> dict[int, tuple[int, float]]:
    spark, read = points.df.sparkSession, points.positions().drop("pid")
    shared = spark.sparkContext.broadcast((tree.arrays(), edges_of, policy.two_level, policy.stride))
    counted = read.mapInArrow(_histograms(shared, points.dims), "node long, bin long, n long")
    if read.rdd.getNumPartitions() * 24 * sum(len(edges) + 1 for _, edges in edges_of.values()) > DIRECT_BYTES:
        counted = counted.groupBy("node", "bin").agg(F.sum("n").alias("n"))
    rows = counted.toArrow()  # open nodes times their sampled edges
    node, bins, n = (rows.column(c).to_numpy() for c in ("node", "bin", "n"))
    by = np.argsort(node, kind="stable")
    out = {}
    for k, (dim, edges) in edges_of.items():
        mine = by[np.searchsorted(node, k, side="left", sorter=by) : np.searchsorted(node, k, side="right", sorter=by)]
        counts = np.bincount(bins[mine], weights=n[mine], minlength=len(edges) + 1)
        found = K.edge_nearest(edges, counts, -(-tree.want[k] // 2) / tree.want[k])
        if found:
            out[k] = (dim, found[0])
    return out
