"""Names for SQL text: distances, cell lookup, cells within a radius, local search."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from orthant import kernel as K
from orthant.functions.shipping import ship
from orthant.operators.knn import Boxes, Knn
from orthant.operators.layout import SpatialLayout
from orthant.plans.global_tree import descend

#: Bodies of SQL functions over arrays of doubles.
SQL_FUNCTIONS = {
    "l2sq": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"),
    "l1dist": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "aggregate(zip_with(a, b, (x, y) -> abs(x - y)), 0D, (s, x) -> s + x)"),
    "linfdist": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "array_max(zip_with(a, b, (x, y) -> abs(x - y)))"),
    "box_min_l2sq": (
        "q ARRAY<DOUBLE>, lo ARRAY<DOUBLE>, hi ARRAY<DOUBLE>",
        "aggregate(transform(zip_with(q, arrays_zip(lo, hi), (x, b) -> greatest(b.lo - x, 0D, x - b.hi)), g -> g * g), 0D, (s, x) -> s + x)",
    ),
}


def register_functions(spark: SparkSession) -> None:
    for name, (args, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS DOUBLE RETURN {body}")
    ship(spark)

    @F.pandas_udf("array<bigint>")
    def edges_histogram(v: pd.Series, edges: pd.Series) -> list:
        """Counts of a group's values between the edges of its first row."""
        return K.histogram(v.to_numpy(dtype=float), np.asarray(edges.iloc[0], dtype=float)).tolist()

    spark.udf.register("edges_histogram", edges_histogram)


def register_layout(spark: SparkSession, layout: SpatialLayout) -> None:
    """cell_of(coords) and tree_cells_within(coords, r2), bound to this layout's tree."""
    ship(spark)
    shared = spark.sparkContext.broadcast((layout.tree.arrays(), layout.tree.cell_of_node(), Boxes(layout, "mbr")))

    @F.arrow_udf("int")
    def cell_of(coords: pa.Array) -> pa.Array:
        arrays, cell, _ = shared.value
        x = np.array(coords.to_pylist(), dtype=float).reshape(len(coords), -1)
        return pa.array(cell[descend(arrays, x)].astype(np.int32))

    @F.udtf(returnType="cell int")
    class CellsWithin:
        def eval(self, coords: list, r2: float) -> Iterator[tuple]:
            boxes = shared.value[2]
            _, cells = boxes.within(np.array([coords], dtype=float), np.array([r2], dtype=float))
            for c in sorted(cells.tolist()):
                yield (int(c),)

    spark.udf.register("cell_of", cell_of)
    spark.udtf.register("tree_cells_within", CellsWithin)


def register_local_search(spark: SparkSession, dims: int, k: int) -> None:
    """knn_local(TABLE(rows) PARTITION BY cell): rows (kind, id, coordinates); kind 0 is a point, 1 a query."""
    ship(spark)

    @F.udtf(returnType="qid bigint, rank int, pid bigint, d2 double")
    class KnnLocal:
        def __init__(self) -> None:
            self.rows: list = []

        def eval(self, row) -> None:
            self.rows.append((row["kind"], row["id"], [float(row[f"c{i}"]) for i in range(dims)]))

        def terminate(self) -> Iterator[tuple]:
            p, q = [r for r in self.rows if r[0] == 0], [r for r in self.rows if r[0] == 1]
            if p and q:
                tree = K.build(np.array([r[2] for r in p]), np.array([r[1] for r in p], dtype=np.int64))
                found = K.search(tree, np.array([r[2] for r in q]), k)
                for i, r in enumerate(q):
                    for j in range(k):
                        if found.ids[i, j] != K.NO_ID:
                            yield int(r[1]), j + 1, int(found.ids[i, j]), float(found.d2[i, j])

    spark.udtf.register("knn_local", KnnLocal)


def knn_merge(column: Column, k: int) -> Column:
    """Aggregate: the k smallest structs of a group, sorted; for a bounded number of candidates a query."""
    return F.slice(F.sort_array(F.collect_list(column)), 1, k)


def knn_view(spark: SparkSession, layout: SpatialLayout, queries_view: str, k: int, name: str) -> None:
    """A temporary view of the neighbours of a view's queries (qid, c0, c1, ...)."""
    Knn(layout, spark.table(queries_view), k).neighbors().createOrReplaceTempView(name)
