"""The experiments as functions that give tables of measures; ``python -m orthant.experiments strong`` sweeps the cores, ``weak`` the scale factors.

Seconds depend on the machine; work counts, depths and balances don't.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import time
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orthant import kernel as K
from orthant import measures
from orthant import points as P
from orthant.functions.shipping import ship
from orthant.operators.knn import Knn
from orthant.operators.layout import build_layout
from orthant.plans.global_tree import sample
from orthant.points import PointSet
from orthant.sources.tables import written

ROW = "setting string, value string, build_s double, query_s double, depth int, balance double, nodes_visited double, points_compared double, remote_cells double, remote_share double"


def measured(ps: PointSet, queries: DataFrame, setting: str, value: object, cells: int = 16, k: int = 5, policy: K.SplitPolicy = K.SplitPolicy(), bucket_size: int = 32, prune: str = "mbr") -> tuple:
    """One run: a row of ROW."""
    began = time.perf_counter()
    layout = build_layout(ps, cells, policy, bucket_size)
    built = time.perf_counter()
    search = Knn(layout, queries, k, prune=prune)
    search.neighbors().agg(F.sum("d2")).collect()
    done = time.perf_counter()
    work, shape = measures.query_work(search).first(), measures.tree_shape(layout).first()
    return (setting, str(value), built - began, done - built, shape["depth"], shape["balance"], work["nodes_visited"], work["points_compared"], work["remote_cells"], work["remote_share"])


def _held(ps: PointSet, every: int = 10) -> tuple[PointSet, DataFrame]:
    ps = PointSet(written(ps.positions(), "points"), ps.dims)
    return ps, written(ps.sample_queries(every, 3), "queries")


def sweep(spark: SparkSession, ps: PointSet, setting: str, values: Iterable, **fixed) -> DataFrame:
    """One setting over several values: cells, k, bucket_size, prune, or a field of the split policy."""
    ps, q = _held(ps)
    rows = []
    for v in values:
        options = dict(fixed)
        if setting in ("cells", "k", "bucket_size", "prune"):
            options[setting] = v
        else:
            options["policy"] = K.SplitPolicy(**{setting: v})
        rows.append(measured(ps, q, setting, v, **options))
    return spark.createDataFrame(rows, ROW)


def policies(spark: SparkSession, sets: dict[str, PointSet], cells: int = 8) -> DataFrame:
    """The three tree policies on the same kernel: seconds, depth and work on every point set."""
    rows = []
    for name, ps in sets.items():
        ps, q = _held(ps)
        for policy, p in (("hist", K.SplitPolicy()), ("vfm", K.SplitPolicy.vfm()), ("brm", K.SplitPolicy.brm()), ("hist_range", K.SplitPolicy("range", "hist"))):
            rows.append(measured(ps, q, name, policy, cells, policy=p))
    return spark.createDataFrame(rows, ROW)


def weak_scaling(spark: SparkSession, steps: list[tuple[str, PointSet]], cells_for_first: int = 2) -> DataFrame:
    """Cells in proportion to the points."""
    rows, first = [], None
    for name, ps in steps:
        ps, q = _held(ps)
        n = ps.df.count()
        first = first or n
        rows.append(measured(ps, q, "weak", f"{name}: {n}", max(1, round(cells_for_first * n / first))))
    return spark.createDataFrame(rows, ROW)


def bin_lookups(spark: SparkSession, ps: PointSet, edges: int = 1024, repeats: int = 5) -> DataFrame:
    """Seconds of both lookups of all values of the second coordinate in its sampled edges, added up over the tasks, and whether they agree."""
    ship(spark)
    e = np.unique(sample(ps, edges)[:, 1])

    def timed(batches):
        took, off = {"binary": 0.0, "two_level": 0.0}, 0
        for batch in batches:
            v = batch.column("c1").to_numpy()
            for name, f in (("binary", K.bin_binary), ("two_level", K.bin_two_level)):
                took[name] += min(_seconds(lambda: f(v, e)) for _ in range(repeats))  # noqa: B023
            off += int((K.bin_two_level(v, e) != K.bin_binary(v, e)).sum())
        yield pa.RecordBatch.from_arrays([pa.array(list(took)), pa.array(list(took.values())), pa.array([0, off])], ["lookup", "seconds", "off"])

    told = ps.positions().select("c1").mapInArrow(timed, "lookup string, seconds double, off long")
    return told.groupBy("lookup").agg(F.sum("seconds").alias("seconds"), (F.sum("off") == 0).alias("agrees"))


def _seconds(f) -> float:
    began = time.perf_counter()
    f()
    return time.perf_counter() - began


def breakdown(spark: SparkSession, sets: dict[str, PointSet], cells: int = 16) -> DataFrame:
    """Shares of the phases of build and query, per point set."""
    out = None
    for name, ps in sets.items():
        ps, q = _held(ps)
        layout, build = measures.build_phases(ps, cells)
        _, query = measures.query_phases(layout, q)
        for part, p in (("build", build), ("query", query)):
            df = p.to_df(spark).select(F.lit(name).alias("points"), F.lit(part).alias("part"), "*")
            out = df if out is None else out.unionByName(df)
    return out


def _in_process(*args: object) -> dict:
    """One measurement in a process of its own."""
    out = subprocess.run([sys.executable, "-m", "orthant.experiments", "one", *map(str, args)], capture_output=True, text=True, check=True, cwd=os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    return json.loads(out.stdout.strip().splitlines()[-1])


def strong_scaling(sf_dir: str, cores: Iterable[int] = (1, 2, 4, 8), points: Iterable[str] = ("events3", "orders3", "line3"), cells: int = 32) -> list[dict]:
    """The same work on ever more cores: a task a core, as threads of one machine here, over executors on a cluster."""
    return [_in_process(sf_dir, n, p, cells) for p in points for n in cores]


def weak_scaling_over_scale_factors(top: str, steps: Iterable[tuple[str, int]] = (("sf0.001", 1), ("sf0.01", 2), ("sf0.1", 8)), points: str = "line3", cells_a_core: int = 4) -> list[dict]:
    """Points and cores grow together, as far as the scale factors allow: cells in proportion to the cores."""
    return [{"scale": name} | _in_process(f"{top}/{name}", n, points, cells_a_core * n) for name, n in steps]


def _one(sf_dir: str, cores: int, points: str, cells: int) -> None:
    spark = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(2 * cores)).config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "6g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    ps = getattr(P, points)(spark, sf_dir)
    ps = PointSet(written(ps.positions().repartition(16), "points"), ps.dims)
    q = written(ps.sample_queries(10, 3), "queries")
    for i in range(3):  # the first ones compile
        r = measured(ps, q, "strong", cores, cells)
    print(json.dumps({"cores": cores, "points": points, "n": ps.df.count(), "cells": cells, "build_s": round(r[2], 3), "query_s": round(r[3], 3)}))
    spark.stop()


if __name__ == "__main__":
    if sys.argv[1] == "one":
        _one(sys.argv[2], int(sys.argv[3]), sys.argv[4], int(sys.argv[5]))
    elif sys.argv[1] == "weak":
        for row in weak_scaling_over_scale_factors(sys.argv[2] if len(sys.argv) > 2 else "/root/testdata"):
            print(json.dumps(row))
    else:
        for row in strong_scaling(sys.argv[2] if len(sys.argv) > 2 else "/root/testdata/sf0.1"):
            print(json.dumps(row))
