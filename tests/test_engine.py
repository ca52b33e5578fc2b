"""Strategies agree, invariants hold, plans have the wanted shape, layouts survive storage."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from orthant import kernel as K
from orthant import measures, relops
from orthant import points as P
from orthant.operators import knn as knn_module
from orthant.operators import predict
from orthant.operators.knn import Knn, knn, knn_all_nodes, knn_brute, knn_relational, knn_replicated, radius_search
from orthant.operators.layout import SpatialLayout, build_layout, collapse_colocated, independent_layout, pack
from orthant.plans import global_tree
from orthant.plans.global_tree import GlobalTree, build_global_tree, descend
from orthant.plans.planner import choose, knn_join
from orthant.points import PointSet
from orthant.sources.tables import written
from orthant.streaming import streams

POLICIES = {"hist": K.SplitPolicy(), "vfm": K.SplitPolicy.vfm(), "brm": K.SplitPolicy.brm(), "exact": K.SplitPolicy("variance_full", "exact"), "sketch": K.SplitPolicy("cycle", "sketch")}


def rows(df):
    return sorted(tuple(r) for r in df.select("qid", "rank", "pid", "d2").collect())


@pytest.fixture(scope="module")
def cloud(spark):
    rng = np.random.default_rng(11)
    x = np.concatenate([rng.normal(size=(400, 3)), rng.integers(0, 3, (200, 3)), np.full((60, 3), 1.0)])
    df = spark.createDataFrame([(i, *map(float, p)) for i, p in enumerate(x)], "pid long, c0 double, c1 double, c2 double").repartition(5)
    return PointSet(df.persist(), 3)


@pytest.fixture(scope="module")
def asked(spark, cloud):
    far = spark.createDataFrame([(10_000, 50.0, -50.0, 0.0), (10_001, 0.0, 0.0, 1e6)], "qid long, c0 double, c1 double, c2 double")
    return cloud.sample_queries(20, 3).unionByName(far).persist()


@pytest.fixture(scope="module")
def want(cloud, asked):
    return rows(knn_brute(cloud, asked, 5))


@pytest.mark.parametrize("cells", [1, 2, 3, 5, 8, 16])
def test_any_number_of_cells(cloud, asked, want, cells):
    assert rows(knn(build_layout(cloud, cells), asked, 5)) == want


@pytest.mark.parametrize("policy", POLICIES)
@pytest.mark.parametrize("bucket", [1, 32])
def test_any_policy(cloud, asked, want, policy, bucket):
    assert rows(knn(build_layout(cloud, 6, POLICIES[policy], bucket), asked, 5)) == want


def test_other_strategies(cloud, asked, want):
    layout = build_layout(cloud, 7, mode="sample")
    assert rows(knn(layout, asked, 5)) == want
    assert rows(knn_relational(layout, asked, 5)) == want
    assert rows(knn_all_nodes(independent_layout(cloud, 3), asked, 5)) == want
    assert rows(knn_replicated(cloud, asked, 5)) == want
    for batch in (1, 7, 1000):
        assert rows(knn(layout, asked, 5, batch_rows=batch)) == want
    for strategy in ("auto", "brute", "replicate", "tree"):
        assert rows(knn_join(cloud, asked, 5, strategy)) == want
    for prune in ("none", "region"):
        assert rows(knn(layout, asked, 5, prune=prune)) == want


@pytest.mark.parametrize("metric", ["l1", "linf"])
def test_other_metrics(cloud, asked, metric):
    exact = rows(knn_brute(cloud, asked, 5, metric=metric))
    assert rows(knn(build_layout(cloud, 6), asked, 5, metric=metric)) == exact
    assert rows(knn(build_layout(cloud, 6), asked, 4, max_radius=0.7, metric=metric)) == rows(knn_brute(cloud, asked, 4, max_radius=0.7, metric=metric))


def test_blocks_of_queries(cloud, asked, want):
    assert rows(knn_brute(cloud, asked, 5, block=10)) == want


def test_small_sets_and_large_k(spark, cloud, asked):
    few = PointSet(cloud.df.where("pid < 4"), 3)
    got = rows(knn(build_layout(few, 3), asked, 10))
    assert got == rows(knn_brute(few, asked, 10)) and len(got) == 4 * asked.count()
    none = PointSet(cloud.df.where("false"), 3)
    assert knn(build_layout(none, 3), asked, 5).count() == 0
    assert knn(build_layout(cloud, 3), asked.where("false"), 5).count() == 0
    with pytest.raises(ValueError):
        knn(build_layout(few, 2), asked, 0)


def test_radius(cloud, asked):
    pairs = sorted(tuple(r) for r in radius_search(cloud, asked, 0.5).select("qid", "pid").collect())
    near = knn_brute(cloud, asked, 660, max_radius=0.5)
    assert pairs == sorted((q, p) for q, _, p, _ in rows(near))
    assert rows(knn(build_layout(cloud, 6), asked, 3, max_radius=0.5)) == rows(knn_brute(cloud, asked, 3, max_radius=0.5))


def test_prefix_of_k_and_far_points(spark, cloud, asked, want):
    six = [r for r in rows(knn(build_layout(cloud, 6), asked, 6)) if r[1] <= 5]
    assert six == want
    more = cloud.df.unionByName(spark.createDataFrame([(99_999, 1e9, 1e9, 1e9)], cloud.df.schema))
    assert rows(knn(build_layout(PointSet(more, 3), 6), asked, 5)) == want


def test_collapsed_spots(cloud, asked, want):
    few = PointSet(collapse_colocated(cloud, 5), 3)
    assert few.df.count() < cloud.df.count() and rows(knn(build_layout(few, 5), asked, 5)) == want


def test_a_spot_with_most_points(spark, asked):
    rng = np.random.default_rng(2)
    x = [(i, 1.0, 1.0, 1.0) for i in range(3000)] + [(5000 + i, *map(float, rng.normal(size=3))) for i in range(300)]
    ps = PointSet(spark.createDataFrame(x, "pid long, c0 double, c1 double, c2 double"), 3)
    for own in (False, True):
        q = ps.sample_queries(100, 3)
        assert rows(knn_join(ps, q, 5, "tree", cells=8, exclude_self=own)) == rows(knn_brute(ps, q, 5, exclude_self=own))
    copies = collapse_colocated(ps, 2, with_copies=True).groupBy("copies").count().collect()
    assert sorted(map(tuple, copies)) == [(1, 300), (3000, 2)]


def test_hot_cells_are_dealt(cloud, asked, want, monkeypatch):
    monkeypatch.setattr(knn_module, "BATCH_ROWS", 5)
    assert rows(knn(build_layout(cloud, 3), asked, 5)) == want


def test_cells_partition_the_points(cloud):
    layout = build_layout(cloud, 9)
    assert layout.n.sum() == cloud.df.count()
    lo, hi = layout.tree.regions()
    for r in layout.points.collect():
        x = np.array([r["c0"], r["c1"], r["c2"]])
        assert (lo[r["cell"]] <= x).all() and (x < hi[r["cell"]]).all()
        assert (layout.lo[r["cell"]] <= x).all() and (x <= layout.hi[r["cell"]]).all()


def test_all_ways_of_routing_agree(cloud):
    tree = build_global_tree(cloud, 9)
    got = tree.routed(cloud.df).withColumn("other", tree.route_reduce()).select("c0", "c1", "c2", "cell", "other").toPandas()
    x = got[["c0", "c1", "c2"]].to_numpy()
    assert (got["cell"] == got["other"]).all() and (tree.cell_of_node()[descend(tree.arrays(), x)] == got["cell"]).all()


def test_many_cells_are_routed_by_the_shipped_tree(spark, cloud, asked, want):
    layout = build_layout(cloud, 100, mode="sample")
    assert layout.cells > 64 and rows(knn(layout, asked, 5)) == want


def test_growing_inside_groups(spark, cloud, asked, want, monkeypatch):
    monkeypatch.setattr(global_tree, "GROUPS", 3)
    layout = build_layout(cloud, 11, mode="groups")
    assert 8 <= layout.cells <= 11 and layout.n.sum() == cloud.df.count() and rows(knn(layout, asked, 5)) == want


def test_balance_of_the_first_split(spark, sf):
    for make in (P.events3, P.orders3):
        layout = build_layout(make(spark, sf), 2)
        assert abs(layout.n[0] / layout.n.sum() - 0.5) < 0.05


def test_tree_does_not_depend_on_partitions(cloud):
    a, b = build_global_tree(cloud, 8), build_global_tree(PointSet(cloud.df.repartition(3), 3), 8)
    assert a == b


def test_depth_of_the_policies(spark):
    ps = P.doctext10(spark, "/root/testdata/sf0.01")
    depth = {n: measures.tree_shape(build_layout(ps, 2, POLICIES[n])).first()["depth"] for n in ("hist", "vfm", "brm")}
    assert depth["hist"] <= depth["vfm"] and depth["hist"] <= depth["brm"]


def test_storage(spark, cloud, asked, want, tmp_path):
    layout = build_layout(cloud, 6)
    layout.save(str(tmp_path / "at"))
    back = SpatialLayout.load(spark, str(tmp_path / "at"))
    assert back.tree == layout.tree and back.facts == layout.facts and rows(knn(back, asked, 5)) == want
    assert GlobalTree.from_df(layout.tree.to_df(spark), 3) == layout.tree


def test_packed_points_lie_bucket_by_bucket(cloud):
    layout = build_layout(cloud, 6)
    own = sorted(tuple(r) for r in layout.points.select("pid", "c0", "c1", "c2").collect())
    assert own == sorted(tuple(r) for r in cloud.df.select("pid", "c0", "c1", "c2").collect())
    boxes = {(r["cell"], r["bucket"]): r for r in layout.buckets().collect()}
    by = {}
    for r in pack(layout).collect():
        by.setdefault((r["cell"], r["bucket"]), []).append((r["c0"], r["c1"], r["c2"]))
    assert set(by) == set(boxes)
    for key, x in by.items():
        x = np.array(x)
        assert len(x) == boxes[key]["n"] and x.min(axis=0).tolist() == boxes[key]["mbr_lo"] and x.max(axis=0).tolist() == boxes[key]["mbr_hi"]
    assert layout.facts["buckets"] == len(boxes) and layout.facts["largest"] == max(r["n"] for r in boxes.values())


def points_side(df):
    """The plan below the join on the side of the packed cells."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    side = plan[plan.index("ShuffledHashJoin") :]
    return side[: side.index("FileScan")]


def test_points_are_not_exchanged(spark, cloud, asked, want, tmp_path):
    """In neither pass, as built and as loaded; no tree is built in a search."""
    layout = build_layout(cloud, 16)
    layout.save(str(tmp_path / "at"))
    for own in (layout, SpatialLayout.load(spark, str(tmp_path / "at"))):
        search = Knn(own, asked, 5)
        for df in (search.remote, knn_module.search_cells(own, search.asked, 5, 0)):
            assert "Exchange" not in points_side(df) and "Sort" not in points_side(df)
        assert rows(search.neighbors()) == want


def test_no_tree_is_built_in_a_search(cloud, asked, want, monkeypatch):
    layout = build_layout(cloud, 4)
    monkeypatch.setattr(knn_module.K, "build", None)  # of this process; workers run the search's own code, which doesn't name it
    import inspect

    assert "build(" not in inspect.getsource(knn_module._search_rows) and rows(knn(layout, asked, 5)) == want


def test_batches_under_way_together(cloud, asked, want):
    assert rows(knn_module.knn_pipelined(build_layout(cloud, 6), asked, 5, batches=3)) == want


def test_a_cell_too_large_for_a_task(spark):
    """It is split by further passes over all points; what stands in one spot is dealt into pieces of the same cell."""
    rng = np.random.default_rng(2)
    x = [(i, 1.0, 1.0, 1.0) for i in range(3000)] + [(5000 + i, *map(float, rng.normal(size=3))) for i in range(900)]
    ps = PointSet(spark.createDataFrame(x, "pid long, c0 double, c1 double, c2 double"), 3)
    layout = build_layout(ps, 2, piece_points=200)
    pieces = {r["cell"]: r["count"] for r in layout.packed.groupBy("cell").count().collect()}
    assert layout.cells > 4 and layout.n.sum() == 3900
    assert max(pieces.values()) >= 15 and all(pieces[c] >= layout.n[c] / 400 for c in pieces) and layout.packed.agg(F.max("n")).first()[0] < 400
    q = ps.sample_queries(50, 3)
    assert rows(knn(layout, q, 5)) == rows(knn_brute(ps, q, 5))
    assert rows(knn(layout, q, 5, exclude_self=True)) == rows(knn_brute(ps, q, 5, exclude_self=True))


def test_five_thousand_cells_asked_and_got(spark):
    ps = PointSet(spark.range(60_000).select(F.col("id").alias("pid"), *(F.pmod(F.xxhash64("id", F.lit(i)), F.lit(1 << 30)).cast("double").alias(f"c{i}") for i in range(2))), 2)
    tree = build_global_tree(PointSet(written(ps.df, "points"), 2), 5000, K.SplitPolicy(sample_per_part=8))
    assert tree.cells == 5000
    assert build_global_tree(ps, 600, K.SplitPolicy(sample_per_part=8)).cells == 600


def test_overweight_cells_of_a_sampled_tree_are_repaired(spark):
    ps = PointSet(written(spark.range(20_000).select(F.col("id").alias("pid"), F.pow(F.pmod(F.xxhash64("id"), F.lit(100_000)) / 100_000, 8).alias("c0")), "points"), 1)
    poor = K.SplitPolicy(sample_per_part=2)
    raw = global_tree.grow_from_sample(global_tree.sample(ps, 2 * 32), 32, poor)
    counts = lambda tree: max(r["count"] for r in tree.routed(ps.df).groupBy("cell").count().collect())
    fixed = build_global_tree(ps, 32, poor, "sample")
    assert counts(raw) > 2 * 20_000 / 32 >= counts(fixed) / 1.5 and fixed.cells > raw.cells


def test_an_index_goes_on_after_a_restart(spark, cloud, asked, want, tmp_path):
    """An index opened again at its path knows batches, delta and tree; a batch that comes again is not taken twice."""
    path, policy = str(tmp_path / "index"), streams.RebuildPolicy(3)
    part = lambda i: cloud.df.where(F.pmod("pid", F.lit(5)) == i)
    index = streams.RebuildingIndex(spark, 3, 4, path, policy)
    for i in range(3):
        index.add(part(i), i)
    # a batch whose line was not written when the process ended
    part(3).where("pid < 50").select("pid", "c0", "c1", "c2").write.parquet(f"{path}/delta/3")
    again = streams.RebuildingIndex(spark, 3, 4, path, policy)
    assert again.done == {0, 1, 2} and again.versions == index.versions and again.delta == index.delta == [1, 2]
    for i in (1, 2, 3, 4):
        again.add(part(i), i)
    assert [v[:3] for v in again.versions] == [(1, 0, part(0).count()), (2, 3, sum(part(i).count() for i in range(4)))]
    last = streams.RebuildingIndex(spark, 3, 4, path, policy)
    assert rows(again.knn(asked, 5)) == rows(last.knn(asked, 5)) == want


def test_a_cluster_must_name_its_shared_folder():
    from orthant.sources import tables

    class Unset:
        def get(self, *_):
            return None

    class Context:
        master = "spark://host:7077"
        getConf = staticmethod(Unset)
        getCheckpointDir = staticmethod(lambda: None)

    class Session:
        conf, sparkContext = Unset(), Context()

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        tables.shared_dir(Session())


def test_recall_and_distance_ratio(cloud, asked):
    exact = knn_brute(cloud, asked, 5)
    worse = exact.where("not (qid = 10000 and rank = 1)").unionByName(exact.where("qid = 10000 and rank = 5").selectExpr("qid", "rank", "pid + 100000 AS pid", "4 * d2 AS d2", "2 * dist AS dist"))
    r = predict.recall(worse, exact).first()
    assert r["n"] - r["found"] == 1 and r["worst_ratio"] == 2.0 and predict.recall(exact, exact).first()["worst_ratio"] == 1.0
    dense = predict.knn_density(exact, 5, 3, 1.0)
    assert dense.where("dense <> (density > 1.0)").count() == 0 and {r["dense"] for r in dense.collect()} == {True, False}


def test_plans(cloud, asked):
    layout = build_layout(cloud, 6)
    text = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in text(knn(layout, asked, 5))
    relational = text(knn_relational(layout, asked, 5))
    assert "Python" not in relational and "Arrow" not in relational and "CartesianProduct" not in relational
    box = text(P.orders3(cloud.df.sparkSession, "/root/testdata/sf0.001").where("pid > 5").positions())
    assert "o_orderpriority" not in box.split("ReadSchema")[1] and "PushedFilters: [IsNotNull(o_orderkey), GreaterThan(o_orderkey,5)]" in box


def test_work_counts(cloud, asked):
    s = Knn(build_layout(cloud, 6), asked, 5).stats()
    r = s.agg(F.min("cells_contacted").alias("c"), F.min("points_compared").alias("p"), F.max("remote_in_answer").alias("m"), F.count("*").alias("n")).first()
    assert r["c"] >= 1 and r["p"] > 0 and r["m"] <= 5 and r["n"] == asked.count()


def test_bad_points(spark):
    rows_ = [(1, 0.0), (2, float("nan")), (3, float("inf")), (None, 1.0), (5, None)]
    ps = PointSet(spark.createDataFrame(rows_, "pid long, c0 double"), 1)
    with pytest.raises(ValueError, match="4 rows"):
        ps.checked()
    assert [r["pid"] for r in ps.checked("drop").df.collect()] == [1] and ps.bad_rows().count() == 4


def test_scaling(spark, cloud):
    z = cloud.scaled("zscore").df.agg(F.avg("c1").alias("m"), F.stddev_pop("c1").alias("s")).first()
    assert abs(z["m"]) < 1e-9 and abs(z["s"] - 1) < 1e-9
    m = cloud.scaled("minmax").df.agg(F.min("c2").alias("a"), F.max("c2").alias("b")).first()
    assert (m["a"], m["b"]) == (0.0, 1.0)


def test_vote_ties(spark):
    n = spark.createDataFrame([(1, 1, 10, 0.0), (1, 2, 11, 1.0), (1, 3, 12, 2.0), (1, 4, 13, 3.0)], "qid long, rank int, pid long, d2 double")
    labels = spark.createDataFrame([(10, "b"), (11, "a"), (12, "a"), (13, "b")], "pid long, label string")
    r = predict.classify(n, labels).first()
    assert r["predicted"] == "b" and r["votes"] == {"a": 2.0, "b": 2.0}


def test_late_rows_of_all_days(spark, sf):
    """Every day but the open last ones, each once: the replayed first day is late and adds nothing."""
    from orthant import relops

    got = sorted((r["day"], r["event_type"], r["n"]) for r in relops.stream_late_rows(spark, sf).collect())
    days = spark.read.parquet(f"{sf}/events.parquet").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day"), "event_type").count().collect()
    last = max(r["day"] for r in days)
    assert got == sorted((r["day"], r["event_type"], r["count"]) for r in days if r["day"] < last) and len({d for d, _, _ in got}) > 4


def test_planner():
    assert choose(1000, 100, 3, 8).strategy == "brute"
    assert choose(10**6, 10**6, 3, 8).strategy == "replicate"
    assert choose(10**7, 10**3, 64, 8).strategy == "brute"
    plan = choose(3 * 10**12, 10**9, 3, 8000)
    assert plan.strategy == "tree" and plan.cells > 10**5


def test_lateral_topk_of_many_copies(spark, tmp_path):
    """Copies of a balance, small nations and lacking balances; no row meets its whole nation."""
    from conftest import same_rows

    x = [(i, i % 3, float(i // 50) if i % 11 else None) for i in range(400)] + [(1000, 7, 1.0), (1001, 7, None), (1002, 8, 5.0), (1003, None, 1.0)]
    spark.createDataFrame(x, "c_custkey long, c_nationkey int, c_acctbal double").coalesce(1).write.parquet(f"{tmp_path}/all")
    next((tmp_path / "all").glob("*.parquet")).rename(tmp_path / "customer.parquet")
    run, sql = relops.QUERIES["op_lateral_topk"]
    got = run(spark, str(tmp_path))
    assert same_rows(got, sql, str(tmp_path))
    joins = [line for line in got._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join" in line]
    assert joins and all("LeftOuter" in line for line in joins)  # each to at most one row: no pairs of a nation


def test_streams_leave_results_in_the_store(spark, sf):
    """No sink in the driver's memory: a stream's result is read from the shared folder."""
    for name in ("stream_distinct_requests", "stream_session_counts"):
        got = relops.QUERIES[name][0](spark, sf)
        assert got.inputFiles() and all("/result/" in f for f in got.inputFiles())


def test_a_stream_without_rows(spark, tmp_path):
    spark.createDataFrame([], "k long").write.parquet(str(tmp_path / "none"))
    assert streams.run_to_store(spark.readStream.schema("k long").parquet(str(tmp_path / "none")), "append").count() == 0


def test_replicated_cell_by_cell(cloud, asked, want, monkeypatch):
    """The driver never fetches all points at once; any number of cells gives the same rows."""
    monkeypatch.setattr(knn_module, "REPLICA_POINTS", 100)
    most, whole = [], knn_module._stream
    monkeypatch.setattr(knn_module, "_stream", lambda part: most.append(sum(len(p) for p in part.column("pid"))) or whole(part))
    assert rows(knn_replicated(cloud, asked, 5)) == want
    assert len(most) > 3 and max(most) < 330
    assert rows(knn_replicated(cloud, asked, 5, exclude_self=True)) == rows(knn_brute(cloud, asked, 5, exclude_self=True))


def test_many_pieces_grow_on_the_executors(cloud, asked, want, monkeypatch):
    """Samples that the driver holds don't grow with the pieces."""
    monkeypatch.setattr(global_tree, "GROUPS", 4)
    held, grow = [], global_tree._grow
    monkeypatch.setattr(global_tree, "_grow", lambda p, t, members, policy: held.append(sum(map(len, members.values()))) or grow(p, t, members, policy))
    layout = build_layout(cloud, 2, K.SplitPolicy(sample_per_part=8), piece_points=20)
    assert max(held) <= 4 * 8 * 2 and layout.cells > 20 and layout.n.sum() == 660
    assert rows(knn(layout, asked, 5)) == want


def test_cells_asked_for_are_counted_after_further_splits(cloud):
    """Cells too large for a task are split, but the count is by the cells asked for."""
    count = lambda layout: {r["c"]: r["count"] for r in layout.points.groupBy(layout.asked_cell().alias("c")).count().collect()}
    split = build_layout(cloud, 2, piece_points=100)
    assert split.cells > 4 and count(split) == count(build_layout(cloud, 2))


def test_bin_lookups_of_a_table(spark, sf):
    from orthant import workloads

    got = workloads.queries()["exp_bin_lookups"](spark, sf)
    assert got.inputFiles() and {r["lookup"]: r["agrees"] for r in got.collect()} == {"binary": True, "two_level": True}


def test_small_batches_meet_a_packed_cell_once(cloud, asked, want):
    layout = build_layout(cloud, 2)
    search = Knn(layout, asked, 5, batch_rows=3)
    assert knn_module.packed_queries(layout, search.asked, asked.count(), 3).count() <= 2
    assert rows(search.neighbors()) == want


def test_exhaustive_search_sends_k_rows_a_core_and_spot(spark, cloud, asked, want):
    """Not for each of the session's shuffle partitions, and queries from one spot ask once."""
    twice = asked.unionByName(asked.withColumn("qid", F.col("qid") + 100_000))
    got = rows(knn_brute(cloud, twice, 5))
    assert got == sorted(want + [(q + 100_000, *r) for q, *r in want])


def test_relational_search_ranks_few_points(spark, cloud, asked, want, monkeypatch):
    """Boxes below the cells bound what a query meets: not all points of its cells, nor all copies in one spot."""
    met, merge = [], knn_module.merge_topk
    monkeypatch.setattr(knn_module, "merge_topk", lambda found, *a: met.append(found.count()) or merge(found, *a))
    assert rows(knn_relational(build_layout(cloud, 2), asked, 5)) == want
    x = np.random.default_rng(3).normal(size=(6000, 3))
    x[:2000] = 0.5
    many = PointSet(spark.createDataFrame([(i, *map(float, p)) for i, p in enumerate(x)], "pid long, c0 double, c1 double, c2 double").persist(), 3)
    own = many.sample_queries(20, 3)
    for k in (5, 40):
        assert rows(knn_relational(build_layout(many, 2), own, k)) == rows(knn(build_layout(many, 2), own, k))
    assert met[1] < 10 * 5 * own.count()
    assert rows(knn_relational(build_layout(many.where("pid < 3"), 2), own, 5)) == rows(knn_brute(many.where("pid < 3"), own, 5))
    assert knn_relational(build_layout(many.where("pid < 0"), 1), own, 5).count() == 0


def test_streams_take_each_event_once(spark, sf, tmp_path):
    """Events that share an id, or have none, are rows like any other: the days are made without a join."""
    from conftest import same_rows

    e = spark.read.parquet(f"{sf}/events.parquet").where("event_id < 40")
    odd = e.withColumn("event_id", F.when(F.col("event_id") % 3 > 0, F.col("event_id") % 7))
    odd.coalesce(1).write.parquet(str(tmp_path / "all"))
    next((tmp_path / "all").glob("*.parquet")).rename(tmp_path / "events.parquet")
    for name in ("stream_session_counts", "stream_tumbling_counts"):
        run, sql = relops.QUERIES[name]
        assert same_rows(run(spark, str(tmp_path)), sql, str(tmp_path))


def test_recall_runs_each_search_once(spark):
    """Neighbours and k-th distances are both taken from what a search gave once."""
    given = spark.createDataFrame([(q, r + 1, 10 * q + r, float(r), float(r)) for q in range(50) for r in range(5)], "qid long, rank int, pid long, d2 double, dist double")
    passed = [spark.sparkContext.accumulator(0) for _ in range(2)]

    def counted(rows_of):
        def run(batches):
            for batch in batches:
                rows_of.add(batch.num_rows)
                yield batch

        return given.mapInArrow(run, given.schema)

    told = predict.recall(*(counted(x) for x in passed)).first()
    assert tuple(told) == (250, 250, 1.0, 1.0) and [x.value for x in passed] == [250, 250]
