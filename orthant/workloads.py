"""The engine's queries by name, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from orthant import kernel as K
from orthant import experiments, measures, relops, tree_sql
from orthant import points as P
from orthant.operators import predict
from orthant.operators.knn import Knn, found_in_all, knn, knn_all_nodes, knn_brute, knn_pipelined, knn_relational, knn_replicated, radius_search
from orthant.operators.layout import build_layout, collapse_colocated, independent_layout
from orthant.plans.global_tree import build_global_tree, sample
from orthant.plans.planner import knn_join
from orthant.points import PointSet
from orthant.sources.tables import table, written

Query = Callable[[SparkSession, str], DataFrame]
_QUERIES: dict[str, Query] = {}
_SQL: dict[str, str] = {}

# ---- point sets as SQL -----------------------------------------------------------------------------------------------

_DAY = "date_diff('day', DATE '1995-01-01', CAST({} AS DATE))"
POINTS_SQL = {
    "events3": """SELECT event_id AS pid, date_diff('microsecond', TIMESTAMP '2024-01-01', ts) / 86400e6 AS c0, value AS c1,
        CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS DOUBLE) AS c2, event_type AS label FROM events""",
    "orders3": f"""SELECT o_orderkey AS pid, o_totalprice / 1000 AS c0, CAST({_DAY.format('o_orderdate')} AS DOUBLE) AS c1,
        CAST(o_custkey AS DOUBLE) AS c2, o_orderpriority AS label FROM orders""",
    "line3": f"""SELECT row_number() OVER () AS pid, l_extendedprice / 1000 AS c0, l_quantity AS c1,
        CAST({_DAY.format('l_shipdate')} AS DOUBLE) AS c2, l_orderkey AS okey FROM lineitem""",
    "grid3": """SELECT row_number() OVER () AS pid, l_quantity AS c0, round(l_discount * 100) AS c1, round(l_tax * 100) AS c2,
        l_orderkey AS okey FROM lineitem""",
    "cust2": "SELECT c_custkey AS pid, c_acctbal AS c0, CAST(c_nationkey AS DOUBLE) AS c1, c_mktsegment AS label FROM customer",
    "part1": "SELECT p_partkey AS pid, CAST(p_partkey % 1000 AS DOUBLE) AS c0, p_retailprice AS target FROM part",
    "supp1": "SELECT s_suppkey AS pid, s_acctbal AS c0 FROM supplier",
    "doctext10": r"""SELECT doc_id AS pid, n / (n + 2000.0::DOUBLE) / 0.2::DOUBLE AS c0, nw / n / 0.05::DOUBLE AS c1, fr / n / 0.05::DOUBLE AS c2, de / n / 0.04::DOUBLE AS c3,
        es / n / 0.03::DOUBLE AS c4, dg / n / 0.02::DOUBLE AS c5, pu / n / 0.05::DOUBLE AS c6, up / n / 0.1::DOUBLE AS c7,
        CAST(dw AS DOUBLE) / CAST(nw AS DOUBLE) / 0.2::DOUBLE AS c8, CAST(dl AS DOUBLE) / CAST(nl AS DOUBLE) / 0.2::DOUBLE AS c9, lang AS label
        FROM (SELECT doc_id, lang, CAST(greatest(length(text), 1) AS DOUBLE) AS n, len(string_split(text, ' ')) AS nw, len(string_split(text, chr(10))) AS nl,
          len(list_distinct(string_split(text, ' '))) AS dw, len(list_distinct(string_split(text, chr(10)))) AS dl,
          length(text) - length(regexp_replace(text, '[éèêàâùçëïôœ]', '', 'g')) AS fr, length(text) - length(regexp_replace(text, '[äöüß]', '', 'g')) AS de,
          length(text) - length(regexp_replace(text, '[ñáíóúü]', '', 'g')) AS es, length(text) - length(regexp_replace(text, '[0-9]', '', 'g')) AS dg,
          length(text) - length(regexp_replace(text, '[!-/:-@]', '', 'g')) AS pu, length(text) - length(regexp_replace(text, '[A-Z]', '', 'g')) AS up FROM documents)""",
}
for _d in (10, 15, 64):
    POINTS_SQL[f"emb{_d}"] = "SELECT vec_id AS pid, " + ", ".join(f"CAST(embedding[{i + 1}] AS DOUBLE) AS c{i}" for i in range(_d)) + ", label FROM embeddings"
SETS: dict[str, tuple[Callable, int]] = {"events3": (P.events3, 3), "orders3": (P.orders3, 3), "line3": (P.line3, 3), "grid3": (P.grid3, 3), "cust2": (P.cust2, 2), "part1": (P.part1, 1), "supp1": (P.supp1, 1), "doctext10": (P.doctext10, 10), "emb10": (P.emb(10), 10), "emb15": (P.emb(15), 15), "emb64": (P.emb(64), 64)}


def distance_sql(dims: int) -> str:
    return " + ".join(f"(p.c{i} - q.c{i}) * (p.c{i} - q.c{i})" for i in range(dims))


def pairs_sql(name: str, queries: str, where: str = "TRUE", points: str = "TRUE", asked: str | None = None) -> str:
    """CTEs p, q and d(qid, pid, d2)."""
    dims = SETS[name][1]
    q = asked or f"SELECT pid AS qid, * EXCLUDE (pid) FROM a WHERE {queries}"
    return f"WITH a AS ({POINTS_SQL[name]}), p AS (SELECT * FROM a WHERE {points}), q AS ({q}), d AS (SELECT q.qid, p.pid, {distance_sql(dims)} AS d2 FROM p, q WHERE {where})"


def knn_sql(name: str, queries: str, k: int, columns: str = "qid, rank, pid, d2, sqrt(d2) AS dist", **kw: str) -> str:
    return pairs_sql(name, queries, **kw) + f", r AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid ORDER BY d2, pid) AS INT) AS rank FROM d), n AS (SELECT * FROM r WHERE rank <= {k}) SELECT {columns} FROM n"


def knn_top_sql(name: str, queries: str, k: int) -> str:
    """The same for very many pairs: only k of each query are ever kept."""
    return pairs_sql(name, queries) + f", m AS (SELECT qid, unnest(min({{'d2': d2, 'pid': pid}}, {k})) AS x FROM d GROUP BY qid) SELECT qid, CAST(row_number() OVER (PARTITION BY qid ORDER BY x) AS INT) AS rank, x.pid AS pid, x.d2 AS d2, sqrt(x.d2) AS dist FROM m"


def add(name: str, query: Query, sql: str | None = None) -> None:
    _QUERIES[name] = query
    if sql is not None:
        _SQL[name] = sql


def tenth(ps: PointSet) -> DataFrame:
    return ps.sample_queries(10, 3)


def some_lines(ps: PointSet) -> DataFrame:
    return ps.df.where(F.pmod("okey", F.lit(20)) == 0).select(F.col("pid").alias("qid"), *ps.coords)


TENTH, LINES = "pid % 10 = 3", "okey % 20 = 0"
CELLS = 16
EVENTS_TREE = tree_sql.tree(POINTS_SQL["events3"], 3, CELLS)


def _with_place(found: DataFrame, queries: DataFrame, dims: int) -> DataFrame:
    """Rank and distance by the query's place, for sets whose ids SQL can't make."""
    return found.join(queries, "qid").select("rank", "d2", *(f"c{i}" for i in range(dims)))


# ---- nearest neighbours ------------------------------------------------------------------------------------------------


def _strategies() -> None:
    def on(f: Callable[[PointSet, DataFrame], DataFrame], name: str = "events3") -> Query:
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            ps = SETS[name][0](spark, sf_dir)
            return f(ps, tenth(ps))

        return run

    ways = {
        "brute": lambda p, q: knn_brute(p, q, 5),
        "tree": lambda p, q: knn(build_layout(p, CELLS), q, 5),
        "sampled_tree": lambda p, q: knn(build_layout(p, CELLS, mode="sample"), q, 5),
        "relational": lambda p, q: knn_relational(build_layout(p, CELLS), q, 5),
        "all_nodes": lambda p, q: knn_all_nodes(independent_layout(p, 4), q, 5),
        "replicate": lambda p, q: knn_replicated(p, q, 5),
        "vfm": lambda p, q: knn(build_layout(p, CELLS, K.SplitPolicy.vfm()), q, 5),
        "brm": lambda p, q: knn(build_layout(p, CELLS, K.SplitPolicy.brm()), q, 5),
        "two_level_bins": lambda p, q: knn(build_layout(p, CELLS, K.SplitPolicy(two_level=True)), q, 5),
        "region_prune": lambda p, q: knn(build_layout(p, CELLS), q, 5, prune="region"),
        "no_prune": lambda p, q: knn(build_layout(p, 4), q, 5, prune="none"),
        "local_scan": lambda p, q: knn(build_layout(p, CELLS, bucket_size=0), q, 5),
        "far_first": lambda p, q: knn(build_layout(p, CELLS), q, 5, order="far_first"),
        "auto": lambda p, q: knn_join(p, q, 5),
    }
    for way, f in ways.items():
        add(f"knn_events3_{way}", on(f), knn_sql("events3", TENTH, 5))
    add("knn_orders3_tree", on(ways["tree"], "orders3"), knn_sql("orders3", TENTH, 5))
    add("knn_emb10_k5", on(ways["tree"], "emb10"), knn_sql("emb10", TENTH, 5))
    add("knn_emb10_k10", on(lambda p, q: knn_join(p, q, 10), "emb10"), knn_sql("emb10", TENTH, 10))
    add("knn_emb15_k10", on(lambda p, q: knn_replicated(p, q, 10), "emb15"), knn_sql("emb15", TENTH, 10))
    add("knn_emb64_brute", on(ways["brute"], "emb64"), knn_sql("emb64", TENTH, 5))
    add("knn_doctext10_tree", on(ways["tree"], "doctext10"), knn_sql("doctext10", TENTH, 5))
    for metric, far in (("l1", " + ".join(f"abs(p.c{i} - q.c{i})" for i in range(3))), ("linf", "greatest(" + ", ".join(f"abs(p.c{i} - q.c{i})" for i in range(3)) + ")")):
        add(f"knn_events3_{metric}", on(lambda p, q, metric=metric: knn(build_layout(p, CELLS), q, 5, metric=metric)), knn_sql("events3", TENTH, 5, "qid, rank, pid, d2, d2 AS dist").replace(distance_sql(3), far))
    add("knn_cust2_k3_p5", on(lambda p, q: knn(build_layout(p, 5), q, 3), "cust2"), knn_sql("cust2", TENTH, 3))
    add("knn_supp1_k200_exceeds_n", lambda s, d: knn(build_layout(P.supp1(s, d), 3), P.supp1(s, d).queries(), 200), knn_sql("supp1", "TRUE", 200))
    add("knn_customer_selfjoin", lambda s, d: knn(build_layout(P.cust2(s, d), CELLS), P.cust2(s, d).queries(), 5), knn_sql("cust2", "TRUE", 5))
    add("knn_exclude_self", on(lambda p, q: knn(build_layout(p, CELLS), q, 5, exclude_self=True)), knn_sql("events3", TENTH, 5, where="p.pid <> q.qid"))
    add("knn_within_radius", on(lambda p, q: knn(build_layout(p, CELLS), q, 5, max_radius=2.0)), knn_sql("events3", TENTH, 5, where=f"{distance_sql(3)} <= 4.0"))
    add("knn_filtered_points", on(lambda p, q: knn(build_layout(p.where("c1 > 110"), 4), q, 5)), knn_sql("events3", TENTH, 5, points="c1 > 110"))
    add("knn_batched", on(lambda p, q: knn(build_layout(p, 4), q, 5, batch_rows=64)), knn_sql("events3", TENTH, 5))
    add("radius_pairs", on(lambda p, q: radius_search(p, q, 2.0)), pairs_sql("events3", TENTH, f"{distance_sql(3)} <= 4.0") + " SELECT qid, pid, d2 FROM d")
    add("radius_count", on(lambda p, q: radius_search(p, q, 2.0).groupBy("qid").agg(F.count(F.lit(1)).alias("n"))), pairs_sql("events3", TENTH, f"{distance_sql(3)} <= 4.0") + " SELECT qid, count(*) AS n FROM d GROUP BY qid")
    for name in ("line3", "grid3"):
        def lines(s: SparkSession, d: str, name: str = name) -> DataFrame:
            ps = SETS[name][0](s, d)
            return _with_place(knn(build_layout(ps, CELLS), some_lines(ps), 5), some_lines(ps), 3)

        # ids differ between the engines, so distances alone are compared
        sql = pairs_sql(name, LINES) + ", m AS (SELECT qid, unnest(min(d2, 5)) AS d2 FROM d GROUP BY qid), r AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid ORDER BY d2) AS INT) AS rank FROM m) SELECT rank, d2, c0, c1, c2 FROM r JOIN q USING (qid)"
        add(f"knn_{name}_tree", lines, sql)

    def collapsed(s: SparkSession, d: str) -> DataFrame:
        ps = P.grid3(s, d)
        few = PointSet(collapse_colocated(ps, 5), 3)
        return _with_place(knn(build_layout(few, CELLS), some_lines(ps), 5), some_lines(ps), 3)

    add("knn_grid3_collapsed", collapsed, _SQL["knn_grid3_tree"])

    def jittered(s: SparkSession, d: str, dims: int) -> DataFrame:
        """Five queries a point."""
        ps = P.emb(dims)(s, d)
        steps = F.explode(F.sequence(F.lit(0), F.lit(4))).alias("j")
        q = ps.positions().select("*", steps)
        q = q.select((F.col("pid") * 5 + F.col("j")).alias("qid"), *((F.col(c) + F.col("j") * F.lit(0.015625)).alias(c) for c in ps.coords))
        return knn_replicated(ps, q, 10)

    for dims, name in ((10, "knn_jittered_external"), (15, "knn_jittered_external_15d")):
        shifted = "SELECT pid * 5 + j AS qid, " + ", ".join(f"c{i} + j * CAST(0.015625 AS DOUBLE) AS c{i}" for i in range(dims)) + " FROM a, (SELECT unnest(range(5)) AS j)"
        add(name, lambda s, d, dims=dims: jittered(s, d, dims), knn_sql(f"emb{dims}", "", 10, asked=shifted))
    for name in ("events3", "orders3"):
        add(f"knn_{name}_selfjoin", lambda s, d, name=name: knn(build_layout(SETS[name][0](s, d), CELLS), SETS[name][0](s, d).queries(), 5), knn_top_sql(name, "TRUE", 5))
    add("knn_events3_pipelined", on(lambda p, q: knn_pipelined(build_layout(p, CELLS), q, 5)), knn_sql("events3", TENTH, 5))
    add("knn_events3_in_pieces", on(lambda p, q: knn(build_layout(p, 2, piece_points=400), q, 5)), knn_sql("events3", TENTH, 5))


# ---- building ----------------------------------------------------------------------------------------------------------

_SAMPLED = "SELECT * FROM a ORDER BY (pid % 2147483648 * 2654435761) % 4294967296, pid LIMIT 512"


def _building() -> None:
    def level1(dim_rule: str) -> Query:
        def run(s: SparkSession, d: str) -> DataFrame:
            tree = build_global_tree(P.events3(s, d), 2, K.SplitPolicy(dim_rule, min_balance=0.0))
            return s.createDataFrame([(tree.dim[0], float(tree.split[0]))], "dim int, split double")

        return run

    def level1_sql(spread: str, source: str) -> str:
        edges = " UNION ALL ".join(f"SELECT {i} AS dim, c{i} AS e FROM s" for i in range(3))
        values = " UNION ALL ".join(f"SELECT {i} AS dim, c{i} AS v FROM a" for i in range(3))
        spreads = " UNION ALL ".join(f"SELECT {i} AS dim, {spread.format(f'c{i}')} AS x FROM {source}" for i in range(3))
        return f"""WITH a AS ({POINTS_SQL['events3']}), s AS ({_SAMPLED}), w AS ({spreads}), best AS (SELECT dim FROM w ORDER BY x DESC, dim LIMIT 1),
            e AS (SELECT DISTINCT e FROM ({edges}) WHERE dim = (SELECT dim FROM best)), v AS (SELECT v FROM ({values}) WHERE dim = (SELECT dim FROM best)),
            b AS (SELECT e, count(*) FILTER (WHERE v < e) AS below, count(*) AS n FROM e, v GROUP BY e)
            SELECT CAST((SELECT dim FROM best) AS INT) AS dim, e AS split FROM b WHERE below > 0 AND below < n ORDER BY abs(below / n - 0.5), e LIMIT 1"""

    add("split_level1_variance", level1("variance"), level1_sql("var_pop({})", "s"))
    add("split_level1_variance_full", level1("variance_full"), level1_sql("var_pop({})", "a"))
    add("split_level1_range", level1("range"), level1_sql("max({0}) - min({0})", "a"))

    def median(rule: str) -> Query:
        def run(s: SparkSession, d: str) -> DataFrame:
            tree = build_global_tree(PointSet.from_columns(P.events3(s, d).df, "pid", ["c1"]), 2, K.SplitPolicy("variance", rule))
            return s.createDataFrame([(float(tree.split[0]),)], "split double")

        return run

    base = f"WITH a AS (SELECT pid, c1 AS v FROM ({POINTS_SQL['events3']})), s AS ({_SAMPLED})"
    hist = ", e AS (SELECT DISTINCT v AS e FROM s), b AS (SELECT e, count(*) FILTER (WHERE v < e) AS below, count(*) AS n FROM e, a GROUP BY e) SELECT e AS split FROM b WHERE below > 0 AND below < n ORDER BY abs(below / n - 0.5), e LIMIT 1"
    add("median_hist", median("hist"), base + hist)
    add("median_exact", median("exact"), base + " SELECT quantile_disc(v, 0.5) AS split FROM a")
    add("median_midrange", median("midrange"), base + " SELECT min(v) + (max(v) - min(v)) / 2 AS split FROM a")
    add("median_first100", lambda s, d: median("first100")(s, d).select(F.round("split", 6).alias("split")), f"WITH a AS (SELECT pid, c1 AS v FROM ({POINTS_SQL['events3']})), s AS (SELECT * FROM a ORDER BY (pid % 2147483648 * 2654435761) % 4294967296, pid LIMIT 100) SELECT round(avg(v), 6) AS split FROM s")

    def sketched(s: SparkSession, d: str) -> DataFrame:
        """Whether the sketch's value lies as near to the middle rank as its accuracy promises."""
        ps = P.events3(s, d)
        tree = build_global_tree(PointSet.from_columns(ps.df, "pid", ["c1"]), 2, K.SplitPolicy("variance", "sketch"))
        below, upto = (F.sum(c.cast("long")) for c in (F.col("c1") < tree.split[0], F.col("c1") <= tree.split[0]))
        return ps.df.agg(F.count(F.lit(1)).alias("n"), ((below / F.count(F.lit(1)) <= 0.5 + 2e-4) & (upto / F.count(F.lit(1)) >= 0.5 - 2e-4)).alias("near"))

    add("median_sketch", sketched, "SELECT count(*) AS n, true AS near FROM events")

    def bins(s: SparkSession, d: str) -> DataFrame:
        """Counts between sampled edges, in generated code: the edges are literals."""
        ps = PointSet.from_columns(P.events3(s, d).df, "pid", ["c1"])
        edges = sorted(set(sample(ps, 16)[:, 0].tolist()))
        at = F.size(F.filter(F.array(*map(F.lit, edges)), lambda e: e <= F.col("c0")))
        return ps.df.groupBy(at.alias("bin")).agg(F.count(F.lit(1)).alias("n"))

    add("histogram_bins", bins, base.replace("LIMIT 512", "LIMIT 16") + ", e AS (SELECT DISTINCT v AS e FROM s), x AS (SELECT pid, count(*) FILTER (WHERE e <= v) AS bin FROM a, e GROUP BY pid) SELECT CAST(bin AS INT) AS bin, count(*) AS n FROM x GROUP BY bin")

    def lookups(s: SparkSession, d: str) -> DataFrame:
        """How many values the two bin lookups place differently: none."""
        ps = PointSet.from_columns(P.events3(s, d).df, "pid", ["c1"])
        edges = sorted(set(sample(ps, 512)[:, 0].tolist()))

        def both(batches):
            import numpy as np
            import pyarrow as pa

            e = np.array(edges)
            for b in batches:
                v = b.column("c0").to_numpy()
                yield pa.RecordBatch.from_arrays([pa.array((K.bin_two_level(v, e) != K.bin_binary(v, e)).astype(np.int64))], ["off"])

        return ps.df.mapInArrow(both, "off long").agg(F.count(F.lit(1)).alias("n"), F.sum("off").alias("different"))

    add("bin_lookup_equivalence", lookups, "SELECT count(*) AS n, CAST(0 AS BIGINT) AS different FROM events")
    def counts(s: SparkSession, d: str, cells: int) -> DataFrame:
        layout = build_layout(P.orders3(s, d), cells)
        return layout.points.groupBy(layout.asked_cell().alias("cell")).agg(F.count(F.lit(1)).alias("n"))

    for cells in (2, 4, 8):
        add(f"cell_counts_level{cells.bit_length() - 1}", lambda s, d, c=cells: counts(s, d, c), f"WITH {tree_sql.tree(POINTS_SQL['orders3'], 3, cells)} SELECT cell, n FROM box")

    def boxes(s: SparkSession, d: str) -> DataFrame:
        sides = [F.get(f"mbr_{side}o" if side == "l" else "mbr_hi", F.lit(i)).alias(f"{side}{i}") for i in range(3) for side in "lh"]
        return build_layout(P.events3(s, d), CELLS).cells_df(s).select(F.col("cell_id").alias("cell"), "n", *sides)

    add("cell_boxes", boxes, f"WITH {EVENTS_TREE} SELECT * FROM box")
    add("tree_nodes", lambda s, d: build_global_tree(P.events3(s, d), CELLS).to_df(s), f"WITH {EVENTS_TREE} {tree_sql.nodes(CELLS)}")

    def sizes(s: SparkSession, d: str) -> DataFrame:
        """Points in the buckets of each cell, and whether all buckets keep to the rule."""
        return build_layout(P.events3(s, d), CELLS).buckets().groupBy("cell").agg(F.sum("n").alias("n"), (F.max("n") <= 32).alias("fits"))

    add("bucket_sizes", sizes, f"WITH {EVENTS_TREE} SELECT cell, n, true AS fits FROM box")

    def owners(s: SparkSession, d: str) -> DataFrame:
        """Queries that the three ways of routing send to different cells: none."""
        ps = P.events3(s, d)
        tree = build_global_tree(ps, CELLS)
        routed = tree.routed(tenth(ps)).withColumn("other", tree.route_reduce())
        return routed.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("cell") != F.col("other")).cast("long")).alias("different"))

    add("owner_lookup", owners, "SELECT count(*) AS n, CAST(0 AS BIGINT) AS different FROM events WHERE event_id % 10 = 3")

    def shapes(s: SparkSession, d: str) -> DataFrame:
        out = None
        for name in ("events3", "orders3", "doctext10"):
            for policy, p in (("hist", K.SplitPolicy()), ("vfm", K.SplitPolicy.vfm()), ("brm", K.SplitPolicy.brm())):
                row = measures.tree_shape(build_layout(SETS[name][0](s, d), 4, p)).select(F.lit(name).alias("points"), F.lit(policy).alias("policy"), "*")
                out = row if out is None else out.unionByName(row)
        return out

    add("tree_depth_by_policy", shapes)


# ---- routing and work --------------------------------------------------------------------------------------------------


def _work() -> None:
    def search(s: SparkSession, d: str, name: str = "events3") -> Knn:
        ps = SETS[name][0](s, d)
        return Knn(build_layout(ps, CELLS), tenth(ps), 5)

    found_sql = f"WITH {EVENTS_TREE}, {tree_sql.search(3, TENTH, 5)} "
    add("remote_cells_per_query", lambda s, d: search(s, d).stats().select("qid", "cells_contacted", "remote_cells", "remote_in_answer"), found_sql + "SELECT * FROM told JOIN won USING (qid)")
    share_sql = "SELECT count(*) AS queries, round(avg(CASE WHEN remote_cells > 0 THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 6) AS remote_share, round(avg(remote_cells), 6) AS remote_cells, round(avg(remote_in_answer), 6) AS remote_in_answer FROM told JOIN won USING (qid)"
    add("remote_share", lambda s, d: measures.query_work(search(s, d)).select("queries", "remote_share", "remote_cells", "remote_in_answer"), found_sql + share_sql)
    add("traversals", lambda s, d: search(s, d).stats().select("qid", "nodes_visited"))
    add("points_compared", lambda s, d: search(s, d).stats().select("qid", "points_compared"))
    add("work_doctext10", lambda s, d: measures.query_work(search(s, d, "doctext10")))
    add("transferred_rows", lambda s, d: search(s, d).found.groupBy("hop").agg(F.count("pid").alias("rows")), found_sql + "SELECT CAST(0 AS INT) AS hop, count(*) AS rows FROM own UNION ALL SELECT 1, count(*) FROM far")

    def transferred_all(s: SparkSession, d: str) -> DataFrame:
        """Rows that the strategy without a global tree ships, counted: parts times k for each query."""
        ps = P.events3(s, d)
        return found_in_all(independent_layout(ps, 4), tenth(ps), 5).agg(F.count("pid").alias("rows"))

    add("transferred_rows_all_nodes", transferred_all, "SELECT count(*) * 20 AS rows FROM events WHERE event_id % 10 = 3")
    add("kth_distance_stats", lambda s, d: search(s, d).neighbors().where("rank = 5").agg(F.count(F.lit(1)).alias("n"), F.min("d2").alias("least"), F.max("d2").alias("largest")), knn_sql("events3", TENTH, 5, "count(*) AS n, min(d2) AS least, max(d2) AS largest") + " WHERE rank = 5")

    def recall(s: SparkSession, d: str) -> DataFrame:
        ps = P.events3(s, d)
        return predict.recall(knn(build_layout(ps, CELLS), tenth(ps), 5), knn_brute(ps, tenth(ps), 5))

    add("recall_vs_brute", recall, "SELECT count(*) * 5 AS n, count(*) * 5 AS found, CAST(1.0 AS DOUBLE) AS recall, CAST(1.0 AS DOUBLE) AS worst_ratio FROM events WHERE event_id % 10 = 3")

    def phases(s: SparkSession, d: str) -> DataFrame:
        ps = P.orders3(s, d)
        layout, build = measures.build_phases(ps, CELLS)
        _, query = measures.query_phases(layout, tenth(ps))
        return build.to_df(s).withColumn("part", F.lit("build")).unionByName(query.to_df(s).withColumn("part", F.lit("query")))

    add("phase_times", phases)

    def invariant(s: SparkSession, d: str) -> DataFrame:
        """Requests whose cell lies beyond the radius, and cells within it that got none: none of either."""
        ps = P.events3(s, d)
        layout = build_layout(ps, CELLS)
        found = Knn(layout, tenth(ps), 5)
        sent = found.requests.groupBy("qid").agg(F.count(F.lit(1)).alias("sent"))
        near = None
        for c in range(layout.cells):
            d2 = None
            for i in range(3):
                gap = F.greatest(F.lit(float(layout.lo[c, i])) - F.col(f"c{i}"), F.lit(0.0), F.col(f"c{i}") - F.lit(float(layout.hi[c, i])))
                d2 = gap * gap if d2 is None else d2 + gap * gap
            hit = ((d2 <= F.col("r2")) & (F.col("owner") != c)).cast("int")
            near = hit if near is None else near + hit
        told = found.bounded.withColumn("near", near).join(sent, "qid", "left").fillna(0, ["sent"])
        return told.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("near") != F.col("sent")).cast("long")).alias("different"))

    add("cells_within_radius", invariant, "SELECT count(*) AS n, CAST(0 AS BIGINT) AS different FROM events WHERE event_id % 10 = 3")


# ---- prediction --------------------------------------------------------------------------------------------------------

_VOTE = """, v AS (SELECT n.qid, p.label, count(*) AS votes, min(rank) AS best FROM n JOIN p USING (pid) GROUP BY ALL),
    w AS (SELECT qid, label AS predicted FROM (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY votes DESC, best, label) AS place FROM v) WHERE place = 1)"""


def _vote_sql(name: str, queries: str, k: int, tail: str) -> str:
    return knn_sql(name, queries, k, where="p.pid <> q.qid").rsplit(" SELECT ", 1)[0] + _VOTE + tail


def _prediction() -> None:
    def loo(name: str, cells: int = 8) -> Callable[[SparkSession, str], tuple[PointSet, DataFrame]]:
        def run(s: SparkSession, d: str) -> tuple[PointSet, DataFrame]:
            ps = SETS[name][0](s, d)
            ps = PointSet(written(ps.df, name), ps.dims)
            return ps, predict.classify(knn(build_layout(ps, cells), ps.queries(), 5, exclude_self=True), ps.df)

        return run

    lang, emb = loo("doctext10"), loo("emb10")
    add("classify_lang_loo", lambda s, d: lang(s, d)[1].select("qid", "predicted"), _vote_sql("doctext10", "TRUE", 5, " SELECT qid, predicted FROM w"))
    hits = " SELECT count(*) AS n, CAST(sum(CASE WHEN predicted = p.label THEN 1 ELSE 0 END) AS BIGINT) AS hits, round(sum(CASE WHEN predicted = p.label THEN 1 ELSE 0 END) / count(*), 6) AS accuracy FROM w JOIN p ON p.pid = w.qid"

    def acc(f: Callable) -> Query:
        def run(s: SparkSession, d: str) -> DataFrame:
            ps, told = f(s, d)
            return predict.accuracy(told, ps.df)

        return run

    add("accuracy", acc(lang), _vote_sql("doctext10", "TRUE", 5, hits))
    add("classify_embedding_control", acc(emb), _vote_sql("emb10", "TRUE", 5, hits))

    def confusion(s: SparkSession, d: str) -> DataFrame:
        ps, told = lang(s, d)
        return predict.confusion(told, ps.df)

    add("confusion_rollup", confusion, _vote_sql("doctext10", "TRUE", 5, " SELECT p.label AS truth, predicted, count(*) AS n FROM w JOIN p ON p.pid = w.qid GROUP BY ROLLUP (p.label, predicted)"))

    def per_class(s: SparkSession, d: str) -> DataFrame:
        ps, told = lang(s, d)
        return predict.class_recall(told, ps.df)

    add("class_recall", per_class, _vote_sql("doctext10", "TRUE", 5, " SELECT p.label AS truth, count(*) AS n, round(avg(CASE WHEN predicted = p.label THEN 1.0::DOUBLE ELSE 0.0::DOUBLE END), 6) AS recall FROM w JOIN p ON p.pid = w.qid GROUP BY p.label"))

    def quality(s: SparkSession, d: str) -> DataFrame:
        ps = P.doctext10(s, d)
        labels = table(s, d, "labels").select(F.col("doc_id").alias("pid"), F.col("quality").alias("q"))
        ps = PointSet(written(ps.df.drop("label").join(labels, "pid").withColumnRenamed("q", "label"), "quality"), 10)
        return predict.accuracy(predict.classify(knn(build_layout(ps, 4), ps.queries(), 5, exclude_self=True), ps.df), ps.df)

    labelled = _vote_sql("doctext10", "TRUE", 5, hits).replace(POINTS_SQL["doctext10"], f"SELECT x.* REPLACE (l.quality AS label) FROM ({POINTS_SQL['doctext10']}) x JOIN labels l ON l.doc_id = x.pid")
    add("classify_quality", quality, labelled)

    def weighted(s: SparkSession, d: str) -> DataFrame:
        ps = P.events3(s, d)
        found = knn(build_layout(ps, CELLS), tenth(ps), 5, exclude_self=True)
        return predict.classify(found, ps.df, weights="inverse").select("qid", "predicted")

    add("weighted_vote", weighted, knn_sql("events3", TENTH, 5, where="p.pid <> q.qid").rsplit(" SELECT ", 1)[0] + _VOTE.replace("count(*) AS votes", "sum(1 / (d2 + CAST(1e-9 AS DOUBLE))) AS votes") + " SELECT qid, predicted FROM w")

    def weighted_mean(s: SparkSession, d: str) -> DataFrame:
        ps = P.part1(s, d)
        return predict.regress(knn(build_layout(ps, 8), tenth(ps), 5, exclude_self=True), ps.df, weights="inverse").select("qid", F.round("predicted", 3).alias("predicted"))

    add("weighted_mean", weighted_mean, knn_sql("part1", TENTH, 5, "qid, round(sum(target / (d2 + CAST(1e-9 AS DOUBLE))) / sum(1 / (d2 + CAST(1e-9 AS DOUBLE))), 3) AS predicted", where="p.pid <> q.qid").replace("FROM n", "FROM n JOIN p USING (pid) GROUP BY qid"))

    def price(s: SparkSession, d: str) -> DataFrame:
        ps = P.part1(s, d)
        return predict.regress(knn(build_layout(ps, 8), tenth(ps), 5, exclude_self=True), ps.df).select("qid", F.round("predicted", 4).alias("predicted"))

    add("regress_retailprice", price, knn_sql("part1", TENTH, 5, "qid, round(CAST(sum(CAST(target AS DECIMAL(20, 6))) AS DOUBLE) / count(*), 4) AS predicted", where="p.pid <> q.qid").replace("FROM n", "FROM n JOIN p USING (pid) GROUP BY qid"))

    def dense(s: SparkSession, d: str) -> DataFrame:
        ps = P.events3(s, d)
        told = predict.knn_density(knn(build_layout(ps, CELLS), tenth(ps), 5, exclude_self=True), 5, 3)
        return told.orderBy("d2_k", "qid").limit(10).select("qid", "d2_k")

    add("density_top10", dense, knn_sql("events3", TENTH, 5, "qid, d2 AS d2_k", where="p.pid <> q.qid") + " WHERE rank = 5 ORDER BY d2, qid LIMIT 10")

    def flags(s: SparkSession, d: str) -> DataFrame:
        """Spots denser than one point in ten units of volume."""
        ps = P.events3(s, d)
        return predict.knn_density(knn(build_layout(ps, CELLS), tenth(ps), 5, exclude_self=True), 5, 3, 0.1).groupBy("dense").agg(F.count(F.lit(1)).alias("n"))

    volume = "CAST(4.1887902047863905 AS DOUBLE) * pow(d2, CAST(1.5 AS DOUBLE))"
    add("density_flags", flags, "SELECT dense, count(*) AS n FROM (" + knn_sql("events3", TENTH, 5, f"d2 = 0 OR CAST(5 AS DOUBLE) / ({volume}) > CAST(0.1 AS DOUBLE) AS dense", where="p.pid <> q.qid") + " WHERE rank = 5) GROUP BY dense")


# ---- experiments -------------------------------------------------------------------------------------------------------


def _experiments() -> None:
    for setting, values in (("bucket_size", (8, 32, 128)), ("sample_per_part", (32, 256)), ("cells", (1, 4, 16)), ("k", (1, 5, 20)), ("prune", ("mbr", "region", "none")), ("two_level", (True, False)), ("stride", (8, 32, 128)), ("local_sample", (64, 256, 1024)), ("dim_rule", ("variance", "variance_full", "range", "cycle")), ("value_rule", ("hist", "exact", "first100", "midrange", "sketch"))):
        add(f"exp_{setting}", lambda s, d, x=setting, v=values: experiments.sweep(s, P.events3(s, d), x, v))
    three = ("events3", "orders3", "doctext10")
    add("exp_policies", lambda s, d: experiments.policies(s, {n: SETS[n][0](s, d) for n in three}))
    add("exp_breakdown", lambda s, d: experiments.breakdown(s, {n: SETS[n][0](s, d) for n in ("orders3", "grid3")}))
    add("exp_bin_lookups", lambda s, d: experiments.bin_lookups(s, P.events3(s, d)))

    def weak(s: SparkSession, d: str) -> DataFrame:
        """Parts of the events in proportion to the cells: a tenth, half, all."""
        ps = P.events3(s, d)
        return experiments.weak_scaling(s, [(str(n), ps.where(F.pmod("pid", F.lit(10)) >= 10 - n)) for n in (1, 5, 10)])

    add("exp_weak_scaling", weak)


_strategies()
_building()
_experiments()
_work()
_prediction()
for _name, (_f, _sql) in relops.QUERIES.items():
    add(_name, _f, _sql)


def queries() -> dict[str, Query]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
