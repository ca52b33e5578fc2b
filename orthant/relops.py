"""Operators around the search, each on a given table, with the SQL that checks it: name -> (query, SQL or None)."""

from __future__ import annotations

import os
import struct
import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from orthant import points as P
from orthant import tree_sql
from orthant.functions import surface
from orthant.operators.knn import Knn
from orthant.operators.layout import build_layout
from orthant.points import PointSet, hash32
from orthant.sources import formats
from orthant.sources.tables import fresh_path, table, written
from orthant.streaming import streams

_EVENTS3 = """SELECT event_id AS pid, date_diff('microsecond', TIMESTAMP '2024-01-01', ts) / 86400e6 AS c0, value AS c1, CAST(regexp_extract(props, '"k": *([0-9]+)', 1) AS DOUBLE) AS c2 FROM events"""
QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def query(sql: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = (f, sql)
        return f

    return keep



def one() -> Column:
    return F.count(F.lit(1))


# ---- projection, filter, sample, statistics ------------------------------------------------------------------------------


@query("SELECT o_orderkey AS pid, o_totalprice / 1000 AS c0, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS DOUBLE) AS c1, CAST(o_custkey AS DOUBLE) AS c2 FROM orders")
def op_project_positions(s, d):
    return P.orders3(s, d).positions()


@query("SELECT event_type, count(*) AS n FROM events WHERE value > 110 GROUP BY event_type")
def op_energy_filter(s, d):
    return table(s, d, "events").where("value > 110").groupBy("event_type").agg(one().alias("n"))


@query("SELECT count(*) AS n, min(l_extendedprice) AS least, max(l_extendedprice) AS most FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_discount BETWEEN 0.02 AND 0.05")
def op_box_filter(s, d):
    box = F.col("l_quantity").between(10, 20) & F.col("l_discount").between(0.02, 0.05)
    return table(s, d, "lineitem").where(box).agg(one().alias("n"), F.min("l_extendedprice").alias("least"), F.max("l_extendedprice").alias("most"))


@query("SELECT o_orderkey AS pid FROM orders WHERE o_orderkey % 10 = 3")
def op_sample_tenth(s, d):
    return P.orders3(s, d).sample_queries(10, 3).select(F.col("qid").alias("pid"))


@query("SELECT event_type, event_id FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY (event_id % 2147483648 * 2654435761) % 4294967296, event_id) AS r FROM events) WHERE r <= 256")
def op_bottom_m_sample(s, d):
    w = Window.partitionBy("event_type").orderBy(hash32(F.col("event_id")), "event_id")
    return table(s, d, "events").withColumn("r", F.row_number().over(w)).where("r <= 256").select("event_type", "event_id")


@query("SELECT count(*) AS n, round(var_pop(value), 4) AS v1, round(var_pop(CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS DOUBLE)), 4) AS v2 FROM events")
def op_variance_by_dim(s, d):
    return P.events3(s, d).df.agg(one().alias("n"), F.round(F.var_pop("c1"), 4).alias("v1"), F.round(F.var_pop("c2"), 4).alias("v2"))


@query("SELECT max(o_totalprice) - min(o_totalprice) AS price, max(o_custkey) - min(o_custkey) AS customer FROM orders")
def op_range_by_dim(s, d):
    return table(s, d, "orders").agg((F.max("o_totalprice") - F.min("o_totalprice")).alias("price"), (F.max("o_custkey") - F.min("o_custkey")).alias("customer"))


@query("SELECT round(quantile_cont(l_extendedprice, 0.5), 6) AS median, round(quantile_cont(l_extendedprice, 0.1), 6) AS d1, round(quantile_cont(l_extendedprice, 0.9), 6) AS d9 FROM lineitem")
def op_percentiles(s, d):
    p = lambda q: F.round(F.percentile("l_extendedprice", F.lit(q)), 6)
    return table(s, d, "lineitem").agg(p(0.5).alias("median"), p(0.1).alias("d1"), p(0.9).alias("d9"))


_EDGES = (0, 5, 10, 20, 40, 80, 160, 320)


@query("SELECT bin, count(*) AS n FROM (SELECT " + " + ".join(f"CAST(value >= {e} AS INT)" for e in _EDGES) + " AS bin FROM events) GROUP BY bin")
def op_histogram_nonuniform(s, d):
    at = F.size(F.filter(F.array(*(F.lit(float(e)) for e in _EDGES)), lambda e: F.col("value") >= e))
    return table(s, d, "events").groupBy(at.alias("bin")).agg(one().alias("n"))


@query("SELECT bin, n, CAST(sum(n) OVER (ORDER BY bin) AS BIGINT) AS upto FROM (SELECT CAST(floor(value / 10) AS BIGINT) AS bin, count(*) AS n FROM events GROUP BY 1)")
def op_prefix_sum(s, d):
    h = table(s, d, "events").groupBy(F.floor(F.col("value") / 10).alias("bin")).agg(one().alias("n"))
    return h.withColumn("upto", F.sum("n").over(Window.orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)))


# ---- joins ---------------------------------------------------------------------------------------------------------------


@query("SELECT r_name, count(*) AS n, CAST(sum(CAST(c_acctbal AS DECIMAL(18, 2))) AS DOUBLE) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def op_broadcast_join(s, d):
    small = table(s, d, "nation").join(table(s, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 rows
    met = table(s, d, "customer").join(F.broadcast(small), F.col("c_nationkey") == F.col("n_nationkey"))
    return met.groupBy("r_name").agg(one().alias("n"), F.sum(F.col("c_acctbal").cast("decimal(18,2)")).cast("double").alias("balance"))


@query("SELECT o_orderkey, count(*) AS lines, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS price FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey")
def op_sortmerge_join(s, d):
    met = table(s, d, "orders").select("o_orderkey").hint("merge").join(table(s, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"))
    return met.groupBy("o_orderkey").agg(one().alias("lines"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("price"))


@query("SELECT doc_id, lang FROM documents SEMI JOIN labels USING (doc_id)")
def op_semi_join(s, d):
    return table(s, d, "documents").select("doc_id", "lang").join(table(s, d, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id, lang FROM documents ANTI JOIN labels USING (doc_id)")
def op_anti_join(s, d):
    return table(s, d, "documents").select("doc_id", "lang").join(table(s, d, "labels"), "doc_id", "left_anti")


_BOXES = ((0, 0.0, 50.0, 0.0, 40.0), (1, 50.0, 600.0, 0.0, 40.0), (2, 0.0, 50.0, 40.0, 100.0), (3, 50.0, 600.0, 40.0, 100.0))
_GAP = "greatest(greatest({0}lo - {0}, 0.0), {0} - {0}hi)"


@query(
    "WITH b(cell, xlo, xhi, ylo, yhi) AS (VALUES " + ", ".join(map(str, _BOXES)) + "), q AS (SELECT event_id, value AS x, CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS DOUBLE) AS y FROM events WHERE event_id % 10 = 3)"
    f" SELECT event_id, cell FROM q, b WHERE {_GAP.format('x')} * {_GAP.format('x')} + {_GAP.format('y')} * {_GAP.format('y')} <= 25"
)
def op_theta_box_join(s, d):
    b = s.createDataFrame(_BOXES, "cell int, xlo double, xhi double, ylo double, yhi double")
    q = P.events3(s, d).df.where("pid % 10 = 3").select(F.col("pid").alias("event_id"), F.col("c1").alias("x"), F.col("c2").alias("y"))
    gap = lambda c: F.greatest(F.col(f"{c}lo") - F.col(c), F.lit(0.0), F.col(c) - F.col(f"{c}hi"))
    return q.join(F.broadcast(b), gap("x") * gap("x") + gap("y") * gap("y") <= 25).select("event_id", "cell")


@query("SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey AND abs(a.s_acctbal - b.s_acctbal) <= 50")
def op_range_join(s, d):
    """Within 50: an equi-join on buckets of that width, each row of one side in three of them."""
    sup = table(s, d, "supplier").select("s_suppkey", "s_acctbal", F.floor(F.col("s_acctbal") / 50).alias("g"))
    near = sup.withColumn("g", F.explode(F.array(*(F.col("g") + i for i in (-1, 0, 1)))))
    on = (F.col("a.g") == F.col("b.g")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey")) & (F.abs(F.col("a.s_acctbal") - F.col("b.s_acctbal")) <= 50)
    return sup.alias("a").join(near.alias("b"), on).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


@query("SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey AND l_shipdate BETWEEN o_orderdate AND o_orderdate + INTERVAL 60 DAY GROUP BY o_orderpriority")
def op_interval_join(s, d):
    on = (F.col("l_orderkey") == F.col("o_orderkey")) & F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("INTERVAL 60 DAYS"))
    return table(s, d, "orders").join(table(s, d, "lineitem"), on).groupBy("o_orderpriority").agg(one().alias("n"))


@query(
    "WITH e AS (SELECT * FROM events WHERE event_type = 'error'), p AS (SELECT user_id, ts AS pts FROM events WHERE event_type = 'purchase')"
    " SELECT event_id, max(pts) AS last_purchase FROM e LEFT JOIN p ON e.user_id = p.user_id AND p.pts <= e.ts GROUP BY event_id"
)
def op_asof_join(s, d):
    """The last purchase before each error of the same user: one window, no pairs."""
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    seen = table(s, d, "events").where(F.col("event_type").isin("error", "purchase")).withColumn("last_purchase", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(w))
    return seen.where("event_type = 'error'").select("event_id", "last_purchase")


@query(
    "SELECT a.c_custkey AS a, b.c_custkey AS b FROM customer a, customer b WHERE a.c_nationkey = b.c_nationkey AND a.c_custkey <> b.c_custkey"
    " QUALIFY row_number() OVER (PARTITION BY a.c_custkey ORDER BY abs(a.c_acctbal - b.c_acctbal), b.c_custkey) <= 3"
)
def op_lateral_topk(s, d):
    """Three nearest balances in the same nation, from a lateral generator over each spot's few neighbours.

    Only the four smallest keys of a balance can answer, and of other balances those as near as the third distinct one on
    either side; so a customer meets a bounded number of rows, however many share the nation. Lacking balances come last.
    """
    table(s, d, "customer").createOrReplaceTempView("orthant_customer")
    return s.sql(
        "WITH c AS (SELECT c_nationkey AS n, c_acctbal AS v, c_custkey AS k FROM orthant_customer WHERE c_nationkey IS NOT NULL),"
        " few AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY n, v ORDER BY k) AS r FROM c) WHERE r <= 4),"
        " spot AS (SELECT n, v, collect_list(k) AS ks FROM few WHERE v IS NOT NULL GROUP BY n, v),"
        " near AS (SELECT n, v, collect_list(struct(v, ks)) OVER (PARTITION BY n ORDER BY v ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING) AS around FROM spot),"
        " lacks AS (SELECT n, collect_list(k) AS ks FROM few WHERE v IS NULL GROUP BY n),"
        " least AS (SELECT n, collect_list(k) AS ks FROM (SELECT *, row_number() OVER (PARTITION BY n ORDER BY k) AS r FROM c) WHERE r <= 4 GROUP BY n),"
        " met AS (SELECT c.v, c.k, coalesce(near.around, array()) AS around, coalesce(if(c.v IS NULL, least.ks, lacks.ks), array()) AS last"
        " FROM c LEFT JOIN near ON c.n = near.n AND c.v = near.v LEFT JOIN lacks ON c.n = lacks.n LEFT JOIN least ON c.n = least.n),"
        " pairs AS (SELECT k, concat(flatten(transform(around, x -> transform(x.ks, y -> struct(abs(v - x.v) AS gap, y AS k)))), transform(last, y -> struct(double('NaN') AS gap, y AS k))) AS p FROM met)"
        " SELECT a.k AS a, x.k AS b FROM pairs a, LATERAL inline(slice(array_sort(filter(a.p, y -> y.k <> a.k)), 1, 3)) AS x(gap, k)"
    )


# ---- aggregates, windows, sets -------------------------------------------------------------------------------------------

_SPOT = "l_quantity, round(l_discount * 100), round(l_tax * 100)"


@query(f"SELECT copies, count(*) AS spots FROM (SELECT count(*) AS copies FROM lineitem GROUP BY {_SPOT}) GROUP BY copies")
def op_distinct_spots(s, d):
    return P.grid3(s, d).df.groupBy("c0", "c1", "c2").agg(one().alias("copies")).groupBy("copies").agg(one().alias("spots"))


@query("SELECT count(DISTINCT (l_quantity, round(l_discount * 100), round(l_tax * 100))) AS spots, true AS near FROM lineitem")
def op_approx_distinct(s, d):
    """The sketch's count beside the exact one: within five of its standard errors."""
    spot = F.struct("c0", "c1", "c2")
    found = P.grid3(s, d).df.agg(F.approx_count_distinct(spot, 0.02).alias("sketch"), F.count_distinct("c0", "c1", "c2").alias("spots"))
    return found.select("spots", (F.abs(F.col("sketch") - F.col("spots")) <= 0.1 * F.col("spots")).alias("near"))


@query("SELECT event_type, CAST(CASE WHEN value < 20 THEN 0 WHEN value < 40 THEN 1 WHEN value < 60 THEN 2 ELSE 3 END AS INT) AS bin, count(*) AS n FROM events GROUP BY ALL")
def op_edges_histogram(s, d):
    """Counts between given edges, by the grouped aggregate of the SQL surface."""
    surface.register_functions(s)
    table(s, d, "events").createOrReplaceTempView("orthant_events")
    got = s.sql("SELECT event_type, edges_histogram(value, array(20D, 40D, 60D)) AS n FROM orthant_events GROUP BY event_type")
    return got.select("event_type", F.posexplode("n").alias("bin", "n")).where("n > 0")


@query("SELECT event_type, strftime(ts, '%Y-%m-%d') AS day, count(*) AS n FROM events GROUP BY ROLLUP (event_type, strftime(ts, '%Y-%m-%d'))")
def op_rollup(s, d):
    return table(s, d, "events").select("event_type", F.date_format("ts", "yyyy-MM-dd").alias("day")).rollup("event_type", "day").agg(one().alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def op_cube(s, d):
    return table(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(one().alias("n"))


@query("SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")
def op_grouping_sets(s, d):
    return table(s, d, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(one().alias("n"))


@query("SELECT quality, " + ", ".join(f"CAST(coalesce(sum(CASE WHEN lang = '{x}' THEN 1 END), 0) AS BIGINT) AS {x}" for x in ("en", "fr", "de", "es")) + " FROM labels JOIN documents USING (doc_id) GROUP BY quality")
def op_pivot(s, d):
    met = table(s, d, "labels").join(table(s, d, "documents").select("doc_id", "lang"), "doc_id")
    return met.groupBy("quality").pivot("lang", ["en", "fr", "de", "es"]).agg(one()).fillna(0)


@query("SELECT p_partkey, rank() OVER w AS rank, dense_rank() OVER w AS dense, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS INT) AS quarter FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_retailprice)")
def op_rank_family(s, d):
    w = Window.partitionBy("p_brand").orderBy("p_retailprice")
    return table(s, d, "part").select("p_partkey", F.rank().over(w).cast("long").alias("rank"), F.dense_rank().over(w).cast("long").alias("dense"), F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).alias("quarter"))


@query("SELECT event_id, coalesce(date_diff('microsecond', lag(ts) OVER w, ts), -1) AS before, coalesce(date_diff('microsecond', ts, lead(ts) OVER w), -1) AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_lag_lead(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(s, d, "events").select("event_id", "ts", F.lag("ts").over(w).alias("p"), F.lead("ts").over(w).alias("n"))
    return e.select("event_id", F.coalesce(F.timestamp_diff("MICROSECOND", F.col("p"), F.col("ts")), F.lit(-1)).alias("before"), F.coalesce(F.timestamp_diff("MICROSECOND", F.col("ts"), F.col("n")), F.lit(-1)).alias("after"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND 3 FOLLOWING), 6) AS around FROM events")
def op_moving_density(s, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 3)
    return table(s, d, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("around"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def op_topk_global(s, d):
    return table(s, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(20).select("o_orderkey", "o_totalprice")


def _keys(s, d):
    return table(s, d, "customer").select(F.col("c_nationkey").alias("k")), table(s, d, "supplier").select(F.col("s_nationkey").alias("k"))


@query("SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def op_union(s, d):
    a, b = _keys(s, d)
    return a.unionByName(b).distinct()


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def op_intersect(s, d):
    a, b = _keys(s, d)
    return a.intersect(b)


@query("SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def op_except(s, d):
    a, b = _keys(s, d)
    return a.exceptAll(b)


# ---- arrays, maps, strings, dates ----------------------------------------------------------------------------------------


@query(
    "WITH z AS (SELECT embedding AS e FROM embeddings WHERE vec_id = 0) SELECT vec_id, round(list_sum(list_transform(range(1, 65), lambda i: (CAST(embedding[i] AS DOUBLE) - e[i]) * (CAST(embedding[i] AS DOUBLE) - e[i]))), 9) AS d2"
    " FROM embeddings, z ORDER BY d2, vec_id LIMIT 10"
)
def op_array_math(s, d):
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("x"))
    zero = F.broadcast(e.where("vec_id = 0").select(F.col("x").alias("z")))  # one row
    d2 = F.aggregate(F.zip_with("x", "z", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda t, v: t + v)
    return e.join(zero).select("vec_id", F.round(d2, 9).alias("d2")).orderBy("d2", "vec_id").limit(10)


@query("SELECT CAST(i AS INT) AS dim, round(avg(CAST(embedding[i + 1] AS DOUBLE)), 9) AS mean FROM embeddings, (SELECT unnest(range(10)) AS i) GROUP BY i")
def op_posexplode_coords(s, d):
    e = table(s, d, "embeddings").select(F.posexplode(F.slice("embedding", 1, 10)).alias("dim", "x"))
    return e.groupBy("dim").agg(F.round(F.avg(F.col("x").cast("double")), 9).alias("mean"))


@query("SELECT label, count(*) AS votes FROM embeddings GROUP BY label")
def op_map_votes(s, d):
    """Votes through a map and back."""
    v = table(s, d, "embeddings").groupBy("label").agg(one().alias("n"))
    m = v.agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("label", "n")))).alias("m"))  # one entry for each label
    return m.select(F.explode("m").alias("label", "votes"))


@query("SELECT CAST(floor(CAST(regexp_extract(props, '\"k\": *([0-9]+)', 1) AS INT) / 10) AS BIGINT) AS tens, count(*) AS n FROM events GROUP BY 1")
def op_json_extract(s, d):
    return table(s, d, "events").groupBy(F.floor(F.get_json_object("props", "$.k").cast("int") / 10).alias("tens")).agg(one().alias("n"))


@query("SELECT doc_id, length(text) AS chars, length(text) - length(regexp_replace(text, '[A-Z]', '', 'g')) AS capitals, length(text) - length(regexp_replace(text, '[0-9]', '', 'g')) AS digits FROM documents")
def op_string_features(s, d):
    return table(s, d, "documents").select("doc_id", F.length("text").cast("long").alias("chars"), F.regexp_count("text", F.lit("[A-Z]")).cast("long").alias("capitals"), F.regexp_count("text", F.lit("[0-9]")).cast("long").alias("digits"))


@query("SELECT page_id, length(html) AS chars, len(regexp_extract_all(html, '<[a-zA-Z]')) AS tags, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host FROM pages")
def op_page_features(s, d):
    return table(s, d, "pages").select("page_id", F.length("html").cast("long").alias("chars"), F.regexp_count("html", F.lit("<[a-zA-Z]")).cast("long").alias("tags"), F.parse_url("url", F.lit("HOST")).alias("host"))


@query("SELECT role, count(*) AS turns, round(avg(length(text)), 6) AS mean_chars FROM conversations GROUP BY role")
def op_conversation_turns(s, d):
    return table(s, d, "conversations").groupBy("role").agg(one().alias("turns"), F.round(F.avg(F.length("text")), 6).alias("mean_chars"))


@query("SELECT o_orderkey, month(o_orderdate) AS m, dayofweek(o_orderdate) + 1 AS weekday, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def op_date_features(s, d):
    return table(s, d, "orders").select("o_orderkey", F.month("o_orderdate").cast("long").alias("m"), F.dayofweek("o_orderdate").cast("long").alias("weekday"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).cast("long").alias("days"))


# ---- SQL surface, formats ------------------------------------------------------------------------------------------------


@query("SELECT event_id, (value - 50) * (value - 50) + 0 AS d2, greatest(greatest(10 - value, 0.0), value - 20) * greatest(greatest(10 - value, 0.0), value - 20) AS box FROM events")
def op_sql_functions(s, d):
    surface.register_functions(s)
    table(s, d, "events").createOrReplaceTempView("orthant_events")
    return s.sql("SELECT event_id, l2sq(array(value), array(50D)) AS d2, box_min_l2sq(array(value), array(10D), array(20D)) AS box FROM orthant_events")


@query(
    f"WITH {tree_sql.tree(_EVENTS3, 3, 8)}, q AS (SELECT pid AS qid, cell AS owner, * EXCLUDE (pid, cell) FROM leaf WHERE pid % 20 = 0) SELECT qid, owner, b.cell FROM q JOIN box b ON "
    + " + ".join(f"greatest(b.l{i} - c{i}, 0.0::DOUBLE, c{i} - b.h{i}) * greatest(b.l{i} - c{i}, 0.0::DOUBLE, c{i} - b.h{i})" for i in range(3)) + " <= 100"
)
def op_udtf_cells(s, d):
    ps = P.events3(s, d)
    layout = build_layout(ps, 8)
    surface.register_layout(s, layout)
    ps.sample_queries(20, 0).select("qid", F.array("c0", "c1", "c2").alias("coords")).createOrReplaceTempView("orthant_asked")
    return s.sql("SELECT qid, cell_of(coords) AS owner, w.cell FROM orthant_asked, LATERAL tree_cells_within(coords, 100D) w")


@query(
    "WITH p AS (SELECT event_id AS id, event_type AS t, value AS v FROM events) SELECT q.id AS qid, CAST(row_number() OVER (PARTITION BY q.id ORDER BY (p.v - q.v) * (p.v - q.v), p.id) AS INT) AS rank, p.id AS pid,"
    " (p.v - q.v) * (p.v - q.v) AS d2 FROM p JOIN p q ON p.t = q.t WHERE q.id % 20 = 0 QUALIFY rank <= 3"
)
def op_udtf_local_knn(s, d):
    """Nearest values inside each event type, by a table function over partitions."""
    surface.register_local_search(s, 1, 3)
    e = table(s, d, "events").select("event_type", F.col("event_id").alias("id"), F.col("value").alias("c0"))
    e.withColumn("kind", F.lit(0)).unionByName(e.where("id % 20 = 0").withColumn("kind", F.lit(1))).createOrReplaceTempView("orthant_rows")
    return s.sql("SELECT * FROM knn_local(TABLE(orthant_rows) PARTITION BY event_type)")


@query("SELECT 'csv' AS format, count(*) AS n, CAST(sum(CAST(p_retailprice AS DECIMAL(18, 2))) AS DOUBLE) AS price FROM part UNION ALL SELECT 'json', count(*), CAST(sum(CAST(p_retailprice AS DECIMAL(18, 2))) AS DOUBLE) FROM part UNION ALL SELECT 'orc', count(*), CAST(sum(CAST(p_retailprice AS DECIMAL(18, 2))) AS DOUBLE) FROM part")
def op_csv_json_orc_roundtrip(s, d):
    part, out = table(s, d, "part").select("p_partkey", "p_retailprice"), None
    for kind in ("csv", "json", "orc"):
        path = fresh_path(s, kind)
        writer = part.write.format(kind)
        (writer.option("header", True) if kind == "csv" else writer).save(path)
        back = formats.points(s, path, kind, "p_partkey long, p_retailprice double")
        row = back.agg(F.lit(kind).alias("format"), one().alias("n"), F.sum(F.col("p_retailprice").cast("decimal(18,2)")).cast("double").alias("price"))
        out = row if out is None else out.unionByName(row)
    return out


@query("SELECT count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS DOUBLE) AS price, CAST(sum(o_custkey) AS DOUBLE) AS customers FROM orders")
def op_column_arrays_source(s, d):
    """One file for each property, written for the example from the orders, read as row ranges of all files."""
    from urllib.parse import urlparse

    top = fresh_path(s, "arrays")
    if urlparse(top).scheme not in ("", "file"):
        raise ValueError(f"plain array files need a mounted folder, not {top}")
    local = urlparse(top).path
    os.makedirs(local, exist_ok=True)
    rows = table(s, d, "orders").select("o_totalprice", F.col("o_custkey").cast("double").alias("o_custkey"))
    paths = {c: f"{local}/{c}-{uuid.uuid4().hex}.f8" for c in rows.columns}
    files = [open(p, "wb") for p in paths.values()]
    for r in rows.toLocalIterator():  # a partition at a time; each file gets its property in the order of the rows
        for f, x in zip(files, r, strict=True):
            f.write(struct.pack("<d", x))
    for f in files:
        f.close()
    back = formats.column_arrays(s, paths, 4096)
    return back.agg(one().alias("n"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("price"), F.sum("o_custkey").alias("customers"))


@query("SELECT event_id AS pid, value * 2 AS c0 FROM events WHERE event_id % 10 = 3")
def op_explode_pack_coords(s, d):
    packed = formats.pack_coords(table(s, d, "events").where("event_id % 10 = 3").select(F.col("event_id").alias("pid"), (F.col("value") * 2).alias("c0")), 1)
    return formats.explode_coords(packed, "coords", 1)


# ---- streams -------------------------------------------------------------------------------------------------------------


def _by_day(s: SparkSession, d: str) -> str:
    """Events as one file for each day, in the order of the days, so that no file is late."""
    path = fresh_path(s, "days")
    e = P.events3(s, d, time=streams.event_time(), event_type="event_type", user_id="user_id", day=F.to_date("ts")).df.drop("label")
    e.repartitionByRange(8, "day").sortWithinPartitions("day").write.partitionBy("day").parquet(path)
    return path


_EVENT = "pid long, c0 double, c1 double, c2 double, time timestamp, event_type string, user_id long"


def _stream(s: SparkSession, d: str) -> DataFrame:
    return s.readStream.schema(_EVENT + ", day date").parquet(_by_day(s, d))


@query("SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling_counts(s, d):
    got = streams.run_to_store(streams.windowed_counts(_stream(s, d), ["event_type"], F.window("time", "1 day")))
    return got.select(F.to_timestamp_ntz(F.date_format("start", "yyyy-MM-dd HH:mm:ss")).alias("day"), "event_type", "n")


@query("SELECT time_bucket(INTERVAL 6 HOUR, ts) - to_hours(6 * i) AS start, count(*) AS n FROM events, (SELECT unnest(range(4)) AS i) GROUP BY 1")
def stream_sliding_counts(s, d):
    got = streams.run_to_store(streams.windowed_counts(_stream(s, d), [], F.window("time", "1 day", "6 hours")))
    return got.select(F.to_timestamp_ntz(F.date_format("start", "yyyy-MM-dd HH:mm:ss")).alias("start"), "n")


@query(
    "WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),"
    " s AS (SELECT user_id, ts, sum(b) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, count(*) AS n FROM (SELECT DISTINCT user_id, k FROM s) GROUP BY user_id"
)
def stream_session_counts(s, d):
    """Sessions of each user, closed by a gap of 30 minutes."""
    got = streams.run_to_store(streams.windowed_counts(_stream(s, d), ["user_id"], F.session_window("time", "30 minutes")))
    return got.groupBy("user_id").agg(one().alias("n"))


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events WHERE CAST(ts AS DATE) < (SELECT max(CAST(ts AS DATE)) FROM events) GROUP BY ALL")
def stream_late_rows(s, d):
    """Append mode, all days, a day at a time, and the first day once more at the end: what the watermark lets through."""
    path, extra = _by_day(s, d), fresh_path(s, "late")
    days = s.read.schema(_EVENT + ", day date").parquet(path)
    order = [r["day"] for r in days.select("day").distinct().orderBy("day").collect()]  # a row for each day
    for i, day in enumerate([*order, order[0]]):
        days.where(F.col("day") == day).drop("day").coalesce(1).write.mode("append").parquet(f"{extra}/part={i}")
    stream = s.readStream.schema(_EVENT + ", part int").option("maxFilesPerTrigger", 1).option("latestFirst", False).parquet(extra)
    got = streams.run_to_store(streams.windowed_counts(stream, ["event_type"], F.window("time", "1 day")), "append")
    return got.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("SELECT event_id AS pid FROM events")
def stream_distinct_requests(s, d):
    """Every request sent twice, answered once."""
    st = _stream(s, d).withColumn("twice", F.explode(F.array(F.lit(0), F.lit(1)))).withColumnRenamed("pid", "qid")
    got = streams.run_to_store(streams.distinct_requests(st, "60 days").select("qid"), "append")
    return got.select(F.col("qid").alias("pid"))


def _knn_sql(where: str, k: int, columns: str, points: str = "TRUE") -> str:
    own = _EVENTS3
    return (
        f"WITH a AS ({own}), d AS (SELECT q.pid AS qid, p.pid, (p.c0 - q.c0) * (p.c0 - q.c0) + (p.c1 - q.c1) * (p.c1 - q.c1) + (p.c2 - q.c2) * (p.c2 - q.c2) AS d2 FROM a p, a q WHERE q.{where} AND p.{points}),"
        f" r AS (SELECT *, CAST(row_number() OVER (PARTITION BY qid ORDER BY d2, pid) AS INT) AS rank FROM d) SELECT {columns} FROM r WHERE rank <= {k}"
    ).replace("p.TRUE", "TRUE")


@query(_knn_sql("pid % 20 = 0", 5, "qid, rank, pid, d2"))
def stream_knn_replay(s, d):
    """Queries that arrive as a stream give the batch answer."""
    ps = P.events3(s, d)
    layout = build_layout(ps, 8)
    out, asked = fresh_path(s, "answers"), fresh_path(s, "asked")
    ps.sample_queries(20, 0).repartition(3).write.parquet(asked)
    q = s.readStream.schema("qid long, c0 double, c1 double, c2 double").option("maxFilesPerTrigger", 1).parquet(asked)
    streams.stream_knn(q, layout, 5, out, fresh_path(s, "checkpoint")).awaitTermination()
    return s.read.schema("qid long, rank int, pid long, d2 double, dist double, batch int").parquet(out).select("qid", "rank", "pid", "d2")


def _rebuilt(s: SparkSession, d: str, every: int) -> streams.RebuildingIndex:
    path = fresh_path(s, "arriving")
    P.events3(s, d).positions().withColumn("part", F.pmod("pid", F.lit(7))).write.partitionBy("part").parquet(path)
    index = streams.RebuildingIndex(s, 3, 8, fresh_path(s, "index"), streams.RebuildPolicy(every))
    for i in range(7):  # one batch for each folder, as a stream would bring them
        index.add(s.read.parquet(f"{path}/part={i}"), i)
    return index


@query(_knn_sql("pid % 20 = 0", 5, "qid, rank, pid, d2"))
def stream_rebuild_knn(s, d):
    """Between rebuilds: the tree's answer and the delta's."""
    index = _rebuilt(s, d, 3)
    return index.knn(P.events3(s, d).sample_queries(20, 0), 5).select("qid", "rank", "pid", "d2")


@query("SELECT CAST(row_number() OVER (ORDER BY b) AS INT) AS version, CAST(b AS INT) AS batch, (SELECT count(*) FROM events WHERE event_id % 7 <= b) AS points FROM (VALUES (0), (3), (6)) AS v(b)")
def stream_rebuild_versions(s, d):
    index = _rebuilt(s, d, 3)
    return s.createDataFrame([v[:3] for v in index.versions], "version int, batch int, points long")


@query(_knn_sql("pid < 3", 4, "qid, rank, pid, d2"))
def stream_continuous_knn(s, d):
    """The running answers of three standing queries, as the last update of each leaves them."""
    ps = P.events3(s, d)
    asked = ps.positions().where("pid < 3").withColumnRenamed("pid", "qid")
    s.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    updates = streams.continuous_knn(_stream(s, d).select("pid", "c0", "c1", "c2"), asked, 3, 4)
    out = fresh_path(s, "running")
    updates.writeStream.outputMode("update").option("checkpointLocation", fresh_path(s, "checkpoint")).trigger(availableNow=True).foreachBatch(lambda b, i: b.withColumn("batch", F.lit(i)).write.mode("append").parquet(out)).start().awaitTermination()
    got = s.read.schema("qid long, rank int, pid long, d2 double, batch long").parquet(out)
    last = got.withColumn("_l", F.max("batch").over(Window.partitionBy("qid")))
    return last.where("batch = _l").select("qid", "rank", "pid", "d2")


@query("SELECT day, count(*) AS n FROM (SELECT date_trunc('day', ts) AS day FROM events) GROUP BY day")
def stream_cell_counts(s, d):
    """Counts by cell and day add up to the day's."""
    tree = build_layout(P.events3(s, d), 8).tree
    got = streams.run_to_store(streams.windowed_cell_counts(_stream(s, d), tree, "1 day"))
    return got.groupBy(F.to_timestamp_ntz(F.date_format("start", "yyyy-MM-dd HH:mm:ss")).alias("day")).agg(F.sum("n").alias("n"))


@query(_knn_sql("pid % 20 = 0", 5, "qid, rank, pid, d2"))
def layout_reload_knn(s, d):
    """Saved, loaded, searched."""
    from orthant.operators.layout import SpatialLayout

    ps, path = P.events3(s, d), fresh_path(s, "stored")
    build_layout(ps, 8).save(path)
    return Knn(SpatialLayout.load(s, path), ps.sample_queries(20, 0), 5).neighbors().select("qid", "rank", "pid", "d2")


@query(_knn_sql("pid % 20 = 0", 5, "qid, rank, pid, d2"))
def sql_knn_view(s, d):
    ps = P.events3(s, d)
    ps.sample_queries(20, 0).createOrReplaceTempView("orthant_queries")
    surface.knn_view(s, build_layout(ps, 8), "orthant_queries", 5, "orthant_answers")
    return s.sql("SELECT qid, rank, pid, d2 FROM orthant_answers")


@query(_knn_sql("pid % 20 = 0", 5, "qid, rank, pid, d2").replace("value AS c1", "value + 1 AS c1"))
def knn_time_step(s, d):
    """A later state of all points, moved along one axis, under a tree of its own."""
    moved = P.events3(s, d).positions().withColumn("c1", F.col("c1") + 1)
    ps = PointSet(written(moved, "step"), 3)
    return Knn(build_layout(ps, 8), ps.sample_queries(20, 0), 5).neighbors().select("qid", "rank", "pid", "d2")
