"""SQL that grows the partition tree of a point set and searches it: the oracle of cells, boxes and requests.

It holds for the default split policy, a power of two of cells, and sets whose most varying dimension splits evenly enough, so
that no second dimension is tried. Node n has the children 2n + 1 and 2n + 2.
"""

from __future__ import annotations

_HASHED = "(pid % 2147483648 * 2654435761) % 4294967296"


def _pick(dims: int, dim: str) -> str:
    return "CASE " + dim + "".join(f" WHEN {i} THEN c{i}" for i in range(dims)) + " END"


def tree(points: str, dims: int, cells: int, per_cell: int = 256, local: int = 1024) -> str:
    """CTEs: a (points), d{n} (dim) and b{n} (split) of inner nodes, leaf (points with cell), box (cell, n, l{i}, h{i})."""
    own = ", ".join(f"c{i}" for i in range(dims))
    out = [f"a AS MATERIALIZED ({points})", "p0 AS (SELECT * FROM a)", f"s0 AS MATERIALIZED (SELECT pid, {own}, row_number() OVER (ORDER BY {_HASHED}, pid) AS h FROM a QUALIFY h <= {per_cell * cells})"]
    for n in range(cells - 1):
        spreads = " UNION ALL ".join(f"SELECT {i} AS dim, var_pop(c{i}) FILTER (WHERE r <= {local}) AS x, max(c{i}) - min(c{i}) AS w FROM r{n}" for i in range(dims))
        value = _pick(dims, f"(SELECT dim FROM d{n})")
        out += [
            f"r{n} AS (SELECT *, row_number() OVER (ORDER BY h) AS r FROM s{n})",
            f"d{n} AS MATERIALIZED (SELECT dim FROM ({spreads}) WHERE w > 0 ORDER BY x DESC, dim LIMIT 1)",
            f"e{n} AS MATERIALIZED (SELECT DISTINCT {value} AS e FROM s{n})",
            f"v{n} AS MATERIALIZED (SELECT {value} AS v FROM p{n})",
            f"b{n} AS MATERIALIZED (SELECT e AS split FROM (SELECT e, count(*) FILTER (WHERE v < e) AS below, count(*) AS n FROM e{n}, v{n} GROUP BY e) WHERE below > 0 AND below < n ORDER BY abs(below / n - 0.5), e LIMIT 1)",
        ]
        for child, side in ((2 * n + 1, "<"), (2 * n + 2, ">=")):
            out += [f"{k}{child} AS MATERIALIZED (SELECT * FROM {k}{n} WHERE {value} {side} (SELECT split FROM b{n}))" for k in ("p", "s")]
    out.append("leaf AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT *, CAST({i} AS INT) AS cell FROM p{cells - 1 + i}" for i in range(cells)) + ")")
    sides = ", ".join(f"min(c{i}) AS l{i}, max(c{i}) AS h{i}" for i in range(dims))
    out.append(f"box AS MATERIALIZED (SELECT cell, count(*) AS n, {sides} FROM leaf GROUP BY cell)")
    return ", ".join(out)


def nodes(cells: int) -> str:
    """SELECT of the nodes' table, after the CTEs of tree."""
    rows = []
    for n in range(2 * cells - 1):
        level, inner = (n + 1).bit_length() - 1, n < cells - 1
        want, left, right, cell = cells >> level, 2 * n + 1 if inner else -1, 2 * n + 2 if inner else -1, -1 if inner else n - cells + 1
        dim, split = (f"(SELECT dim FROM d{n})", f"(SELECT split FROM b{n})") if inner else ("-1", "0.0")
        rows.append(f"SELECT CAST({n} AS BIGINT) AS node_id, CAST({level} AS INT) AS level, CAST({dim} AS INT) AS dim, CAST({split} AS DOUBLE) AS split, CAST({left} AS BIGINT) AS left, CAST({right} AS BIGINT) AS right, {str(not inner).lower()} AS is_leaf, CAST({cell} AS INT) AS cell_id, CAST({want} AS INT) AS cells")
    return " UNION ALL ".join(rows)


def _distance(dims: int) -> str:
    return " + ".join(f"(p.c{i} - q.c{i}) * (p.c{i} - q.c{i})" for i in range(dims))


def _box_distance(dims: int) -> str:
    gap = "greatest(b.l{0} - q.c{0}, 0.0::DOUBLE, q.c{0} - b.h{0})"
    return " + ".join(f"{gap.format(i)} * {gap.format(i)}" for i in range(dims))


def search(dims: int, queries: str, k: int) -> str:
    """CTEs after those of tree: q (queries with owner), own (candidates of the owner), r (radius), req (requests), far (their candidates)."""
    d2 = _distance(dims)
    return (
        f"q AS MATERIALIZED (SELECT pid AS qid, cell AS owner, * EXCLUDE (pid, cell) FROM leaf WHERE {queries}),"
        f" own AS MATERIALIZED (SELECT q.qid, p.pid, p.cell, {d2} AS d2 FROM leaf p JOIN q ON p.cell = q.owner QUALIFY row_number() OVER (PARTITION BY q.qid ORDER BY d2, p.pid) <= {k}),"
        f" r AS MATERIALIZED (SELECT qid, CASE WHEN count(*) = {k} THEN max(d2) ELSE 'inf'::DOUBLE END AS r2 FROM own GROUP BY qid),"
        f" req AS MATERIALIZED (SELECT q.*, r.r2, b.cell FROM q JOIN r USING (qid) JOIN box b ON b.cell <> q.owner AND {_box_distance(dims)} <= r.r2),"
        f" far AS MATERIALIZED (SELECT q.qid, p.pid, p.cell, {d2} AS d2 FROM leaf p JOIN req q ON p.cell = q.cell WHERE {d2} <= q.r2 QUALIFY row_number() OVER (PARTITION BY q.qid, p.cell ORDER BY d2, p.pid) <= {k}),"
        f" best AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY d2, pid) AS rank FROM (SELECT * FROM own UNION ALL SELECT * FROM far) QUALIFY rank <= {k}),"
        " told AS MATERIALIZED (SELECT qid, CAST(1 + count(req.cell) AS INT) AS cells_contacted, CAST(count(req.cell) AS INT) AS remote_cells FROM q LEFT JOIN req USING (qid) GROUP BY qid),"
        " won AS MATERIALIZED (SELECT qid, CAST(count(*) FILTER (WHERE best.cell <> q.owner) AS INT) AS remote_in_answer FROM best JOIN q USING (qid) GROUP BY qid)"
    )
