"""DuckDB SQL for the workloads: nets, facilities, objects and exact distances rebuilt from raw tables by formula.

Nothing here is shared with the engine. Distances are found by recursion over (facility, vertex)
with a bound that no k nearest facility exceeds; ``guarded`` turns a bound that binds into an error.
"""

from __future__ import annotations


def grid_ctes(name: str = "thinned") -> str:
    """n, vertices, edges, arcs of a grid net."""
    if name == "wide":
        src, key, detour = "orders", "o_orderkey", "10 * CAST(floor(o_totalprice / 10000) AS BIGINT)"
    else:
        src, key, detour = "part", "p_partkey", "0" if name == "lattice" else "10 * CAST(p_size AS BIGINT)"
    keep = "true" if name == "lattice" else "(g.i % s = 0 OR (g.i * 2654435761) % 3 <> 0)"
    return f"""
n AS (SELECT count(*) AS n, CAST(ceil(sqrt(count(*))) AS BIGINT) AS s FROM {src}),
g AS (SELECT CAST({key} AS BIGINT) AS i, CAST({detour} AS BIGINT) AS detour FROM {src}),
vertices AS (SELECT i AS v, (i % s) * 1000 + (i * 7919) % 401 AS x, (i // s) * 1000 + (i * 104729) % 401 AS y FROM g, n),
pairs AS (
  SELECT 2 * g.i AS eid, g.i AS u, g.i + 1 AS v, detour FROM g, n WHERE g.i % s < s - 1 AND g.i + 1 < n.n
  UNION ALL SELECT 2 * g.i + 1, g.i, g.i + s, detour FROM g, n WHERE g.i + s < n.n AND {keep}),
edges AS (
  SELECT eid, u, p.v AS v, CAST(ceil(sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE))) AS BIGINT) + detour AS w
  FROM pairs p JOIN vertices a ON a.v = p.u JOIN vertices b ON b.v = p.v),
arcs AS (SELECT u AS src, v AS dst, w FROM edges UNION ALL SELECT v, u, w FROM edges)"""


def irregular_ctes() -> str:
    """The net of the embeddings' first two components."""
    return """
n AS (SELECT count(*) AS n, 1 AS s FROM embeddings),
vertices AS (SELECT CAST(vec_id AS BIGINT) AS v, CAST(round(CAST(embedding[1] AS DOUBLE) * 100000) AS BIGINT) AS x, CAST(round(CAST(embedding[2] AS DOUBLE) * 100000) AS BIGINT) AS y FROM embeddings),
near AS (
  SELECT a, b FROM (SELECT a.v AS a, b.v AS b, row_number() OVER (PARTITION BY a.v ORDER BY (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y), b.v) AS rk
                    FROM vertices a JOIN vertices b ON a.v <> b.v) WHERE rk <= 3
  UNION ALL SELECT v, b FROM (SELECT v, lead(v) OVER (ORDER BY x, v) AS b FROM vertices) WHERE b IS NOT NULL),
pairs AS (SELECT DISTINCT least(a, b) AS u, greatest(a, b) AS v FROM near),
edges AS (
  SELECT u * 1048576 + p.v AS eid, u, p.v AS v, greatest(1, CAST(ceil(sqrt(CAST((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) AS DOUBLE))) AS BIGINT)) AS w
  FROM pairs p JOIN vertices a ON a.v = p.u JOIN vertices b ON b.v = p.v),
arcs AS (SELECT u AS src, v AS dst, w FROM edges UNION ALL SELECT v, u, w FROM edges)"""


def net_ctes(name: str = "thinned") -> str:
    return irregular_ctes() if name == "irregular" else grid_ctes(name)


SITES = "sites AS (SELECT DISTINCT (CAST(s_suppkey AS BIGINT) * 7919) % n.n AS q FROM supplier, n)"
CORNER = "corner AS (SELECT CAST(p_partkey AS BIGINT) AS q FROM part, n WHERE p_partkey % s < 10 AND p_partkey // s < 10)"
FACILITIES = {
    "all": "facilities AS (SELECT v AS f, x, y FROM vertices)",
    "tenth": "facilities AS (SELECT v AS f, x, y FROM vertices WHERE v % 10 = 0 OR v IN (SELECT q FROM sites))",
    "sites": "facilities AS (SELECT v AS f, x, y FROM vertices WHERE v IN (SELECT q FROM sites))",
}
INCIDENT = """
inc AS (SELECT a, eid, w, row_number() OVER (PARTITION BY a ORDER BY eid) - 1 AS slot, count(*) OVER (PARTITION BY a) AS degree
        FROM (SELECT u AS a, eid, w FROM edges UNION ALL SELECT v, eid, w FROM edges))"""
_RAW = {
    "orders": "SELECT CAST(o_orderkey AS BIGINT) AS m, (CAST(o_orderkey AS BIGINT) * 48271) % n.n AS a, o_orderkey // n.n AS p, CAST(round(o_totalprice * 100) AS BIGINT) AS z FROM orders, n",
    "events": "SELECT CAST(event_id AS BIGINT) AS m, (CAST(event_id AS BIGINT) * 48271) % n.n AS a, event_id // n.n AS p, CAST(round(value * 100) AS BIGINT) AS z FROM events, n",
    "lineitem": """SELECT m, (m * 48271) % n.n AS a, m // n.n AS p, CAST(round(l_extendedprice * 100) AS BIGINT) AS z
      FROM (SELECT *, (CAST(l_orderkey AS BIGINT) * 8 + l_linenumber) * 64 + row_number() OVER (PARTITION BY l_orderkey, l_linenumber ORDER BY l_extendedprice, l_partkey, l_suppkey) - 1 AS m FROM lineitem), n""",
    "updates": """SELECT CAST(user_id AS BIGINT) AS m, (CAST(user_id AS BIGINT) * 48271 + event_id * 16807) % n.n AS a, event_id // n.n AS p,
      CAST(round(value * 100) AS BIGINT) AS z, ts, CAST(event_id AS BIGINT) AS event_id FROM events, n""",
    "latest": """SELECT m, a, p, z FROM (SELECT *, row_number() OVER (PARTITION BY m ORDER BY ts DESC, event_id DESC) AS rn FROM (
      SELECT CAST(user_id AS BIGINT) AS m, (CAST(user_id AS BIGINT) * 48271 + event_id * 16807) % n.n AS a, event_id // n.n AS p,
      CAST(round(value * 100) AS BIGINT) AS z, ts, event_id FROM events, n WHERE ts <= TIMESTAMP '2024-01-16 00:00:00')) WHERE rn = 1""",
}


def objects_ctes(kind: str = "orders") -> str:
    extra = ", ts, event_id" if kind == "updates" else ""
    return f"""{INCIDENT},
raw AS ({_RAW[kind]}),
objects AS (SELECT m, inc.eid AS eid, z % inc.w AS off{extra} FROM raw JOIN inc ON inc.a = raw.a AND inc.slot = raw.p % inc.degree)"""


def dist_cte(bound: int | None = 6000, seeds: str = "SELECT f, f AS v, CAST(0 AS BIGINT) AS d FROM facilities") -> str:
    """Shortest distances from all seeds up to the bound."""
    limit = f"AND t.d + a.w <= {bound}" if bound is not None else ""
    return f"""
dist(f, v, d) USING KEY (f, v) AS (
  {seeds}
  UNION
  SELECT t.f, a.dst, min(t.d + a.w) FROM dist t JOIN arcs a ON a.src = t.v LEFT JOIN recurring.dist r ON r.f = t.f AND r.v = a.dst
  WHERE (r.d IS NULL OR t.d + a.w < r.d) {limit} GROUP BY t.f, a.dst)"""


OBJECT_DISTANCE = """
ends AS (SELECT m, e.u AS v, off AS x FROM objects JOIN edges e USING (eid) UNION ALL SELECT m, e.v, w - off FROM objects JOIN edges e USING (eid)),
od AS (SELECT m, f, min(x + d) AS d FROM ends JOIN dist USING (v) GROUP BY m, f)"""


def knn_cte(k: int, ties: str = "by_id") -> str:
    rank = "row_number() OVER (PARTITION BY m ORDER BY d, f)" if ties == "by_id" else "rank() OVER (PARTITION BY m ORDER BY d)"
    return f"{OBJECT_DISTANCE},\nknn AS (SELECT m, f, d, CAST(rk AS INTEGER) AS rk FROM (SELECT *, {rank} AS rk FROM od) WHERE rk <= {k})"


def prefix(net: str = "thinned", fac: str = "all", objects: str | None = "orders", k: int | None = 10, bound: int | None = 6000, ties: str = "by_id", extra: str = "") -> str:
    """``WITH RECURSIVE`` and all tables up to ``knn(m, f, d, rk)``."""
    parts = [net_ctes(net), SITES]
    if net != "irregular":
        parts.append(CORNER)
    parts.append(FACILITIES[fac])
    if objects:
        parts.append(objects_ctes(objects))
    if k is not None:
        parts += [dist_cte(bound), knn_cte(k, ties)]
    if extra:
        parts.append(extra)
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n"


ANSWERS = "answers AS (SELECT q, m, d AS net_dist, rk FROM knn JOIN sites ON q = f)"


def candidates_cte(batch: str = "sites", ends: bool = False, k: int = 10) -> str:
    """``own(q, v, d)``: vertices with a query of the batch among their k nearest; ``tested(q, m, cnt)``: the objects on
    roads at these, with the facilities in the circle around each that just holds the query by its better end."""
    return f"""own AS (SELECT f AS q, v, d FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY d, f) AS rk FROM dist) JOIN {batch} ON q = f WHERE rk <= {k}),
roads AS (SELECT q, eid, any_value(w) AS w, min(du) AS du, min(dv) AS dv FROM (
  SELECT q, eid, w, d AS du, NULL AS dv FROM own JOIN edges e ON e.u = own.v UNION ALL SELECT q, eid, w, NULL, d FROM own JOIN edges e ON e.v = own.v) GROUP BY q, eid),
held AS (SELECT q, m, eid, off, CAST(least(du + off, dv + w - off) AS DOUBLE) * 1.000001 AS r FROM objects JOIN roads USING (eid)),
spots AS (SELECT q, m, r, a.x + (b.x - a.x) * (CAST(off AS DOUBLE) / w) AS px, a.y + (b.y - a.y) * (CAST(off AS DOUBLE) / w) AS py
  FROM held JOIN edges e USING (eid) JOIN vertices a ON a.v = e.u JOIN vertices b ON b.v = e.v),
celled AS (SELECT *, unnest(generate_series(CAST(floor((px - r) / 4000) AS BIGINT), CAST(floor((px + r) / 4000) AS BIGINT))) AS cx FROM spots),
tested AS (SELECT q, m, count(f) AS cnt FROM celled JOIN facilities ON x // 4000 = cx AND y BETWEEN py - r AND py + r AND (x - px) * (x - px) + (y - py) * (y - py) <= r * r GROUP BY q, m)"""
