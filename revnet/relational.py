"""Relational operators around the batch queries, each as a query with DuckDB SQL of the same result."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions.geometry import box_bounds2, cells_of_circle, enclosing_circle
from .operators.distance import located, with_ends
from .operators.nearest import nearest_site
from .operators.snapshot import as_of_positions
from .plans.options import RknnOptions
from .sources import tables as T
from .workloads import Setting

_P = O.prefix(k=None)
_A = O.prefix(extra=O.ANSWERS)
_REGISTRY: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {}


def _query(sql: str | None, name: str | None = None):
    def keep(fn):
        _REGISTRY[name or fn.__name__] = (fn, sql)
        return fn

    return keep


@_query(f"{_P} SELECT v, x + y AS xy FROM vertices")
def op_scan_project(spark, d):
    return Setting(spark, d).net.vertices.select("v", (F.col("x") + F.col("y")).alias("xy"))


@_query(f"{_P} SELECT v, x, y FROM vertices WHERE x BETWEEN 5000 AND 12000 AND y BETWEEN 3000 AND 9000")
def op_filter_bbox(spark, d):
    return T.network(spark, d).vertices.where("x between 5000 and 12000 and y between 3000 and 9000")


@_query(f"{_P} SELECT f FROM facilities WHERE (x - 10000) * (x - 10000) + (y - 10000) * (y - 10000) <= 25000000")
def op_filter_circle(spark, d):
    return T.facilities(T.network(spark, d)).where("(x - 10000) * (x - 10000) + (y - 10000) * (y - 10000) <= 25000000").select("f")


@_query(f"{_P} SELECT src, dst, w FROM arcs")
def op_union_arcs(spark, d):
    return T.network(spark, d).arcs


@_query(f"{_P} SELECT u AS v FROM edges WHERE eid % 2 = 0 INTERSECT SELECT u FROM edges WHERE eid % 2 = 1")
def op_intersect_routes(spark, d):
    e = T.network(spark, d).edges
    return e.where("eid % 2 = 0").select(F.col("u").alias("v")).intersect(e.where("eid % 2 = 1").select("u"))


@_query(f"{_P} SELECT f FROM facilities EXCEPT SELECT u FROM objects JOIN edges USING (eid)")
def op_except_unserved(spark, d):
    s = Setting(spark, d)
    return s.facilities.select("f").exceptAll(with_ends(s.objects, s.net).select(F.col("u").alias("f")).distinct())


@_query(f"{_P} SELECT m, u, v, w - off AS rest FROM objects JOIN edges USING (eid)")
def op_hash_join_edges(spark, d):
    s = Setting(spark, d)
    return s.objects.hint("shuffle_hash").join(s.net.edges, "eid").select("m", "u", "v", (F.col("w") - F.col("off")).alias("rest"))


@_query(f"{_P} SELECT q, x, y FROM sites JOIN vertices ON v = q")
def op_broadcast_join_sites(spark, d):
    s = Setting(spark, d)
    return s.net.vertices.join(F.broadcast(s.sites), F.col("v") == F.col("q")).select("q", "x", "y")  # one row per supplier at most


@_query(f"{_P} SELECT a.src AS a, b.dst AS b, min(a.w + b.w) AS d FROM arcs a JOIN arcs b ON a.dst = b.src WHERE a.src < b.dst GROUP BY a.src, b.dst")
def op_merge_join_arcs(spark, d):
    arcs = Setting(spark, d).net.arcs
    two = arcs.alias("a").hint("merge").join(arcs.alias("b"), F.col("a.dst") == F.col("b.src")).where("a.src < b.dst")
    return two.groupBy(F.col("a.src").alias("a"), F.col("b.dst").alias("b")).agg(F.min(F.col("a.w") + F.col("b.w")).alias("d"))


@_query(f"{_A} SELECT q, count(m) AS answers FROM sites LEFT JOIN answers USING (q) GROUP BY q")
def op_left_join_empty(spark, d):
    s = Setting(spark, d)
    return s.sites.join(s.batch(), "q", "left").groupBy("q").agg(F.count("m").alias("answers"))


@_query(f"{O.prefix(fac='tenth', k=None)} SELECT coalesce(q, f) AS id, q IS NOT NULL AS is_site, f IS NOT NULL AS is_tenth FROM sites FULL JOIN (SELECT f FROM facilities WHERE f % 10 = 0) t ON q = f")
def op_full_join_sites(spark, d):
    s = Setting(spark, d)
    tenth = s.facilities.where("f % 10 = 0").select("f")
    j = s.sites.join(tenth, F.col("q") == F.col("f"), "full")
    return j.select(F.coalesce("q", "f").alias("id"), F.col("q").isNotNull().alias("is_site"), F.col("f").isNotNull().alias("is_tenth"))


@_query(f"{_P} SELECT m FROM objects WHERE EXISTS (SELECT 1 FROM edges JOIN sites ON q = u OR q = edges.v WHERE edges.eid = objects.eid)")
def op_semi_hits(spark, d):
    s = Setting(spark, d)
    near = s.net.edges.select("eid", F.explode(F.array("u", "v")).alias("q")).join(s.sites, "q", "left_semi")
    return s.objects.join(near, "eid", "left_semi").select("m")


@_query(f"{_P} SELECT m FROM objects WHERE NOT EXISTS (SELECT 1 FROM edges JOIN sites ON q = u OR q = edges.v WHERE edges.eid = objects.eid)")
def op_anti_misses(spark, d):
    s = Setting(spark, d)
    near = s.net.edges.select("eid", F.explode(F.array("u", "v")).alias("q")).join(s.sites, "q", "left_semi")
    return s.objects.join(near, "eid", "left_anti").select("m")


_AT = "spot AS (SELECT m, CAST(round(a.x + (b.x - a.x) * (CAST(off AS DOUBLE) / w)) AS BIGINT) AS px, CAST(round(a.y + (b.y - a.y) * (CAST(off AS DOUBLE) / w)) AS BIGINT) AS py FROM objects JOIN edges e USING (eid) JOIN vertices a ON a.v = e.u JOIN vertices b ON b.v = e.v)"


def _spots(s: Setting) -> DataFrame:
    return located(s.objects, s.net).select("m", F.round("px").cast("long").alias("px"), F.round("py").cast("long").alias("py"))


@_query(f"""{_P}, {_AT}, c AS (SELECT m, v, (px - x) * (px - x) + (py - y) * (py - y) AS d2 FROM spot JOIN sites ON true JOIN vertices ON v = q)
SELECT m, v AS q, d2 FROM (SELECT *, row_number() OVER (PARTITION BY m ORDER BY d2, v) AS r FROM c) WHERE r = 1""")
def op_theta_join_nearest(spark, d):
    s = Setting(spark, d)
    sites = s.net.vertices.join(s.sites, F.col("v") == F.col("q"), "left_semi")
    return nearest_site(_spots(s), sites).select("m", "q", "d2")


@_query(f"""{_P}, {_AT} SELECT m, count(f) AS cnt FROM spot LEFT JOIN facilities ON x BETWEEN px - 1500 AND px + 1500 AND y BETWEEN py - 1500 AND py + 1500
AND (x - px) * (x - px) + (y - py) * (y - py) <= 2250000 GROUP BY m""")
def op_range_join_grid(spark, d):
    s = Setting(spark, d)
    side = 1500.0
    c = _spots(s).withColumn("c", F.explode(cells_of_circle(F.col("px"), F.col("py"), F.lit(1500), side))).select("m", "px", "py", "c.cx", "c.cy")
    p = s.facilities.select("f", "x", "y", F.floor(F.col("x") / side).alias("cx"), F.floor(F.col("y") / side).alias("cy"))
    hit = c.join(p, ["cx", "cy"]).where("(x - px) * (x - px) + (y - py) * (y - py) <= 2250000")
    return s.objects.select("m").join(hit.groupBy("m").agg(F.count(F.lit(1)).alias("cnt")), "m", "left").select("m", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"))


@_query(f"{_P} SELECT m, objects.eid AS eid, off FROM objects JOIN edges USING (eid) WHERE off BETWEEN w // 4 AND w // 2")
def op_interval_join_offsets(spark, d):
    s = Setting(spark, d)
    r = s.net.edges.selectExpr("eid", "w div 4 as lo", "w div 2 as hi")
    return s.objects.join(r, "eid").where("off between lo and hi").select("m", "eid", "off")


_MARKS = "marks AS (SELECT unnest(generate_series(TIMESTAMP '2024-01-05', TIMESTAMP '2024-01-25', INTERVAL 5 DAY)) AS mark)"


@_query(f"""{O.prefix(objects='updates', k=None)}, {_MARKS}, j AS (SELECT m, mark, eid, off, row_number() OVER (PARTITION BY m, mark ORDER BY ts DESC, event_id DESC) AS r
FROM objects JOIN marks ON ts <= mark) SELECT m, CAST(epoch(mark) AS BIGINT) AS mark, eid, off FROM j WHERE r = 1""")
def op_asof_position(spark, d):
    s = Setting(spark, d, obj_kind="updates")
    marks = spark.sql("select explode(sequence(timestamp '2024-01-05', timestamp '2024-01-25', interval 5 days)) as mark")
    return as_of_positions(s.objects, marks).select("m", F.unix_seconds("mark").alias("mark"), "eid", "off")


@_query(f"""{_A} SELECT a.q AS a, b.q AS b, count(*) AS shared FROM answers a JOIN answers b ON a.m = b.m AND a.q < b.q GROUP BY a.q, b.q""")
def op_self_overlap(spark, d):
    # an object has at most k sites, so the pairs per object are bounded by k squared
    r = Setting(spark, d).batch().groupBy("m").agg(F.sort_array(F.collect_list("q")).alias("s"))
    pairs = F.flatten(F.transform("s", lambda x, i: F.transform(F.slice("s", i + 2, F.size("s")), lambda y: F.struct(x.alias("a"), y.alias("b")))))
    return r.select(F.explode(pairs).alias("p")).groupBy("p.a", "p.b").agg(F.count(F.lit(1)).alias("shared"))


@_query(f"{_P} SELECT eid, count(*) AS objects, CAST(sum(off) AS BIGINT) AS offs, max(off) AS far FROM objects GROUP BY eid")
def op_group_edge_load(spark, d):
    return Setting(spark, d).objects.groupBy("eid").agg(F.count(F.lit(1)).alias("objects"), F.sum("off").cast("long").alias("offs"), F.max("off").alias("far"))


@_query(f"{_A} SELECT q, count(DISTINCT eid) AS roads FROM answers JOIN objects USING (m) GROUP BY q")
def op_group_distinct(spark, d):
    s = Setting(spark, d)
    return s.batch().join(s.objects, "m").groupBy("q").agg(F.countDistinct("eid").alias("roads"))


@_query(f"{_P} SELECT eid, count(*) AS objects FROM objects GROUP BY eid HAVING count(*) >= 8")
def op_having_busy(spark, d):
    return Setting(spark, d).objects.groupBy("eid").agg(F.count(F.lit(1)).alias("objects")).where("objects >= 8")


_OWN = "own AS (SELECT (CAST(s_suppkey AS BIGINT) * 7919) % n.n AS q, min(s_nationkey) AS nk FROM supplier, n GROUP BY 1), a2 AS (SELECT n_name, r_name, m, net_dist FROM answers JOIN own USING (q) JOIN nation ON n_nationkey = nk JOIN region ON r_regionkey = n_regionkey)"


def _by_nation(spark, d) -> DataFrame:
    s = Setting(spark, d)
    own = T.table(spark, d, "supplier").groupBy(F.expr(f"(cast(s_suppkey as long) * 7919) % {s.n}").alias("q")).agg(F.min("s_nationkey").alias("n_nationkey"))
    geo = own.join(T.table(spark, d, "nation"), "n_nationkey").join(T.table(spark, d, "region"), F.col("r_regionkey") == F.col("n_regionkey"))
    return s.batch().join(geo.select("q", "n_name", "r_name"), "q")


@_query(f"{_A}, {_OWN} SELECT coalesce(r_name, 'ALL') AS region, coalesce(n_name, 'ALL') AS nation, count(*) AS answers, CAST(grouping(n_name) AS INTEGER) AS g FROM a2 GROUP BY ROLLUP (r_name, n_name)")
def op_rollup_nation_region(spark, d):
    r = _by_nation(spark, d).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("answers"), F.grouping("n_name").cast("int").alias("g"))
    return r.select(F.coalesce("r_name", F.lit("ALL")).alias("region"), F.coalesce("n_name", F.lit("ALL")).alias("nation"), "answers", "g")


@_query(f"""{_A}, {_OWN} SELECT coalesce(r_name, 'ALL') AS region, coalesce(CAST(near AS VARCHAR), 'ALL') AS near, count(*) AS answers
FROM (SELECT r_name, CASE WHEN net_dist < 1500 THEN 'near' ELSE 'far' END AS near FROM a2) GROUP BY CUBE (r_name, near)""")
def op_cube_segments(spark, d):
    r = _by_nation(spark, d).withColumn("near", F.when(F.col("net_dist") < 1500, "near").otherwise("far")).cube("r_name", "near").agg(F.count(F.lit(1)).alias("answers"))
    return r.select(F.coalesce("r_name", F.lit("ALL")).alias("region"), F.coalesce("near", F.lit("ALL")).alias("near"), "answers")


@_query(f"{_A}, {_OWN} SELECT coalesce(r_name, 'ALL') AS region, coalesce(n_name, 'ALL') AS nation, count(*) AS answers FROM a2 GROUP BY GROUPING SETS ((r_name), (n_name), ())")
def op_grouping_sets(spark, d):
    _by_nation(spark, d).createOrReplaceTempView("answers_by_nation")
    return spark.sql("select coalesce(r_name, 'ALL') region, coalesce(n_name, 'ALL') nation, count(*) answers from answers_by_nation group by grouping sets ((r_name), (n_name), ())")


@_query(f"{_A} SELECT q, count(*) FILTER (rk = 1) AS first, count(*) FILTER (rk = 2) AS second, count(*) FILTER (rk = 3) AS third FROM answers WHERE rk <= 3 GROUP BY q")
def op_pivot_variant(spark, d):
    p = Setting(spark, d).batch(RknnOptions(plan="region", ranks=True)).where("rk <= 3").groupBy("q").pivot("rk", [1, 2, 3]).count().na.fill(0)
    return p.select("q", F.col("1").alias("first"), F.col("2").alias("second"), F.col("3").alias("third"))


@_query(f"{_A} SELECT m, q, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM answers WINDOW w AS (PARTITION BY m ORDER BY net_dist // 500, q), v AS (PARTITION BY m ORDER BY net_dist // 500)")
def op_rank_ties(spark, d):
    w = Window.partitionBy("m").orderBy(F.expr("net_dist div 500"))
    full = Window.partitionBy("m").orderBy(F.expr("net_dist div 500"), "q")
    return Setting(spark, d).batch().select("m", "q", F.row_number().over(full).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"))


@_query(f"{O.prefix()} SELECT m, rk, coalesce(lead(d) OVER (PARTITION BY m ORDER BY rk) - d, -1) AS gap FROM knn")
def op_lead_slack(spark, d):
    s = Setting(spark, d)
    from .operators.flood import object_knn

    near = object_knn(s.objects, s.net, s.labels(), 10)
    return near.select("m", "rk", F.expr("coalesce(lead(d) over (partition by m order by rk) - d, -1L)").alias("gap"))


@_query(f"""{_A}, c AS (SELECT rk, count(*) AS n FROM answers GROUP BY rk) SELECT rk, n, coalesce(n * 1000 // lag(n) OVER (ORDER BY rk), -1) AS ratio FROM c""")
def op_lag_growth(spark, d):
    c = Setting(spark, d).batch(RknnOptions(plan="region", ranks=True)).groupBy("rk").agg(F.count(F.lit(1)).alias("n"))  # k rows
    return c.select("rk", "n", F.expr("coalesce(n * 1000 div lag(n) over (order by rk), -1L)").alias("ratio"))


_U = O.prefix(objects="updates", k=None)


@_query(f"{_U} SELECT event_id, CAST(sum(off) OVER (PARTITION BY m ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM objects")
def op_rows_frame(spark, d):
    o = Setting(spark, d, obj_kind="updates").objects
    return o.select("event_id", F.sum("off").over(Window.partitionBy("m").orderBy("ts", "event_id").rowsBetween(-4, 0)).cast("long").alias("s"))


@_query(f"{_U} SELECT event_id, count(*) OVER (PARTITION BY m ORDER BY t RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS t FROM objects)")
def op_range_frame(spark, d):
    o = Setting(spark, d, obj_kind="updates").objects.withColumn("t", F.unix_seconds("ts"))
    return o.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("m").orderBy("t").rangeBetween(-86400, 0)).alias("day"))


@_query(f"{O.prefix()} SELECT v, d AS kth FROM (SELECT *, row_number() OVER (PARTITION BY v ORDER BY d, f) AS rk FROM dist) WHERE rk = 10")
def op_nth_kth_distance(spark, d):
    s = Setting(spark, d)
    lab = s.labels()
    w = Window.partitionBy("v").orderBy("d", "f").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return lab.select("v", F.nth_value("d", 10).over(w).alias("kth")).where("kth is not null").distinct()


@_query(f"{_A} SELECT q, answers FROM (SELECT q, count(*) AS answers FROM answers GROUP BY q) ORDER BY answers DESC, q LIMIT 10")
def op_topk_sites(spark, d):
    return Setting(spark, d).batch().groupBy("q").agg(F.count(F.lit(1)).alias("answers")).orderBy(F.desc("answers"), "q").limit(10)


@_query(f"{O.prefix()} SELECT m, f, d FROM knn WHERE rk <= 3")
def op_topk_per_group(spark, d):
    s = Setting(spark, d)
    from .operators.flood import knn

    return knn(s.objects, s.net, s.facilities, 3).select("m", "f", "d")


@_query(f"{_A} SELECT q, m, row_number() OVER (PARTITION BY q ORDER BY net_dist DESC, m) AS place FROM answers")
def op_sort_multi(spark, d):
    w = Window.partitionBy("q").orderBy(F.desc("net_dist"), "m")
    return Setting(spark, d).batch().select("q", "m", F.row_number().over(w).cast("long").alias("place")).orderBy("q", "place")


@_query(f"{_A} SELECT q, string_agg(CAST(m AS VARCHAR), '|' ORDER BY m) AS members FROM answers GROUP BY q")
def op_members_string(spark, d):
    r = Setting(spark, d).batch().groupBy("q").agg(F.sort_array(F.collect_list("m")).alias("l"))
    return r.select("q", F.concat_ws("|", F.transform("l", lambda x: x.cast("string"))).alias("members"))


@_query(f"{_A} SELECT q, count(*) AS n, min(m) AS lo, max(m) AS hi, CAST(sum(CASE WHEN m % 2 = 0 THEN 1 ELSE 0 END) AS BIGINT) AS even FROM answers GROUP BY q")
def op_array_ops(spark, d):
    r = Setting(spark, d).batch().groupBy("q").agg(F.collect_list("m").alias("l"))
    return r.select("q", F.size("l").cast("long").alias("n"), F.array_min("l").alias("lo"), F.array_max("l").alias("hi"), F.size(F.filter("l", lambda x: x % 2 == 0)).cast("long").alias("even"))


@_query(f"{O.prefix()} SELECT m, f, d FROM knn WHERE rk <= 2")
def op_map_distances(spark, d):
    s = Setting(spark, d)
    from .operators.flood import knn

    maps = knn(s.objects, s.net, s.facilities, 2).groupBy("m").agg(F.map_from_entries(F.collect_list(F.struct("f", "d"))).alias("x"))
    return maps.select("m", F.explode("x").alias("f", "d"))


@_query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def op_json_k(spark, d):
    return T.table(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@_query(f"{_P} SELECT q, 'site-' || lpad(CAST(q AS VARCHAR), 8, '0') AS label, upper('v' || CAST(q AS VARCHAR)) AS code FROM sites")
def op_string_labels(spark, d):
    s = Setting(spark, d).sites
    return s.select("q", F.format_string("site-%s", F.lpad(F.col("q").cast("string"), 8, "0")).alias("label"), F.upper(F.concat(F.lit("v"), F.col("q").cast("string"))).alias("code"))


@_query("SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS hour, count(*) AS updates FROM events GROUP BY 1")
def op_date_buckets(spark, d):
    return T.table(spark, d, "events").groupBy(F.unix_seconds(F.date_trunc("hour", F.col("ts").cast("timestamp"))).alias("hour")).agg(F.count(F.lit(1)).alias("updates"))


@_query(f"""{_P} SELECT v, CAST(pow(greatest(5000 - x, 0, x - 9000), 2) + pow(greatest(5000 - y, 0, y - 9000), 2) AS BIGINT) AS lo,
CAST(pow(greatest(abs(x - 5000), abs(x - 9000)), 2) + pow(greatest(abs(y - 5000), abs(y - 9000)), 2) AS BIGINT) AS hi FROM vertices""")
def op_math_bounds(spark, d):
    p = T.network(spark, d).vertices.withColumns({"x0": F.lit(5000), "x1": F.lit(9000), "y0": F.lit(5000), "y1": F.lit(9000)})
    lo, hi = box_bounds2(F.col("x"), F.col("y"), "x0", "y0", "x1", "y1")
    return p.select("v", lo.cast("long").alias("lo"), hi.cast("long").alias("hi"))


@_query(f"{_P} SELECT m, CASE WHEN off = 0 THEN 'START' WHEN off * 2 < w THEN 'FIRST' ELSE coalesce(nullif('LAST', ''), '?') END AS half FROM objects JOIN edges USING (eid)")
def op_case_null(spark, d):
    s = Setting(spark, d)
    half = F.when(F.col("off") == 0, "START").when(F.col("off") * 2 < F.col("w"), "FIRST").otherwise(F.coalesce(F.nullif(F.lit("LAST"), F.lit("")), F.lit("?")))
    return s.objects.join(s.net.edges, "eid").select("m", half.alias("half"))


def views(spark, d, k: int = 10) -> Setting:
    """Register road_vertices, road_edges, facilities, sites, objects, vertex_knn and rknn_result for SQL."""
    s = Setting(spark, d)
    for name, df in (("road_vertices", s.net.vertices), ("road_edges", s.net.edges), ("facilities", s.facilities), ("sites", s.sites), ("objects", s.objects)):
        df.createOrReplaceTempView(name)
    lab = s.labels(k)
    lab.createOrReplaceTempView("vertex_knn")
    s.batch(vertex_labels=lab).createOrReplaceTempView("rknn_result")
    return s


@_query(f"{_A} SELECT f FROM facilities WHERE EXISTS (SELECT 1 FROM answers WHERE q = f AND net_dist < 1000)")
def op_exists_subquery(spark, d):
    views(spark, d)
    return spark.sql("select f from facilities where exists (select 1 from rknn_result r where r.q = f and r.net_dist < :near)", {"near": 1000})


@_query(f"{_A}, c AS (SELECT q, count(*) AS n FROM answers GROUP BY q), t AS (SELECT avg(n) AS a FROM c) SELECT q, n FROM c, t WHERE n > a")
def op_cte_chain(spark, d):
    views(spark, d)
    return spark.sql("with c as (select q, count(*) n from rknn_result group by q), t as (select avg(n) a from c) select q, n from c cross join t where n > a")


@_query(f"{O.prefix()} SELECT q, f, d FROM (SELECT v AS q, f, d, row_number() OVER (PARTITION BY v ORDER BY d, f) AS rk FROM dist WHERE f <> v) JOIN sites USING (q) WHERE rk <= 3")
def op_lateral_nearest(spark, d):
    views(spark, d)
    return spark.sql("select q, n.f, n.d from sites, lateral (select f, d from vertex_knn k where k.v = sites.q and k.f <> sites.q order by d, f limit 3) n")


@_query(None)
def op_udf_circle(spark, d):
    p = T.network(spark, d).vertices.groupBy(F.expr("v div 50").alias("g"))
    return p.agg(enclosing_circle(F.col("x"), F.col("y")).alias("c")).select("g", F.col("c")[0].alias("cx"), F.col("c")[1].alias("cy"), F.col("c")[2].alias("cr"))


@_query(f"{_P} SELECT v // 50 AS g, count(*) AS inside FROM vertices GROUP BY 1")
def op_udaf_enclosing(spark, d):
    p = T.network(spark, d).vertices.withColumn("g", F.expr("v div 50"))
    c = p.groupBy("g").agg(enclosing_circle(F.col("x"), F.col("y")).alias("c"))
    return p.join(c, "g").where("sqrt(pow(x - c[0], 2) + pow(y - c[1], 2)) <= c[2]").groupBy("g").agg(F.count(F.lit(1)).alias("inside"))


@_query(f"{_P} SELECT q, cx, cy FROM sites JOIN vertices ON v = q, (SELECT unnest(generate_series(-50, 200)) AS cx), (SELECT unnest(generate_series(-50, 200)) AS cy) WHERE cx BETWEEN CAST(floor((x - 2500) / 1000.0) AS BIGINT) AND CAST(floor((x + 2500) / 1000.0) AS BIGINT) AND cy BETWEEN CAST(floor((y - 2500) / 1000.0) AS BIGINT) AND CAST(floor((y + 2500) / 1000.0) AS BIGINT)")
def op_udtf_cells(spark, d):
    from .functions.tables import register

    register(spark)
    s = Setting(spark, d)
    s.net.vertices.join(s.sites, F.col("v") == F.col("q")).select("q", "x", "y").createOrReplaceTempView("site_points")
    return spark.sql("select q, c.cx, c.cy from site_points, lateral expand_cells(x, y, 2500L, 1000L) c")


@_query("WITH RECURSIVE " + ",\n".join([O.net_ctes()]) + """, h(v, hop) USING KEY (v) AS (SELECT CAST(0 AS BIGINT), 0 UNION
SELECT a.dst, min(t.hop + 1) FROM h t JOIN arcs a ON a.src = t.v LEFT JOIN recurring.h r ON r.v = a.dst WHERE r.v IS NULL AND t.hop < 6 GROUP BY a.dst) SELECT v, hop FROM h""")
def op_recursive_hops(spark, d):
    T.network(spark, d).materialized().arcs.createOrReplaceTempView("road_arcs")
    return spark.sql(
        "with recursive h(v, hop) as (select 0L, 0 union all select a.dst, h.hop + 1 from h join road_arcs a on a.src = h.v where h.hop < 6) select v, min(hop) as hop from h group by v"
    )


def queries() -> dict:
    return {k: v[0] for k, v in _REGISTRY.items()}


def oracle_sql() -> dict[str, str]:
    return {k: v[1] for k, v in _REGISTRY.items() if v[1]}
