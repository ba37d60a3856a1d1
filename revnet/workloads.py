"""The experiment workloads as queries over the given tables, each with its DuckDB SQL."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass
from functools import cached_property, partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles as O
from .functions.tables import register_rknn
from .metrics import run_stats
from .network import RoadNetwork
from .operators import baselines as B
from .operators.batch import BatchRun, as_pairs, batch_rknn, in_waves, monochromatic, rknn, run_batch
from .operators.count_tree import build_count_tree, range_count, range_search
from .operators.distance import located, network_distance
from .operators.flood import object_knn, vertex_knn
from .operators.halo import TiledNetwork, halo_knn, tile_network
from .operators.regions import influence_region, safe_slack
from .operators.snapshot import order_assignment, shortage, snapshot
from .operators.tiles import tile_knn
from .plans.options import FAITHFUL, RknnOptions
from .plans.storage import stored
from .sources import tables as T

Query = Callable[[SparkSession, str], DataFrame]


@dataclass
class Setting:
    """One experiment setting: a network, facilities, a batch and objects over the tables of ``sf_dir``."""

    spark: SparkSession
    sf_dir: str
    net_name: str = "thinned"
    fac_kind: str = "all"
    obj_kind: str = "orders"

    @cached_property
    def net(self) -> RoadNetwork:
        return T.network(self.spark, self.sf_dir, self.net_name).materialized()

    @cached_property
    def n(self) -> int:
        return self.net.vertices.count()

    @cached_property
    def sites(self) -> DataFrame:
        return stored(T.query_sites(self.spark, self.sf_dir, self.n), "sites")

    @cached_property
    def facilities(self) -> DataFrame:
        return stored(T.facilities(self.net, self.fac_kind, None if self.fac_kind == "all" else self.sites), "facilities")

    @cached_property
    def tiled(self) -> TiledNetwork:
        return tile_network(self.net, self.facilities)

    def labels(self, k: int = 10) -> DataFrame:
        return stored(halo_knn(self.tiled, k), "labels")

    @cached_property
    def objects(self) -> DataFrame:
        return stored(T.moving_objects(self.spark, self.sf_dir, self.net, self.obj_kind, self.n), "objects")

    def objects_near(self, vertices: DataFrame) -> DataFrame:
        """The objects anchored at ``vertices(v)``, not stored."""
        return T.moving_objects(self.spark, self.sf_dir, self.net, self.obj_kind, self.n, vertices)

    def batch(self, options: RknnOptions | None = None, queries: DataFrame | None = None, **kw) -> DataFrame:
        return self.run(options, queries, **kw).result

    def run(self, options: RknnOptions | None = None, queries: DataFrame | None = None, objects: DataFrame | None = None, **kw) -> BatchRun:
        q, m = self.sites if queries is None else queries, self.objects if objects is None else objects
        return run_batch(self.net, self.facilities, q, m, options or RknnOptions(plan="flood"), tiled=self.tiled, **kw)


def _answers(df: DataFrame) -> DataFrame:
    return df.select("q", "m", "net_dist")


_PAIRS = O.prefix(extra=O.ANSWERS)
_PLAIN = f"{_PAIRS} SELECT q, m, net_dist FROM answers"


def net_vertices(spark, d):
    return Setting(spark, d).net.vertices


def net_edges(spark, d):
    return Setting(spark, d).net.edges


def net_degree_profile(spark, d):
    deg = Setting(spark, d).net.arcs.groupBy("src").agg(F.count(F.lit(1)).alias("degree"), F.sum("w").alias("road"))
    return deg.groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"), F.sum("road").cast("long").alias("road"))


def net_sizes(spark, d):
    out = None
    for name in ("lattice", "thinned", "wide", "irregular"):
        s = Setting(spark, d, name)
        row = s.net.edges.agg(F.lit(name).alias("net"), F.count(F.lit(1)).alias("edges"), F.sum("w").cast("long").alias("road")).withColumn("vertices", F.lit(s.n).cast("long"))
        out = row if out is None else out.unionByName(row)
    return out


def objects_placed(spark, d):
    return Setting(spark, d).objects


def objects_located(spark, d):
    s = Setting(spark, d)
    return located(s.objects, s.net).select("m", F.round("px").cast("long").alias("px"), F.round("py").cast("long").alias("py"))


def sssp_from_sites(spark, d):
    s = Setting(spark, d)
    return network_distance(s.net, s.sites.select(F.col("q").alias("s"), F.col("q").alias("v"), F.lit(0).cast("long").alias("d")), 12000)


def vertex_knn_k10(spark, d):
    s = Setting(spark, d)
    return vertex_knn(s.net, s.facilities, 10)


def vertex_knn_halo(spark, d):
    s = Setting(spark, d)
    return halo_knn(s.tiled, 10)


def object_knn_k10(spark, d):
    s = Setting(spark, d)
    return object_knn(s.objects, s.net, s.labels(), 10)


def rknn_single(spark, d):
    s = Setting(spark, d)
    return rknn(s.net, s.facilities, 0, s.objects, RknnOptions(ranks=True), tiled=s.tiled)


def batch_rknn_default(spark, d):
    return Setting(spark, d).batch(RknnOptions(plan="auto")).select("q", "m", "net_dist")


def batch_rknn_expand(spark, d, options: RknnOptions = RknnOptions(plan="expand")):
    return _answers(Setting(spark, d).batch(options))


def batch_rknn_region(spark, d):
    return _answers(Setting(spark, d).batch(RknnOptions(plan="region")))


def batch_rknn_ties(spark, d):
    return Setting(spark, d).batch(RknnOptions(plan="region", ties="inclusive", ranks=True))


def batch_rknn_ranks(spark, d):
    return Setting(spark, d).batch(RknnOptions(plan="expand", ranks=True))


def batch_rknn_waves(spark, d):
    s = Setting(spark, d)
    return _answers(in_waves(s.net, s.facilities, s.sites, s.objects, 3, RknnOptions(plan="expand"), tiled=s.tiled))


def batch_rknn_pairs(spark, d):
    s = Setting(spark, d)
    pairs = as_pairs(s.batch(), s.sites)
    return pairs.select("q", "n_members", F.concat_ws(",", F.transform("members", lambda x: x.cast("string"))).alias("members"))


SIZES = (10, 20, 50, 100, 200, 500, 1000)


def _total(run: BatchRun, name: str, value) -> DataFrame:
    """One row of a series: answers, members and their distances."""
    return run.result.agg(F.lit(value).alias(name), F.count(F.lit(1)).alias("answers"), F.countDistinct("m").alias("members"), F.coalesce(F.sum("net_dist"), F.lit(0)).cast("long").alias("dist"))


def _series(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionByName(r)
    return out


def batch_size_sweep(spark, d):
    s = Setting(spark, d)
    labels = s.labels()
    return _series([_total(s.run(RknnOptions(plan="auto"), T.spread_batch(spark, d, s.n, size), vertex_labels=labels), "batch", size) for size in SIZES]).withColumn("batch", F.col("batch").cast("long"))


def _k_series(spark, d, ks: tuple[int, ...]) -> DataFrame:
    s = Setting(spark, d)
    return _series([_total(s.run(RknnOptions(k=k, plan="auto")), "k", k) for k in ks]).withColumn("k", F.col("k").cast("long"))


def k_sweep(spark, d):
    return _k_series(spark, d, (1, 5, 10, 20))


def k_sweep_large(spark, d):
    return _k_series(spark, d, (50, 100))


_OBJECT = RknnOptions(plan="expand", cache_key="object")


def _searched(run: BatchRun) -> DataFrame:
    """Lookups and searches of a run whose answers have been asked for, as one row."""
    return run_stats(run).where(F.col("metric").isin("lookups", "searches")).groupBy().pivot("metric", ["lookups", "searches"]).agg(F.first("value"))


def object_count_sweep(spark, d):
    s, rows = Setting(spark, d), []
    tree = build_count_tree(s.facilities)
    for kind in ("events", "orders", "lineitem"):
        objs = stored(T.moving_objects(spark, d, s.net, kind, s.n), "objects")
        run = s.run(_OBJECT, objects=objs, tree=tree)
        rows.append(_total(run, "objects", kind).crossJoin(F.broadcast(_searched(run))))  # one row each
    return _series(rows)


def _counted(spark, d, variants: dict[str, RknnOptions], queries: str = "sites", keep: tuple[str, ...] = ("lookups", "searches", "hits_per_1000")) -> DataFrame:
    s = Setting(spark, d)
    q = s.sites if queries == "sites" else stored(T.corner_batch(spark, d), "corner")
    tree = build_count_tree(s.facilities)
    rows = []
    for name, o in variants.items():
        run = s.run(o, q, tree=tree)
        rows.append(run_stats(run).where(F.col("metric").isin(*keep)).select(F.lit(name).alias("variant"), "metric", "value"))
        rows.append(run.result.agg(F.lit(name).alias("variant"), F.lit("answers").alias("metric"), F.count(F.lit(1)).alias("value")))
    return _series(rows)


_ONE = RknnOptions(plan="expand", cache_key="object", share=False)


def obo_vs_shared_counts(spark, d):
    return _counted(spark, d, {"shared": _OBJECT, "one_by_one": _ONE})


def obo_vs_shared_clustered(spark, d):
    return _counted(spark, d, {"shared": _OBJECT, "one_by_one": _ONE}, "corner")


def ablation_quick_verify(spark, d):
    return _counted(spark, d, {"full": _OBJECT, "no_quick": RknnOptions(plan="expand", cache_key="object", quick=False)})


_SHAPES = {b: RknnOptions(plan="expand", cache_key="object", bound=b) for b in ("mbc", "mbr", "both")}


def ablation_mbr_mbc(spark, d):
    return _counted(spark, d, _SHAPES)


def tree_nodes_by_shape(spark, d):
    upper = {f"{b}_upper": RknnOptions(plan="expand", cache_key="object", bound=b, count_mode="upper") for b in ("mbc", "mbr")}
    return _counted(spark, d, _SHAPES | upper, keep=("tree_nodes", "lookups", "searches"))


def ablation_rules(spark, d):
    return _counted(spark, d, {"stop": RknnOptions(plan="expand"), "ends": RknnOptions(plan="expand", ends=True)}, keep=("candidates", "labels"))


def labels_by_rules(spark, d):
    """Labels and candidates of every set of pruning rules, none included, for a batch of three."""
    s, rows = Setting(spark, d), []
    labels, q = s.labels(), stored(T.spread_batch(spark, d, s.n, 3), "three")
    for rules in ((), ("path_count",), ("ancestor",), ("stop",), ("stop", "ancestor"), ("stop", "path_count")):
        run = s.run(RknnOptions(plan="expand", rules=rules, ends=True, quick=False), q, vertex_labels=labels)
        name = "+".join(rules) or "none"
        rows.append(run_stats(run).where("metric in ('labels', 'candidates')").select(F.lit(name).alias("rules"), "metric", "value"))
        rows.append(run.result.agg(F.lit(name).alias("rules"), F.lit("answers").alias("metric"), F.count(F.lit(1)).alias("value")))
    return _series(rows)


def batch_clustered(spark, d):
    s = Setting(spark, d)
    return _answers(s.batch(queries=T.corner_batch(spark, d)))


NETS = ("lattice", "thinned", "wide", "irregular")


def networks_compare(spark, d):
    return _series([_total(Setting(spark, d, x).run(RknnOptions(plan="auto")), "net", x) for x in NETS])


def _compared(spark, d, method: Callable[[Setting, DataFrame], DataFrame], sizes: tuple[int, ...] = (10, 100)) -> DataFrame:
    """A baseline on all nets, for batches of several sizes; the largest holds the others, so it alone is answered."""
    rows = []
    for name in NETS:
        s = Setting(spark, d, name)
        batch = stored(T.query_sites(spark, d, s.n, max(sizes)), "batch")
        got = stored(method(s, batch).select("q", "m", "net_dist"), "compared")
        for size in sizes:
            part = got.join(T.query_sites(spark, d, s.n, size), "q", "left_semi")
            rows.append(_total(BatchRun(part, name), "net", name).withColumn("batch", F.lit(size).cast("long")))
    return _series(rows)


def networks_naive(spark, d):
    return _compared(spark, d, lambda s, q: B.naive_rknn(s.net, s.facilities, q, s.objects, 10, tiled=s.tiled))


def networks_hub(spark, d):
    return _compared(spark, d, lambda s, q: B.hub_rknn_widening(s.net, s.facilities, q, s.objects, 10))


def networks_eager(spark, d):
    return _compared(spark, d, lambda s, q: B.eager_expand_rknn(s.net, s.facilities, q, s.objects_near, 10, tiled=s.tiled))


def networks_region(spark, d):
    return _compared(spark, d, lambda s, q: s.batch(RknnOptions(plan="region"), q))


def facility_density(spark, d):
    out = None
    for kind in ("all", "tenth", "sites"):
        r = Setting(spark, d, fac_kind=kind).batch(RknnOptions(k=2, plan="flood"))
        row = r.agg(F.lit(kind).alias("facilities"), F.count(F.lit(1)).alias("answers"), F.countDistinct("m").alias("members"), F.sum("net_dist").cast("long").alias("dist"))
        out = row if out is None else out.unionByName(row)
    return out


def baseline_naive(spark, d):
    s = Setting(spark, d)
    return _answers(B.naive_rknn(s.net, s.facilities, s.sites, s.objects, 10, tiled=s.tiled))


def baseline_hub(spark, d):
    s = Setting(spark, d)
    return _answers(B.hub_rknn_widening(s.net, s.facilities, s.sites, s.objects, 10))


def baseline_eager(spark, d):
    s = Setting(spark, d)
    return _answers(B.eager_expand_rknn(s.net, s.facilities, s.sites, s.objects, 10, tiled=s.tiled))


def baseline_influence(spark, d):
    s = Setting(spark, d)
    region = influence_region(s.net, s.labels(), s.sites, 10)
    hit = s.objects.join(region, "eid").where("off between lo and hi")
    return hit.groupBy("q").agg(F.count(F.lit(1)).alias("members"), F.sum("m").cast("long").alias("ids"))


def baseline_safe_slack(spark, d):
    s = Setting(spark, d)
    return safe_slack(object_knn(s.objects, s.net, s.labels(11), 11), 10)


def baseline_voronoi(spark, d):
    s = Setting(spark, d, fac_kind="tenth")
    return B.network_voronoi(s.net, s.facilities)


def baseline_shortcuts(spark, d):
    s = Setting(spark, d)
    return _answers(B.shortcut_rknn(s.net, [B.grid_cells(s.net, 12000)], s.facilities, s.sites, s.objects, 10))


def baseline_two_level(spark, d):
    s = Setting(spark, d)
    return _answers(B.shortcut_rknn(s.net, [B.grid_cells(s.net, 6000), B.grid_cells(s.net, 18000)], s.facilities, s.sites, s.objects, 10))


def baseline_sequential(spark, d):
    """A baseline asked for the queries of a small batch one after the other."""
    s = Setting(spark, d)
    few = [r.q for r in T.spread_batch(spark, d, s.n, 3).collect()]  # three queries
    return _answers(B.run_sequential(lambda q: B.eager_expand_rknn(s.net, s.facilities, q, s.objects, 10, tiled=s.tiled), few, spark))


def shortcut_distances(spark, d):
    s = Setting(spark, d)
    cells = stored(B.grid_cells(s.net, 12000), "cells")
    return B.overlay_distance(s.net, cells, s.sites.select(F.col("q").alias("s")), bound=12000)


def range_count_circles(spark, d):
    s = Setting(spark, d)
    at = located(s.objects, s.net).select(F.col("m").alias("id"), F.round("px").cast("double").alias("px"), F.round("py").cast("double").alias("py"), (F.col("m") % 3000 + 500).cast("double").alias("r"))
    return range_count(build_count_tree(s.facilities), at).select("id", F.col("cnt").cast("long").alias("cnt"))


def radius_limited(spark, d):
    s = Setting(spark, d)
    o = RknnOptions(plan="expand", max_radius=2500)
    return _answers(s.batch(o)).where("net_dist <= 2500")


def hop_limited(spark, d):
    s = Setting(spark, d)
    return _answers(s.batch(RknnOptions(plan="expand", max_hops=3)))


def range_search_circles(spark, d):
    s = Setting(spark, d)
    at = located(s.objects, s.net).select(F.col("m").alias("id"), F.round("px").cast("double").alias("px"), F.round("py").cast("double").alias("py"), (F.col("m") % 3000 + 500).cast("double").alias("r"))
    return range_search(build_count_tree(s.facilities), at, "both")


def tile_knn_k10(spark, d):
    s = Setting(spark, d)
    return tile_knn(s.net, B.grid_cells(s.net, 12000), s.facilities, 10).select("v", "f", "d", F.col("rk").cast("int").alias("rk"))


def monochromatic_rknn(spark, d):
    return Setting(spark, d).batch(RknnOptions(k=5, exclude_self=True, ranks=True))


def rknn_table_function(spark, d):
    s = Setting(spark, d)
    register_rknn(spark, s.net, s.facilities, s.objects)
    return spark.sql("select site as q, m, net_dist from values (0L), (7L) t(site), lateral rknn_of(site, 10)")


def shortage_report(spark, d):
    s = Setting(spark, d)
    return shortage(s.batch(), T.table(spark, d, "supplier"), T.table(spark, d, "nation"), s.n)


def assignment(spark, d):
    return order_assignment(Setting(spark, d).batch(RknnOptions(plan="region")))


def snapshot_rknn(spark, d):
    s = Setting(spark, d, obj_kind="updates")
    objs = snapshot(s.objects, "2024-01-16 00:00:00")
    return _answers(batch_rknn(s.net, s.facilities, s.sites, objs, RknnOptions(plan="flood")))


def example_delivery(spark, d):
    from .examples import delivery

    net, fac, q, objs = delivery(spark)
    return batch_rknn(net, fac, q, objs, RknnOptions(k=2, plan="expand")).select("q", "m", "net_dist")


def example_prune(spark, d):
    from .examples import pruning

    net, fac, q, objs = pruning(spark)
    return batch_rknn(net, fac, q, objs, RknnOptions(k=1, plan="expand", rules=("stop",))).select("q", "m", "net_dist")


def queries() -> dict[str, Query]:
    out: dict[str, Query] = {f.__name__: f for f in (
        net_vertices, net_edges, net_degree_profile, net_sizes, objects_placed, objects_located, sssp_from_sites, vertex_knn_k10, object_knn_k10, rknn_single,
        batch_rknn_default, batch_rknn_expand, batch_rknn_region, batch_rknn_ties, batch_rknn_pairs, batch_size_sweep, k_sweep, k_sweep_large, object_count_sweep, vertex_knn_halo, batch_rknn_ranks, batch_rknn_waves,
        obo_vs_shared_counts, obo_vs_shared_clustered, ablation_quick_verify, ablation_mbr_mbc, ablation_rules, tree_nodes_by_shape, labels_by_rules, networks_naive, networks_hub, networks_eager, networks_region, batch_clustered, networks_compare, facility_density,
        baseline_naive, baseline_hub, baseline_eager, baseline_influence, baseline_safe_slack, baseline_voronoi, baseline_shortcuts, baseline_two_level, baseline_sequential, shortcut_distances, range_count_circles, range_search_circles,
        radius_limited, hop_limited, tile_knn_k10, monochromatic_rknn, rknn_table_function, shortage_report, snapshot_rknn, example_delivery, example_prune,
    )}
    out["order_assignment"] = assignment
    out["batch_rknn_faithful"] = partial(batch_rknn_expand, options=FAITHFUL)
    out["batch_rknn_rectangles"] = partial(batch_rknn_expand, options=RknnOptions(plan="expand", bound="mbr", cache_key="object"))
    out["batch_rknn_no_quick"] = partial(batch_rknn_expand, options=RknnOptions(plan="expand", quick=False, cache_payload="full_map"))
    return out


_TOTAL = "count(m) AS answers, count(DISTINCT m) AS members, CAST(coalesce(sum(net_dist), 0) AS BIGINT) AS dist"


def _sweep_sql() -> str:
    sizes = " UNION ALL ".join(f"SELECT {b} AS b" for b in SIZES)
    return f"""{O.prefix()}, sizes AS ({sizes}),
picked AS (SELECT DISTINCT b, (CAST(p_partkey AS BIGINT) * 7919) % n.n AS q FROM part, n, sizes WHERE p_partkey < b)
SELECT CAST(b AS BIGINT) AS batch, {_TOTAL} FROM (SELECT b, m, d AS net_dist FROM picked LEFT JOIN knn ON f = q) GROUP BY b"""


def _k_sql(ks: tuple[int, ...], k: int, bound: int) -> str:
    values = " UNION ALL ".join(f"SELECT {x} AS k" for x in ks)
    return f"""{O.prefix(k=k, bound=bound, extra=O.ANSWERS)}, ks AS ({values})
SELECT CAST(k AS BIGINT) AS k, {_TOTAL} FROM answers JOIN ks ON rk <= k GROUP BY k"""


def _counts_sql(variants: dict[str, tuple[str, str]], batch: str = "sites", ends: bool = False) -> str:
    """Lookups, searches, hits and answers from candidates made anew: variant -> (pairs looked up, what is searched)."""
    rows = []
    for name, (where, what) in variants.items():
        head = f"SELECT '{name}' AS variant"
        rows.append(f"""{head}, unnest(['lookups', 'searches', 'hits_per_1000']) AS metric, unnest([l, s, CASE WHEN l > 0 THEN greatest(0, (l - s) * 1000 // l) ELSE 0 END]) AS value
            FROM (SELECT count(*) AS l, {what} AS s FROM tested WHERE {where})""")
        rows.append(f"{head}, 'answers' AS metric, count(*) AS value FROM knn JOIN {batch} ON q = f")
    return f"{O.prefix(extra=O.candidates_cte(batch, ends))} " + " UNION ALL ".join(rows)


_UNSURE, _DISTINCT, _EACH = "cnt > 10", "count(DISTINCT m)", "count(*)"


def _summary(name: str, label: str, **kw) -> str:
    return f"""(SELECT '{label}' AS {name}, count(*) AS answers, count(DISTINCT m) AS members, CAST(sum(net_dist) AS BIGINT) AS dist
FROM ({O.prefix(extra=O.ANSWERS, **kw)} SELECT * FROM answers))"""


def _objects_sql(kind: str) -> str:
    own = "SELECT q, m, d AS net_dist FROM knn JOIN sites ON q = f"
    return f"""(SELECT '{kind}' AS objects, {_TOTAL}, any_value(l) AS lookups, any_value(s) AS searches FROM (
{O.prefix(objects=kind, extra=O.candidates_cte())} SELECT a.*, t.l, t.s FROM ({own}) a, (SELECT count(*) AS l, count(DISTINCT m) AS s FROM tested WHERE {_UNSURE}) t))"""


_BOUNDS = {"irregular": 40000, "wide": 8000}


def _networks_sql(sizes: tuple[int, ...] = (10, 100)) -> str:
    rows = []
    for x in NETS:
        for b in sizes:
            rows.append(f"""(SELECT '{x}' AS net, CAST({b} AS BIGINT) AS batch, {_TOTAL} FROM ({O.prefix(net=x, bound=_BOUNDS.get(x, 6000), extra=O.ANSWERS)}
              SELECT * FROM answers WHERE q IN (SELECT (CAST(s_suppkey AS BIGINT) * 7919) % n.n FROM supplier, n WHERE s_suppkey < {b})))""")
    return " UNION ALL ".join(rows)


def oracle_sql() -> dict[str, str]:
    p, a = O.prefix(k=None), _PAIRS
    seeds = "SELECT q AS f, q AS v, CAST(0 AS BIGINT) AS d FROM sites"
    sssp = "WITH RECURSIVE " + ",\n".join([O.net_ctes(), O.SITES, O.dist_cte(12000, seeds)]) + " SELECT f AS s, v, d FROM dist"
    vk = "row_number() OVER (PARTITION BY v ORDER BY d, f)"
    out = {
        "net_vertices": f"{p} SELECT v, x, y FROM vertices",
        "net_edges": f"{p} SELECT eid, u, v, w FROM edges",
        "net_degree_profile": f"{p} SELECT degree, count(*) AS vertices, CAST(sum(road) AS BIGINT) AS road FROM (SELECT src, count(*) AS degree, sum(w) AS road FROM arcs GROUP BY src) GROUP BY degree",
        "net_sizes": " UNION ALL ".join(
            f"(SELECT * FROM (WITH {O.net_ctes(x)} SELECT '{x}' AS net, count(*) AS edges, CAST(sum(w) AS BIGINT) AS road, CAST((SELECT n FROM n) AS BIGINT) AS vertices FROM edges))"
            for x in ("lattice", "thinned", "wide", "irregular")
        ),
        "objects_placed": f"{p} SELECT m, eid, off FROM objects",
        "objects_located": f"""{p} SELECT m, CAST(round(a.x + (b.x - a.x) * (CAST(off AS DOUBLE) / w)) AS BIGINT) AS px, CAST(round(a.y + (b.y - a.y) * (CAST(off AS DOUBLE) / w)) AS BIGINT) AS py
            FROM objects JOIN edges e USING (eid) JOIN vertices a ON a.v = e.u JOIN vertices b ON b.v = e.v""",
        "sssp_from_sites": sssp,
        "vertex_knn_k10": f"{O.prefix()} SELECT v, f, d, CAST(rk AS INTEGER) AS rk FROM (SELECT *, {vk} AS rk FROM dist) WHERE rk <= 10",
        "vertex_knn_halo": f"{O.prefix()} SELECT v, f, d, CAST(rk AS INTEGER) AS rk FROM (SELECT *, {vk} AS rk FROM dist) WHERE rk <= 10",
        "tile_knn_k10": f"{O.prefix()} SELECT v, f, d, CAST(rk AS INTEGER) AS rk FROM (SELECT *, {vk} AS rk FROM dist) WHERE rk <= 10",
        "object_knn_k10": f"{O.prefix()} SELECT m, f, d, rk FROM knn",
        "rknn_single": f"{O.prefix()} SELECT f AS q, m, d AS net_dist, rk FROM knn WHERE f = 0",
        "batch_rknn_default": _PLAIN, "batch_rknn_expand": _PLAIN, "batch_rknn_region": _PLAIN, "batch_rknn_faithful": _PLAIN,
        "batch_rknn_rectangles": _PLAIN, "batch_rknn_no_quick": _PLAIN,
        "batch_rknn_ties": f"{O.prefix(ties='inclusive', extra=O.ANSWERS)} SELECT q, m, net_dist, rk FROM answers",
        "batch_rknn_pairs": f"{a} SELECT q, count(m) AS n_members, coalesce(string_agg(CAST(m AS VARCHAR), ',' ORDER BY m), '') AS members FROM sites LEFT JOIN answers USING (q) GROUP BY q",
        "batch_size_sweep": _sweep_sql(),
        "k_sweep": _k_sql((1, 5, 10, 20), 20, 8000),
        "k_sweep_large": _k_sql((50, 100), 100, 20000),
        "object_count_sweep": " UNION ALL ".join(_objects_sql(x) for x in ("events", "orders", "lineitem")),
        "batch_rknn_ranks": f"{_PAIRS} SELECT q, m, net_dist, rk FROM answers", "batch_rknn_waves": _PLAIN,
        "obo_vs_shared_counts": _counts_sql({"shared": (_UNSURE, _DISTINCT), "one_by_one": (_UNSURE, _EACH)}),
        "obo_vs_shared_clustered": _counts_sql({"shared": (_UNSURE, _DISTINCT), "one_by_one": (_UNSURE, _EACH)}, "corner"),
        "ablation_quick_verify": _counts_sql({"full": (_UNSURE, _DISTINCT), "no_quick": ("true", _DISTINCT)}),
        "ablation_mbr_mbc": _counts_sql({x: (_UNSURE, _DISTINCT) for x in _SHAPES}),
        "ablation_rules": f"""{O.prefix(extra=O.candidates_cte())}, reached AS (SELECT q, v FROM own UNION SELECT q, a.dst FROM own JOIN arcs a ON a.src = own.v),
            ends_of AS (SELECT DISTINCT q, m FROM reached JOIN edges e ON e.u = reached.v OR e.v = reached.v JOIN objects USING (eid)), c AS (
            SELECT 'stop' AS variant, (SELECT count(*) FROM tested) AS c UNION ALL SELECT 'ends', (SELECT count(*) FROM ends_of))
            SELECT variant, 'candidates' AS metric, c AS value FROM c UNION ALL SELECT variant, 'labels', (SELECT count(*) FROM reached) FROM c UNION ALL SELECT variant, 'answers', (SELECT count(*) FROM knn JOIN sites ON q = f) FROM c""",
        **{f"networks_{x}": _networks_sql() for x in ("naive", "hub", "eager", "region")},
        "hop_limited": f"""{O.prefix(extra=O.candidates_cte())}, hop(q, v, h) AS (SELECT q, q, 0 FROM sites UNION
              SELECT hop.q, a.dst, h + 1 FROM hop JOIN arcs a ON a.src = hop.v JOIN own ON own.q = hop.q AND own.v = a.dst WHERE h < 3),
            near AS (SELECT DISTINCT q, v FROM hop)
            SELECT DISTINCT k.f AS q, k.m AS m, k.d AS net_dist FROM knn k JOIN objects USING (m) JOIN edges e USING (eid) JOIN near ON near.q = k.f AND (near.v = e.u OR near.v = e.v)""",
        "baseline_two_level": _PLAIN, "baseline_shortcuts": _PLAIN, "shortcut_distances": sssp,
        "baseline_sequential": f"{O.prefix()} SELECT f AS q, m, d AS net_dist FROM knn WHERE f IN (SELECT (CAST(p_partkey AS BIGINT) * 7919) % n.n FROM part, n WHERE p_partkey < 3)",
        "range_search_circles": f"""{p}, spot AS (SELECT m AS id, round(a.x + (b.x - a.x) * (CAST(off AS DOUBLE) / w)) AS px, round(a.y + (b.y - a.y) * (CAST(off AS DOUBLE) / w)) AS py,
              CAST(m % 3000 + 500 AS DOUBLE) AS r FROM objects JOIN edges e USING (eid) JOIN vertices a ON a.v = e.u JOIN vertices b ON b.v = e.v)
            SELECT id, f FROM spot JOIN facilities ON x BETWEEN px - r AND px + r AND y BETWEEN py - r AND py + r AND (x - px) * (x - px) + (y - py) * (y - py) <= r * r""",
        "batch_clustered": f"{O.prefix()} SELECT q, m, d AS net_dist FROM knn JOIN corner ON q = f",
        "networks_compare": " UNION ALL ".join(_summary("net", x, net=x, bound=_BOUNDS.get(x, 6000)) for x in NETS),
        "facility_density": " UNION ALL ".join(_summary("facilities", x, fac=x, k=2, bound=None if x == "sites" else 12000) for x in ("all", "tenth", "sites")),
        "baseline_naive": _PLAIN, "baseline_hub": _PLAIN, "baseline_eager": _PLAIN,
        "baseline_influence": f"{a} SELECT q, count(*) AS members, CAST(sum(m) AS BIGINT) AS ids FROM answers GROUP BY q",
        "baseline_safe_slack": f"""{O.prefix(k=11)} SELECT m, max(CASE WHEN rk = 10 THEN d END) AS d_k, max(CASE WHEN rk = 11 THEN d END) AS d_k1,
            max(CASE WHEN rk = 11 THEN d END) - max(CASE WHEN rk = 10 THEN d END) AS twice_slack FROM knn GROUP BY m""",
        "baseline_voronoi": f"{O.prefix(fac='tenth', bound=20000)} SELECT v, f AS owner, d FROM (SELECT *, {vk} AS rk FROM dist) WHERE rk = 1",
        "range_count_circles": f"""{p}, spot AS (SELECT m AS id, round(a.x + (b.x - a.x) * (CAST(off AS DOUBLE) / w)) AS px, round(a.y + (b.y - a.y) * (CAST(off AS DOUBLE) / w)) AS py,
              CAST(m % 3000 + 500 AS DOUBLE) AS r FROM objects JOIN edges e USING (eid) JOIN vertices a ON a.v = e.u JOIN vertices b ON b.v = e.v)
            SELECT id, count(f) AS cnt FROM spot LEFT JOIN facilities ON x BETWEEN px - r AND px + r AND y BETWEEN py - r AND py + r
              AND (x - px) * (x - px) + (y - py) * (y - py) <= r * r GROUP BY id""",
        "radius_limited": f"{a} SELECT q, m, net_dist FROM answers WHERE net_dist <= 2500",
        "monochromatic_rknn": f"""{O.prefix()} SELECT f AS q, v AS m, d AS net_dist, CAST(rk AS INTEGER) AS rk FROM (
            SELECT *, {vk} AS rk FROM dist WHERE f <> v) JOIN sites ON q = f WHERE rk <= 5""",
        "shortage_report": f"""{a}, own AS (SELECT (CAST(s_suppkey AS BIGINT) * 7919) % n.n AS q, min(s_nationkey) AS nk FROM supplier, n GROUP BY 1),
            per AS (SELECT q, count(m) AS answers FROM sites LEFT JOIN answers USING (q) GROUP BY q)
            SELECT n_name AS nation, count(*) AS sites, CAST(sum(answers) AS BIGINT) AS answers, CAST(min(answers) AS BIGINT) AS fewest, CAST(sum(CASE WHEN answers = 0 THEN 1 ELSE 0 END) AS BIGINT) AS empty_sites
            FROM per JOIN own USING (q) JOIN nation ON n_nationkey = nk GROUP BY n_name""",
        "rknn_table_function": f"{O.prefix()} SELECT f AS q, m, d AS net_dist FROM knn WHERE f IN (0, 7)",
        "order_assignment": f"{a} SELECT m, q, net_dist FROM (SELECT *, row_number() OVER (PARTITION BY m ORDER BY net_dist, q) AS r FROM answers) WHERE r = 1",
        "snapshot_rknn": f"{O.prefix(objects='latest', extra=O.ANSWERS)} SELECT q, m, net_dist FROM answers",
        "example_delivery": "SELECT CAST(q AS BIGINT) AS q, CAST(m AS BIGINT) AS m, CAST(d AS BIGINT) AS net_dist FROM (VALUES (1, 1, 1), (1, 2, 1), (2, 1, 3), (3, 3, 3), (3, 4, 1), (4, 2, 3), (4, 3, 1), (4, 4, 3)) t(q, m, d)",
        "example_prune": "SELECT CAST(q AS BIGINT) AS q, CAST(m AS BIGINT) AS m, CAST(d AS BIGINT) AS net_dist FROM (VALUES (0, 1, 6), (0, 3, 2)) t(q, m, d)",
    }
    return out
