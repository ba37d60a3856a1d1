"""The batch reverse k-nearest-neighbour query."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork, validate_inputs
from ..plans.options import RknnOptions
from ..plans.planner import choose_plan
from ..plans.storage import drop_stored, stored
from .count_tree import CountTree, build_count_tree
from .expand import Expansion, expand
from .flood import object_knn, vertex_knn
from .halo import TiledNetwork, halo_knn, tile_network
from .regions import influence_region, region_members, tile_regions
from .verify import DistanceCache, candidates, exact_membership, quick_verify, road_ends


@dataclass
class BatchRun:
    """Answers ``(q, m, net_dist)``, with ``rk`` if asked for, and the tables behind a batch's measures (where the plan has them)."""

    result: DataFrame
    plan: str
    expansion: Expansion | None = None
    candidates: DataFrame | None = None  # (q, m, eid, off, d_ub, cnt, nodes, verdict)
    cache: DistanceCache | None = None
    tables: list = field(default_factory=list)

    def close(self) -> None:
        """Empty the cache and delete the tables of this batch, once its result has been read or written."""
        if self.cache is not None:
            self.cache.clear()
        for t in self.tables + (self.expansion.tables if self.expansion else []):
            drop_stored(t)
        self.tables = []


def run_batch(
    net: RoadNetwork, facilities: DataFrame, queries: DataFrame, objects: DataFrame | Callable[[DataFrame], DataFrame], options: RknnOptions | None = None, tree: CountTree | None = None,
    vertex_labels: DataFrame | None = None, validate: bool = False, admissibility: float | None = None, tiled: TiledNetwork | None = None,
) -> BatchRun:
    """Answer a batch; every plan and option gives the same rows.

    Repeated queries count once, an empty batch or no objects give an empty result, objects that
    reach fewer than k facilities count all of them. ``tree``, ``tiled`` and ``vertex_labels`` may be
    handed in where several batches share the facilities, ``admissibility`` where it is known (else
    one small aggregate finds it, as the circle test needs it on networks with roads shorter than
    straight lines). A hop limit asks for objects on roads at vertices that are so few roads from q,
    over vertices that have q among their k nearest; a radius limit for those at most so far.
    ``objects`` may be a function of vertices ``(v)`` that gives at least the objects on roads with both
    ends among them; an expansion asks it for the roads that it has met alone.
    """
    o = options or RknnOptions()
    if callable(objects) and (validate or o.exclude_self or o.plan != "expand"):
        objects = objects(net.vertices)
    if validate:
        validate_inputs(net, facilities, queries, objects)
    queries = queries.select("q").distinct()
    if o.exclude_self:
        got = monochromatic(net, facilities, queries, o.k, o.ties)
        return BatchRun(got if o.ranks else got.drop("rk"), "flood")
    plan, tiled = o.plan, tiled or tile_network(net, facilities)
    if plan == "auto":
        limited = o.max_radius is not None or o.max_hops is not None
        plan = "expand" if limited else choose_plan(net, facilities, queries, o.k, objects, (tiled.n, tiled.f)).plan
        if plan == "expand" and o.share and o.cache_key == "vertex":
            o = replace(o, quick=False)  # the expansion has met the lists of both ends, so a circle test would save no search
    if plan == "expand":
        return _expand(net, facilities, queries, objects, o, tree, vertex_labels, admissibility, tiled)
    if plan == "region" and vertex_labels is None:
        got = region_members(tile_regions(tiled, queries, o.k, o.ties, o.ranks), objects)
        return BatchRun(got.select("q", "m", F.col("d").alias("net_dist"), *(["rk"] if o.ranks else [])), plan)
    made = []
    if vertex_labels is None:
        vertex_labels = stored(halo_knn(tiled, o.k, o.ties), "vertex-labels")
        made = [vertex_labels]
    if plan == "flood":
        # only roads with a query of the batch in the lists of their ends can hold answers
        near = vertex_labels.where(F.col("rk") <= o.k).withColumnRenamed("f", "q").join(queries, "q", "left_semi").select("v").distinct()
        roads = net.edges.join(near.withColumnRenamed("v", "u"), "u", "left_semi").unionByName(net.edges.join(near, "v", "left_semi").select("u", "eid", "v", "w")).select("eid").distinct()
        roads = stored(roads, "near-roads")
        got = object_knn(objects.join(roads, "eid", "left_semi"), net, vertex_labels, o.k, o.ties).withColumnRenamed("f", "q").join(queries, "q", "left_semi")
        made.append(roads)
    else:
        region = stored(influence_region(net, vertex_labels, queries, o.k, o.ties), "regions")
        got = region_members(region, objects)
        made.append(region)
    return BatchRun(got.select("q", "m", F.col("d").alias("net_dist"), *(["rk"] if o.ranks else [])), plan, tables=made)


def _expand(net, facilities, queries, objects, o: RknnOptions, tree, vertex_labels, admissibility, tiled) -> BatchRun:
    exp = expand(tiled, queries, o.k, o.rules, o.ties, o.share, o.max_radius, o.max_hops, vertex_labels, o.max_rounds)
    limited = o.max_radius is not None or o.max_hops is not None
    met = []
    if callable(objects):
        met = [stored(road_ends(exp.labels, net, o.ends), "road-ends")]
        objects = objects(met[0])
    cand = candidates(exp.labels, objects, net, o.ends)
    if o.max_radius is not None:
        cand = cand.where(F.col("d_ub") <= o.max_radius)
    cache = DistanceCache(net, facilities, o.k, o.ties, o.cache_key, o.cache_payload, tiled)
    if o.share and exp.lists is not None:
        cache.take(exp.lists)
    quick = o.quick and not o.ranks and not limited  # ranks, and distances under a limit, come from exact lists alone
    if quick:
        if admissibility is None:
            admissibility = net.admissibility()
        tree = tree or build_count_tree(facilities, o.tree_fanout, o.leaf_size)
        cand = quick_verify(cand, objects, net, tree, o.k, o.bound, o.count_mode, admissibility)
    else:
        cand = cand.withColumns({"cnt": F.lit(None).cast("long"), "nodes": F.lit(0).cast("long"), "verdict": F.lit("UNKNOWN")})
    cand = stored(cand, "candidates")
    answers = exact_membership(cand.where("verdict = 'UNKNOWN'"), objects, cache, o.share, "stop" not in o.rules).withColumnRenamed("d", "net_dist")
    if o.max_radius is not None:
        answers = answers.where(F.col("net_dist") <= o.max_radius)
    if not o.ranks:
        answers = answers.drop("rk")
    if quick:
        # at a vertex that was left the label is the true distance, so a sure pair's is too
        answers = answers.unionByName(cand.where("verdict = 'YES'").select("q", "m", F.col("d_ub").alias("net_dist")))
    return BatchRun(answers, "expand", exp, cand, cache, [cand, *met])


def batch_rknn(net: RoadNetwork, facilities: DataFrame, queries: DataFrame, objects: DataFrame, options: RknnOptions | None = None, **kw) -> DataFrame:
    """Answers ``(q, m, net_dist)``, with the rank ``rk`` of q among the facilities of m if the options ask for it."""
    return run_batch(net, facilities, queries, objects, options, **kw).result


def rknn(net: RoadNetwork, facilities: DataFrame, q: int, objects: DataFrame, options: RknnOptions | None = None, **kw) -> DataFrame:
    """The batch of one query."""
    one = net.vertices.sparkSession.createDataFrame([(q,)], "q long")
    return batch_rknn(net, facilities, one, objects, options, **kw)


def as_pairs(result: DataFrame, queries: DataFrame) -> DataFrame:
    """``(q, n_members, members)``: every query of the batch with its sorted objects, empty ones included."""
    sets = result.groupBy("q").agg(F.sort_array(F.collect_list("m")).alias("members"))
    empty = F.array().cast("array<long>")
    return queries.select("q").distinct().join(sets, "q", "left").select("q", F.size(F.coalesce("members", empty)).cast("long").alias("n_members"), F.coalesce("members", empty).alias("members"))


def one_by_one(net: RoadNetwork, facilities: DataFrame, query_list: list[int], objects: DataFrame, options: RknnOptions | None = None, **kw) -> DataFrame:
    """The batch as a driver loop of single queries, nothing shared between them; for comparison only."""
    spark, out = net.vertices.sparkSession, None
    for q in query_list:
        run = run_batch(net, facilities, spark.createDataFrame([(q,)], "q long"), objects, replace(options or RknnOptions(), plan="expand"), **kw)
        part = stored(run.result, "one")
        run.close()
        out = part if out is None else out.unionByName(part)
    return out


def in_waves(net: RoadNetwork, facilities: DataFrame, queries: DataFrame, objects: DataFrame, count: int, options: RknnOptions | None = None, **kw) -> DataFrame:
    """The batch in ``count`` waves of queries that lie close together, one after the other; each wave's cache is cleared at its end.

    Bounds the labels and lists that are held at a time; queries of a wave share most.
    """
    from ..plans.batching import waves

    cut = stored(waves(queries, net.vertices, count), "waves")
    kw.setdefault("tiled", tile_network(net, facilities))
    out = None
    for i in range(count):
        run = run_batch(net, facilities, cut.where(F.col("wave") == i).select("q"), objects, options, **kw)
        part = stored(run.result, "wave")
        run.close()
        out = part if out is None else out.unionByName(part)
    return out


def monochromatic(net: RoadNetwork, facilities: DataFrame, queries: DataFrame, k: int, ties: str = "by_id") -> DataFrame:
    """Reverse kNN among the facilities themselves, ``(q, m, net_dist, rk)`` with m a facility other than q."""
    from .flood import knn_of_vertex_objects

    near = knn_of_vertex_objects(net, facilities, k, ties)
    return near.select(F.col("f").alias("q"), F.col("v").alias("m"), F.col("d").alias("net_dist"), "rk").join(queries.select("q").distinct(), "q", "left_semi")
