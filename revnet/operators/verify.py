"""Candidates of an expansion, the quick circle test and the exact test behind a shared cache."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import drop_stored, stored
from .count_tree import CountTree, range_count
from .distance import object_seeds
from .flood import object_knn, ranked
from .halo import TiledNetwork, search_sources, tile_network, vertex_sources


def candidates(labels: DataFrame, objects: DataFrame, net: RoadNetwork, ends: bool = True) -> DataFrame:
    """``(q, m, eid, off, d_ub)``: objects on roads at reached vertices, once per query, by the better end.

    Without ``ends`` only roads at vertices count that the expansion left: an object whose way to q
    passes a vertex that lacks q among its k nearest lacks it too. Roads meet the labels first, so the
    objects are read once and joined by their road alone.
    """
    at = labels if ends or "go" not in labels.columns else labels.where("go")
    e, none = net.edges, F.lit(None).cast("long")
    by_u = at.select("q", F.col("v").alias("u"), F.col("d").alias("du")).join(e, "u").select("q", "eid", "w", "du", none.alias("dv"))
    by_v = at.select("q", "v", F.col("d").alias("dv")).join(e, "v").select("q", "eid", "w", none.alias("du"), "dv")
    roads = by_u.unionByName(by_v).groupBy("q", "eid", "w").agg(F.min("du").alias("du"), F.min("dv").alias("dv"))
    best = F.least(F.col("du") + F.col("off"), F.col("dv") + F.col("w") - F.col("off"))  # nulls are skipped
    return objects.select("m", "eid", "off").join(roads, "eid").select("q", "m", "eid", "off", best.alias("d_ub"))


def road_ends(labels: DataFrame, net: RoadNetwork, ends: bool = True) -> DataFrame:
    """``(v)``: both ends of all roads whose objects ``candidates`` takes."""
    at = (labels if ends or "go" not in labels.columns else labels.where("go")).select("v").distinct()
    e = net.edges.select("u", "v")
    met = e.join(at, "v", "left_semi").unionByName(e.join(at.withColumnRenamed("v", "u"), "u", "left_semi").select("u", "v"))
    return met.select(F.explode(F.array("u", "v")).alias("v")).distinct()


def quick_verify(cand: DataFrame, objects: DataFrame, net: RoadNetwork, tree: CountTree, k: int, bound: str = "mbc", count_mode: str = "exact", admissibility: float = 1.0) -> DataFrame:
    """``cand`` with the facilities in the circle around each object that just holds q, and a verdict.

    At most k of them prove that q is among the k nearest (YES); more prove nothing (UNKNOWN). The
    circle is widened by a millionth, and by the network's admissibility if roads can be shorter
    than straight lines; both only ever count more.
    """
    wide = 1.000001 / min(1.0, admissibility)
    c = cand if "off" in cand.columns else cand.join(objects.select("m", "eid", "off"), "m")
    e = net.located_edges()
    part = F.col("off") / F.col("w")
    c = c.join(e.drop("u", "v"), "eid").select(
        *(F.col(x) for x in c.columns), (F.col("ux") + (F.col("vx") - F.col("ux")) * part).alias("px"), (F.col("uy") + (F.col("vy") - F.col("uy")) * part).alias("py"),
        (F.col("d_ub") * F.lit(wide)).alias("r"),
    )
    got = range_count(tree, c.withColumn("id", F.struct(*c.columns[:-3])), bound, count_mode)
    return got.select("id.*", "cnt", "nodes").withColumn("verdict", F.when(F.col("cnt") <= k, "YES").otherwise("UNKNOWN"))


@dataclass
class DistanceCache:
    """kNN lists of objects (or of edge ends) that a batch has asked for; empty at the start of a batch.

    ``have(key, complete_k)`` lists what is complete, ``lists(key, f, d, rk)`` the facilities. A
    facility that a complete list lacks is not among the k nearest, so such a lookup is a hit too.
    An expansion hands in the lists of vertices that it has met (``take``); ``filled`` counts the
    searches that the cache itself ran.
    """

    net: RoadNetwork
    facilities: DataFrame
    k: int
    ties: str = "by_id"
    key: str = "vertex"
    payload: str = "knn"
    tiled: TiledNetwork | None = None
    have: DataFrame | None = None
    lists: DataFrame | None = None
    filled: int = 0
    tables: list = field(default_factory=list)

    def _tiled(self) -> TiledNetwork:
        if self.tiled is None:
            self.tiled = tile_network(self.net, self.facilities)
        return self.tiled

    def _keys(self, objects: DataFrame) -> DataFrame:
        return objects.select(F.col("m").alias("key")) if self.key == "object" else object_seeds(objects, self.net).select(F.col("v").alias("key"))

    def _add(self, have: DataFrame, lists: DataFrame) -> None:
        have = have.withColumn("complete_k", F.lit(self.k))
        self.lists = lists if self.lists is None else self.lists.unionByName(lists)
        self.have = have if self.have is None else self.have.unionByName(have)

    def take(self, lists: DataFrame) -> None:
        """Complete ``lists(v, f, d, rk)`` of vertices that the cache does not hold; ignored by a cache of objects."""
        if self.key == "vertex":
            named = lists.withColumnRenamed("v", "key")
            self._add(named.select("key").distinct(), named)

    def missing(self, objects: DataFrame) -> DataFrame:
        """Keys of the objects that the cache does not hold yet."""
        keys = self._keys(objects).distinct()
        return keys if self.have is None else keys.join(self.have, "key", "left_anti")

    def hits(self, objects: DataFrame) -> DataFrame:
        """Keys of the objects that the cache holds."""
        keys = self._keys(objects).distinct()
        return keys.where("1 = 0") if self.have is None else keys.join(self.have, "key", "left_semi")

    def fill(self, objects: DataFrame) -> int:
        """Search the missing keys, all at once; returns how many searches that took."""
        miss = stored(self.missing(objects), "misses")
        n = miss.count()
        self.tables.append(miss)
        if not n:
            return 0
        if self.key == "object":
            asked = miss if self.have is None else objects.join(miss.select(F.col("key").alias("m")), "m", "left_semi")
            sources = object_sources((objects if self.have is None else asked).select("m", F.lit(-1).cast("long").alias("b"), "eid", "off").dropDuplicates(["m"]), self.net)
        else:
            sources = vertex_sources(miss.select(F.col("key").alias("v")))
        new = stored(search_sources(self._tiled(), sources, self.k, self.ties, self.payload == "full_map").select(F.col("a").alias("key"), "f", "d", "rk"), "cache")
        self._add(miss, new)
        self.tables.append(new)
        self.filled += n
        return n

    def search_pairs(self, pairs: DataFrame) -> DataFrame:
        """``(q, m, f, d, rk)``: a search of its own for each pair ``(q, m, eid, off)``; nothing is kept."""
        sources = stored(object_sources(pairs.select("m", F.col("q").alias("b"), "eid", "off"), self.net), "pair-sources")
        self.tables.append(sources)
        self.filled += sources.count()
        return search_sources(self._tiled(), sources, self.k, self.ties).select(F.col("b").alias("q"), F.col("a").alias("m"), "f", "d", "rk")

    def lookup(self, objects: DataFrame) -> DataFrame:
        """kNN of the objects ``(m, f, d, rk)`` from complete lists."""
        if self.lists is None:
            return objects.selectExpr("m", "m as f", "m as d", "1 as rk").where("1 = 0")
        if self.key == "object":
            return objects.select("m").distinct().join(self.lists.withColumnRenamed("key", "m"), "m").where(F.col("rk") <= self.k).select("m", "f", "d", "rk")
        return object_knn(objects, self.net, self.lists.where(F.col("rk") <= self.k if self.ties == "by_id" else F.lit(True)).withColumnRenamed("key", "v"), self.k, self.ties)

    def export(self) -> DataFrame:
        """``(key, distances)``: each key's map from facility to distance."""
        return self.lists.groupBy("key").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("f", "d")))).alias("distances"))

    def clear(self) -> None:
        """Forget everything; a new batch starts with an empty cache."""
        for t in self.tables:
            drop_stored(t)
        self.have = self.lists = None
        self.tables, self.filled = [], 0


def object_sources(objects: DataFrame, net: RoadNetwork) -> DataFrame:
    """Sources of a search for ``objects(m, b, eid, off)``: both ends of each object's road."""
    o = objects.join(net.edges, "eid")
    return o.select(F.col("m").alias("a"), "b", F.col("u").alias("v1"), F.col("off").alias("d1"), F.col("v").alias("v2"), (F.col("w") - F.col("off")).alias("d2"))


def exact_membership(unknown: DataFrame, objects: DataFrame, cache: DistanceCache, share: bool = True, far: bool = False) -> DataFrame:
    """Of the pairs ``unknown(q, m)``, those in which q is among the k nearest of m, with distance and rank.

    With ``share`` an object is searched at most once whatever the number of its queries, without
    once for each. Where many pairs lie ``far`` apart, lists of ends are looked through for q by road before those of objects are made:
    what is among the k nearest of an object is among those of an end of its road.
    """
    if "off" not in unknown.columns:
        unknown = unknown.join(objects.select("m", "eid", "off"), "m")
    if not share:
        return cache.search_pairs(unknown).where("f = q").select("q", "m", "d", "rk")
    asked = stored(unknown.select("m", "eid", "off").distinct(), "asked")
    cache.tables.append(asked)
    cache.fill(asked)
    if far and cache.key == "vertex" and cache.lists is not None:
        near = cache.lists.where(F.col("rk") <= cache.k).select(F.col("key").alias("v"), F.col("f").alias("q")).join(unknown.select("q").distinct(), "q", "left_semi")
        e = cache.net.edges
        roads = e.join(near, "v").select("q", "eid").unionByName(e.join(near.withColumnRenamed("v", "u"), "u").select("q", "eid")).distinct()
        unknown = stored(unknown.select("q", "m", "eid", "off").join(stored(roads, "asked-roads"), ["q", "eid"], "left_semi"), "asked-near")
        cache.tables.append(unknown)
        asked = unknown.select("m", "eid", "off").distinct()
    return unknown.select("q", "m").join(cache.lookup(asked).withColumnRenamed("f", "q"), ["q", "m"]).select("q", "m", "d", "rk")


def quick_reject(cand: DataFrame, objects: DataFrame, net: RoadNetwork, landmarks: DataFrame, facilities: DataFrame, k: int) -> DataFrame:
    """Pairs of ``cand(q, m)`` that landmark bounds rule out: k facilities surely nearer to m than q.

    ``landmarks(s, v, d)`` are distances from a few landmarks. A facility's upper bound is the best
    way through a landmark, q's lower bound the largest difference of its and m's distances.
    """
    seeds = object_seeds(objects.join(cand.select("m").distinct(), "m", "left_semi"), net)
    lm = seeds.join(landmarks.select("s", "v", F.col("d").alias("dl")), "v").groupBy("m", "s").agg(F.min(F.col("d") + F.col("dl")).alias("dm"))
    fl = landmarks.join(facilities.select(F.col("f").alias("v")), "v", "left_semi").select("s", F.col("v").alias("f"), F.col("d").alias("df"))
    best = ranked(fl.withColumnRenamed("df", "d"), "s", k + 1, "by_id").select("s", "f", F.col("d").alias("df"))
    upper = lm.join(best, "s").groupBy("m", "f").agg(F.min(F.col("dm") + F.col("df")).alias("d"))
    kth = ranked(upper, "m", k + 1, "by_id").select("m", "f", F.col("d").alias("ub"))
    low = cand.select("q", "m").join(lm, "m").join(fl.withColumnRenamed("f", "q"), ["q", "s"]).groupBy("q", "m").agg(F.max(F.abs(F.col("dm") - F.col("df"))).alias("lb"))
    sure = low.join(kth, "m").where("ub < lb and f <> q").groupBy("q", "m").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= k)
    return sure.select("q", "m")
