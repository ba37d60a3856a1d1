"""Pruned expansion from all query facilities at once."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import drop_stored, stored
from .flood import vertex_knn
from .halo import REGION_LIMIT, TiledNetwork, expand_free, expand_in_tiles, expand_whole


@dataclass
class Expansion:
    """``labels(q, v, d, c, go)`` of reached vertices (``go``: left again), rounds, labels made by round,
    k nearest facilities ``lists(v, f, d, rk)`` met on the way and the searches that found them."""

    labels: DataFrame
    rounds: int
    made: list[int]
    lists: DataFrame | None = None
    searches: int = 0
    tables: list = field(default_factory=list)


def expand(t: TiledNetwork, queries: DataFrame, k: int, rules: tuple[str, ...] = ("stop",), ties: str = "by_id", share: bool = True, max_radius: int | None = None, max_hops: int | None = None, vertex_labels: DataFrame | None = None, max_rounds: int = 100_000) -> Expansion:
    """The expansion by tiles where the stop rule bounds it; where not, with the whole network in a task.

    If that is too large, expansions under other rules run by tiles too, and those without any in blocks of the network.
    Waves too wide for a task, and all without the stop rule under a hop limit, go on in rounds, with k nearest facilities of all vertices.
    """
    if "stop" not in rules and max_hops is None and t.n <= REGION_LIMIT:
        labels = expand_whole(t, queries.select("q").distinct(), k, rules, ties, max_radius)
        return Expansion(labels, 1, [], tables=[])
    if not rules and max_hops is None:
        labels, rounds = expand_free(t, queries.select("q").distinct(), max_radius)
        return Expansion(labels, rounds, [], tables=[])
    if "stop" not in rules and max_hops is not None:
        if vertex_labels is None and "ancestor" in rules:
            vertex_labels = vertex_knn(t.net, t.facilities, k, ties, max_rounds)
        return pruned_expand(t.net, t.facilities, queries, k, rules, ties, vertex_labels, max_radius, max_hops, max_rounds)
    got = expand_in_tiles(t, queries, k, rules, ties, share, max_radius, max_hops)
    out = Expansion(got.labels, got.rounds, [], got.lists, got.searches, got.tables)
    if "stop" not in rules:
        out.lists, out.searches = None, 0  # as of the whole network in a task
    if got.left is not None:
        labels = vertex_labels if vertex_labels is not None else vertex_knn(t.net, t.facilities, k, ties, max_rounds)
        rest = pruned_expand(t.net, t.facilities, got.left, k, rules, ties, labels, max_radius, max_hops, max_rounds)
        out.labels, out.rounds, out.made = out.labels.unionByName(rest.labels), out.rounds + rest.rounds, rest.made
    return out


def pruned_expand(
    net: RoadNetwork, facilities: DataFrame, queries: DataFrame, k: int, rules: tuple[str, ...] = ("stop", "path_count"), ties: str = "by_id",
    vertex_labels: DataFrame | None = None, max_radius: int | None = None, max_hops: int | None = None, max_rounds: int = 100_000,
) -> Expansion:
    """Vertices reached from each query facility in rounds over the network, with the length ``d`` of the way found.

    Rules, any set of which keeps every way to an answer whole:
    ``stop``: a vertex where k facilities come before q is kept as an end, but not left;
    ``path_count``: a vertex whose way holds k other facilities is dropped (``c`` counts them);
    ``ancestor``: a vertex is dropped if the last facility on its way that has q among its k nearest
    is not among its own k nearest. The first and last need ``vertex_labels`` of the k nearest.
    Without rules the expansion covers the component of q. A radius or hop limit cuts all ways.
    """
    if {"stop", "ancestor"} & set(rules) and vertex_labels is None:
        raise ValueError("rules stop and ancestor need the k nearest facilities of vertices")
    fac = facilities.select(F.col("f").alias("v"), F.lit(1).alias("is_f"))
    near = stored(vertex_labels.select("v", "f", F.lit(True).alias("near")), "near") if {"stop", "ancestor"} & set(rules) else None
    first = queries.select("q", F.col("q").alias("v"), F.lit(0).cast("long").alias("d"), F.lit(0).alias("c"), F.lit(None).cast("long").alias("anc")).distinct()
    labels = stored(first.withColumns({"go": F.lit(True), "fresh": F.lit(True)}), "expand")
    made = [labels.count()]
    for rounds in range(1, max_rounds):
        if max_hops is not None and rounds > max_hops:
            break
        step = labels.where("go and fresh").join(net.arcs, F.col("v") == F.col("src"))
        step = step.select("q", F.col("dst").alias("v"), (F.col("d") + F.col("w")).alias("d"), "c", "anc")
        if max_radius is not None:
            step = step.where(F.col("d") <= max_radius)
        step = step.join(fac, "v", "left").withColumn("is_f", F.coalesce("is_f", F.lit(0)))
        step = step.withColumn("c", F.col("c") + F.when(F.col("v") != F.col("q"), F.col("is_f")).otherwise(0))
        if "path_count" in rules:
            step = step.where(F.col("c") < k)
        if "ancestor" in rules:
            step = step.join(near.withColumnRenamed("f", "anc"), ["v", "anc"], "left").where("anc is null or near").drop("near")
        leave = F.lit(True)
        if near is not None:
            step = step.join(near.select("v", F.col("f").alias("q"), F.col("near").alias("own")), ["v", "q"], "left")
            step = step.withColumn("anc", F.when((F.col("is_f") == 1) & F.col("own"), F.col("v")).otherwise(F.col("anc")))
            if "stop" in rules:
                leave = F.coalesce("own", F.lit(False))
        step = step.select("q", "v", "d", "c", "anc", leave.alias("go"), F.lit(True).alias("fresh"))
        both = labels.withColumn("fresh", F.lit(False)).unionByName(step).repartition("v")
        # of equally short ways: an old label first (it has been left already), then the one with most facilities
        best = both.groupBy("q", "v").agg(F.min(F.struct("d", "fresh", (-F.col("c")).alias("c"), "anc", "go")).alias("m"))
        old = labels
        labels = stored(best.select("q", "v", "m.d", (-F.col("m.c")).alias("c"), "m.anc", "m.go", "m.fresh"), "expand")
        drop_stored(old)
        made.append(labels.where("fresh").count())
        if not made[-1]:
            break
    if near is not None:
        drop_stored(near)
    return Expansion(labels.select("q", "v", "d", "c", "go"), len(made) - 1, made, tables=[labels])
