"""k nearest facilities of vertices and objects by label floods.

If f is among the k nearest of v, it is among the k nearest of every vertex on the shortest way from
v to f. So a flood that starts at all facilities and keeps k labels per vertex loses nothing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import drop_stored, stored
from .distance import object_distance, object_seeds


def ranked(df: DataFrame, group: str, k: int, ties: str, facility: str = "f") -> DataFrame:
    """Rows of the ``k`` nearest per ``group`` with ``rk``: by (d, id), or all of fewer than k strictly nearer ones."""
    w = Window.partitionBy(group)
    rk: Column = F.row_number().over(w.orderBy("d", facility)) if ties == "by_id" else F.rank().over(w.orderBy("d"))
    return df.withColumn("rk", rk).where(F.col("rk") <= k)


def vertex_knn(net: RoadNetwork, facilities: DataFrame, k: int, ties: str = "by_id", max_rounds: int = 100_000) -> DataFrame:
    """``(v, f, d, rk)``: the k nearest facilities of every vertex, in rounds over the whole network (see ``halo_knn`` for tiles)."""
    seeds = facilities.select(F.col("f").alias("v"), "f", F.lit(0).cast("long").alias("d")).distinct()
    return label_flood(net, seeds, k, ties, max_rounds)


def label_flood(net: RoadNetwork, seeds: DataFrame, k: int, ties: str = "by_id", max_rounds: int = 100_000) -> DataFrame:
    """``(v, f, d, rk)``: the k nearest facilities of every vertex from first labels ``seeds(v, f, d)``.

    A round joins the labels that are new with the arcs and keeps the k best per vertex; one exchange
    by vertex serves both the minimum per facility and the ranking. Vertices that reach fewer
    facilities have fewer rows.
    """
    labels = stored(ranked(seeds.groupBy("v", "f").agg(F.min("d").alias("d")), "v", k, ties).withColumn("fresh", F.lit(True)), "flood")
    for _ in range(max_rounds):
        step = labels.where("fresh").join(net.arcs, F.col("v") == F.col("src")).select(F.col("dst").alias("v"), "f", (F.col("d") + F.col("w")).alias("d"), F.lit(True).alias("fresh"))
        both = labels.select("v", "f", "d", F.lit(False).alias("fresh")).unionByName(step).repartition("v")
        best = both.groupBy("v", "f").agg(F.min(F.struct("d", "fresh")).alias("m")).select("v", "f", "m.d", "m.fresh")
        old = labels
        labels = stored(ranked(best, "v", k, ties), "flood")
        drop_stored(old)
        if labels.where("fresh").isEmpty():
            return labels.select("v", "f", "d", "rk")
    raise RuntimeError("labels did not settle")


def ball_knn(net: RoadNetwork, facilities: DataFrame, seeds: DataFrame, k: int, ties: str = "by_id", full_map: bool = False, max_rounds: int = 100_000) -> DataFrame:
    """The k nearest facilities ``(s, f, d, rk)`` of each source in ``seeds(s, v, d)``, searched from the sources outwards.

    Each source's search ends once nothing nearer than its k-th facility is open; labels at just that
    distance stay, as a tied facility may have the smaller id. ``full_map`` returns all settled
    facilities of the search, ranked.
    """
    fac = facilities.select(F.col("f").alias("v"), F.lit(True).alias("is_f"))
    first = seeds.groupBy("v", "s").agg(F.min("d").alias("d")).join(fac, "v", "left")
    labels = stored(first.select("s", "v", "d", F.coalesce("is_f", F.lit(False)).alias("is_f"), F.lit(True).alias("fresh")), "ball")
    limit = None
    for _ in range(max_rounds):
        step = labels.where("fresh").join(net.arcs, F.col("v") == F.col("src")).select("s", F.col("dst").alias("v"), (F.col("d") + F.col("w")).alias("d"))
        step = step.join(fac, "v", "left").select("s", "v", "d", F.coalesce("is_f", F.lit(False)).alias("is_f"), F.lit(True).alias("fresh"))
        both = labels.withColumn("fresh", F.lit(False)).unionByName(step).repartition("s")
        best = both.groupBy("s", "v").agg(F.min(F.struct("d", "fresh")).alias("m"), F.first("is_f").alias("is_f")).select("s", "v", "m.d", "is_f", "m.fresh")
        kth = F.nth_value(F.when(F.col("is_f"), F.col("d")), k, ignoreNulls=True).over(
            Window.partitionBy("s").orderBy(F.when(F.col("is_f"), F.col("d")).asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
        )
        best = best.withColumn("kth", kth).where("kth is null or d <= kth").drop("kth")
        old = labels
        labels = stored(best, "ball")
        drop_stored(old)
        if labels.where("fresh").isEmpty():
            limit = labels
            break
    if limit is None:
        raise RuntimeError("searches did not settle")
    found = limit.where("is_f").select("s", F.col("v").alias("f"), "d")
    return ranked(found, "s", 1 << 30 if full_map else k, ties)


def object_knn(objects: DataFrame, net: RoadNetwork, vertex_labels: DataFrame, k: int, ties: str = "by_id") -> DataFrame:
    """``(m, f, d, rk)`` of objects from the labels at both ends of their edges."""
    return ranked(object_distance(objects, net, vertex_labels), "m", k, ties)


def knn(objects: DataFrame, net: RoadNetwork, facilities: DataFrame, k: int, ties: str = "by_id") -> DataFrame:
    """kNN of objects by one flood over the network."""
    return object_knn(objects, net, vertex_knn(net, facilities, k, ties), k, ties)


def knn_from_objects(objects: DataFrame, net: RoadNetwork, facilities: DataFrame, k: int, ties: str = "by_id", full_map: bool = False) -> DataFrame:
    """kNN of objects by one bounded search per object, as ``(m, f, d, rk)``."""
    seeds = object_seeds(objects, net).withColumnRenamed("m", "s")
    return ball_knn(net, facilities, seeds, k, ties, full_map).withColumnRenamed("s", "m")


def knn_of_vertex_objects(net: RoadNetwork, facilities: DataFrame, k: int, ties: str = "by_id") -> DataFrame:
    """kNN of facilities among the other facilities ``(v, f, d, rk)``: k + 1 labels, then without itself."""
    labels = vertex_knn(net, facilities, k + 1, ties)
    own = labels.join(facilities.select(F.col("f").alias("v")), "v", "left_semi").where("v <> f").drop("rk")
    return ranked(own, "v", k, ties)
