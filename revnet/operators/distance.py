"""Network distances: bounded shortest paths from many seeds at once, and distances of objects."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import drop_stored, stored


def network_distance(net: RoadNetwork, seeds: DataFrame, bound: int | None = None, max_rounds: int = 100_000) -> DataFrame:
    """Shortest distances ``(s, v, d)`` from ``seeds(s, v, d)``, up to ``bound``.

    All sources relax together: a round joins the labels that got shorter with the arcs and keeps
    minima, in one exchange by vertex. Unreached vertices have no row; no seeds give an empty table.
    """
    labels = stored(seeds.groupBy("v", "s").agg(F.min("d").alias("d")).withColumn("fresh", F.lit(True)), "labels")
    for _ in range(max_rounds):
        step = labels.where("fresh").join(net.arcs, F.col("v") == F.col("src")).select(F.col("dst").alias("v"), "s", (F.col("d") + F.col("w")).alias("d"), F.lit(True).alias("fresh"))
        if bound is not None:
            step = step.where(F.col("d") <= bound)
        old = labels
        both = labels.withColumn("fresh", F.lit(False)).unionByName(step).repartition("v")
        labels = stored(both.groupBy("v", "s").agg(F.min(F.struct("d", "fresh")).alias("m")).select("v", "s", "m.d", "m.fresh"), "labels")
        drop_stored(old)
        if labels.where("fresh").isEmpty():
            return labels.select("s", "v", "d")
    raise RuntimeError("distances did not settle")


def with_ends(objects: DataFrame, net: RoadNetwork) -> DataFrame:
    """``objects`` with the ends and length of their edge, ``(m, eid, off, u, v, w)``."""
    return objects.select("m", "eid", "off").join(net.edges, "eid").select("m", "eid", "off", "u", "v", "w")


def object_seeds(objects: DataFrame, net: RoadNetwork) -> DataFrame:
    """Both ends of each object's edge as ``(m, v, d)``, d the way from the object."""
    o = with_ends(objects, net)
    return o.select("m", F.col("u").alias("v"), F.col("off").alias("d")).unionByName(o.select("m", "v", (F.col("w") - F.col("off")).alias("d")))


def object_distance(objects: DataFrame, net: RoadNetwork, vertex_dist: DataFrame, name: str = "f") -> DataFrame:
    """Distances ``(m, f, d)`` of objects to facilities from ``vertex_dist(v, f, d)``: the better of both ends."""
    at = vertex_dist.select("v", name, F.col("d").alias("dv"))
    # dealt by object, as rankings per object follow
    return object_seeds(objects, net).join(at, "v").repartition("m").groupBy("m", name).agg(F.min(F.col("d") + F.col("dv")).alias("d"))


def located(objects: DataFrame, net: RoadNetwork) -> DataFrame:
    """Objects with plane coordinates ``(m, eid, off, px, py)``, interpolated along the edge."""
    o = objects.select("m", "eid", "off").join(net.located_edges(), "eid")
    part = F.col("off") / F.col("w")
    return o.select("m", "eid", "off", (F.col("ux") + (F.col("vx") - F.col("ux")) * part).alias("px"), (F.col("uy") + (F.col("vy") - F.col("uy")) * part).alias("py"))
