"""Road networks: vertices, undirected edges stored once, and their arcs."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .plans.storage import stored


@dataclass
class RoadNetwork:
    """``vertices(v, x, y)`` and ``edges(eid, u, v, w)`` with u < v and w > 0; integer distances."""

    vertices: DataFrame
    edges: DataFrame
    keep: bool = False  # store arcs when they are first asked for

    @cached_property
    def arcs(self) -> DataFrame:
        """``(src, dst, w)``: both directions, of parallel edges the shortest."""
        e = self.edges
        both = e.select(F.col("u").alias("src"), F.col("v").alias("dst"), "w").unionByName(e.select(F.col("v").alias("src"), F.col("u").alias("dst"), "w"))
        out = both.groupBy("src", "dst").agg(F.min("w").alias("w"))
        return stored(out, "arcs") if self.keep else out

    def lists(self) -> DataFrame:
        """``(v, dst, w)``: each vertex with the arrays of its arcs, in one exchange where no arcs are at hand."""
        arcs = self.__dict__.get("arcs")
        if arcs is None:
            both = self.edges.select(F.explode(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst"), "w"), F.struct(F.col("v").alias("src"), F.col("u").alias("dst"), "w"))).alias("a"))
            arcs = both.select("a.*").repartition("src").groupBy("src", "dst").agg(F.min("w").alias("w"))
        return arcs.groupBy(F.col("src").alias("v")).agg(F.collect_list("dst").alias("dst"), F.collect_list("w").alias("w"))

    def materialized(self) -> RoadNetwork:
        """The same network over stored tables, for iterations that read it again and again."""
        return RoadNetwork(stored(self.vertices, "vertices"), stored(self.edges, "edges"), keep=True)

    def located_edges(self) -> DataFrame:
        """``edges`` with the coordinates of both ends, ``(eid, u, v, w, ux, uy, vx, vy)``."""
        p = self.vertices
        a = p.select(F.col("v").alias("u"), F.col("x").alias("ux"), F.col("y").alias("uy"))
        b = p.select("v", F.col("x").alias("vx"), F.col("y").alias("vy"))
        return self.edges.join(a, "u").join(b, "v")

    def admissibility(self) -> float:
        """Smallest ratio of road length to straight line; circles are widened by its inverse where it is below 1."""
        e = self.located_edges()
        line = F.sqrt((F.col("ux") - F.col("vx")) ** 2 + (F.col("uy") - F.col("vy")) ** 2)
        got = e.where(line > 0).agg(F.min(F.col("w") / line).alias("a")).first().a
        return 1.0 if got is None else float(got)

    def validate(self) -> None:
        """Raise on broken invariants: u < v, w > 0, unique ids, ends that exist, positive admissibility."""
        bad = self.edges.where("u is null or v is null or w is null or not (u < v) or not (w > 0)").limit(1).count()
        if bad:
            raise ValueError("edges need u < v and w > 0")
        if not self.edges.groupBy("eid").count().where("count > 1").isEmpty():
            raise ValueError("edge ids must be unique")
        if not self.vertices.groupBy("v").count().where("count > 1").isEmpty():
            raise ValueError("vertex ids must be unique")
        ends = self.edges.select(F.explode(F.array("u", "v")).alias("v"))
        if not ends.join(self.vertices, "v", "left_anti").isEmpty():
            raise ValueError("edges must end at known vertices")


def validate_inputs(net: RoadNetwork, facilities: DataFrame, queries: DataFrame, objects: DataFrame) -> None:
    """Queries must be facilities, facilities vertices, objects on edges with 0 <= off <= w."""
    if not queries.select(F.col("q").alias("f")).join(facilities, "f", "left_anti").isEmpty():
        raise ValueError("every query must be a facility")
    if not facilities.select(F.col("f").alias("v")).join(net.vertices, "v", "left_anti").isEmpty():
        raise ValueError("every facility must be a vertex")
    o = objects.join(net.edges.select("eid", "w"), "eid", "left")
    if not o.where("w is null or off is null or off < 0 or off > w").isEmpty():
        raise ValueError("objects must lie on known edges, 0 <= off <= w")


def apply_weight_updates(net: RoadNetwork, updates: DataFrame) -> RoadNetwork:
    """A new snapshot of the network in which ``updates(eid, w)`` replace weights; caches of the old one do not carry over."""
    u = updates.select("eid", F.col("w").alias("_new"))
    return RoadNetwork(net.vertices, net.edges.join(u, "eid", "left").select("eid", "u", "v", F.coalesce("_new", "w").alias("w")))
