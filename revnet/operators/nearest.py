"""Nearest sites of points in the plane by squared distance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.storage import drop_stored, stored


def nearest_site(points: DataFrame, sites: DataFrame, per_cell: int = 2) -> DataFrame:
    """``(m, q, d2)``: of ``points(m, px, py)`` the nearest of ``sites(v, x, y)``, ties by id; all coordinates whole numbers.

    A site is listed in its grid cell and the eight around, so a point meets by one join all sites
    that are nearer than a cell's side. Points whose best is not go on with cells twice as wide, the last
    of which hold all sites.
    """
    sites = stored(sites.select("v", "x", "y"), "nearest-sites")
    todo = stored(points.select("m", "px", "py"), "nearest-points")
    box = sites.select("x", "y").unionByName(todo.select(F.col("px").alias("x"), F.col("py").alias("y"))).agg(F.min("x"), F.max("x"), F.min("y"), F.max("y")).first()
    n = sites.count()
    if not n or box[0] is None:
        return todo.selectExpr("m", "m as q", "m as d2").where("1 = 0")
    wide = max(box[1] - box[0], box[3] - box[2], 1)
    side, done = max(1, int(wide / max((n / per_cell) ** 0.5, 1))), None
    while True:
        cell = lambda c, by=side: F.floor(F.col(c) / F.lit(by)).cast("long")
        near = F.array(*[F.struct((cell("x") + i).alias("cx"), (cell("y") + j).alias("cy")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
        lists = sites.select("v", "x", "y", F.explode(near).alias("c")).groupBy("c.cx", "c.cy").agg(F.collect_list(F.struct("v", "x", "y")).alias("s"))
        d2 = lambda p: (F.col("px") - p["x"]) * (F.col("px") - p["x"]) + (F.col("py") - p["y"]) * (F.col("py") - p["y"])
        best = F.array_min(F.transform("s", lambda p: F.struct(d2(p).alias("d2"), p["v"].alias("q"))))
        met = todo.withColumns({"cx": cell("px"), "cy": cell("py")}).join(lists, ["cx", "cy"], "left").select("m", "px", "py", best.alias("b"))
        met = stored(met, "nearest-met")
        last = side > wide
        sure = F.lit(True) if last else F.coalesce(F.col("b.d2") <= side * side, F.lit(False))
        part = met.where(sure).select("m", "b.q", "b.d2")
        done = part if done is None else done.unionByName(part)
        drop_stored(todo)
        todo = met.where(~sure).select("m", "px", "py")
        if last or todo.isEmpty():
            drop_stored(sites)
            return done
        todo = stored(todo, "nearest-points")
        side *= 2
