"""Networks, facilities, query batches and moving objects derived from the given tables by integer formulas."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import stored


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def grid_side(spark: SparkSession, sf_dir: str, name: str = "part") -> tuple[int, int]:
    """Rows of the table, and the side of the grid they form."""
    n = table(spark, sf_dir, name).count()
    return n, int(-(-(n**0.5) // 1)) if n else 1


def grid_network(spark: SparkSession, sf_dir: str, name: str = "thinned") -> RoadNetwork:
    """``lattice`` and ``thinned`` (vertices of part), ``wide`` (vertices of orders)."""
    source, key, size = ("orders", "o_orderkey", F.expr("10 * cast(floor(o_totalprice / 10000) as long)")) if name == "wide" else ("part", "p_partkey", F.expr("10 * cast(p_size as long)"))
    if name == "lattice":
        size = F.lit(0).cast("long")
    n, s = grid_side(spark, sf_dir, source)
    rows = table(spark, sf_dir, source).select(F.col(key).cast("long").alias("i"), size.alias("detour"))

    def x(i: str) -> str:
        return f"(({i}) % {s}) * 1000 + (({i}) * 7919) % 401"

    def y(i: str) -> str:
        return f"(({i}) div {s}) * 1000 + (({i}) * 104729) % 401"

    vertices = rows.selectExpr("i as v", f"{x('i')} as x", f"{y('i')} as y")
    keep = "true" if name == "lattice" else f"(i % {s} = 0 or (i * 2654435761) % 3 <> 0)"
    right = rows.where(f"i % {s} < {s - 1} and i + 1 < {n}").selectExpr("2 * i as eid", "i as u", "i + 1 as v", "detour")
    down = rows.where(f"i + {s} < {n} and {keep}").selectExpr("2 * i + 1 as eid", "i as u", f"i + {s} as v", "detour")
    e = right.unionByName(down)
    length = f"ceil(sqrt(cast(pow({x('u')} - ({x('v')}), 2) + pow({y('u')} - ({y('v')}), 2) as double)))"
    return RoadNetwork(vertices, e.selectExpr("eid", "u", "v", f"cast({length} as long) + detour as w"))


def irregular_network(spark: SparkSession, sf_dir: str) -> RoadNetwork:
    """Vertices from two components of each embedding; edges to the 3 nearest vertices and along the x order.

    The nearest vertices come from grid cells that widen until three are certain, not from all pairs.
    """
    p = table(spark, sf_dir, "embeddings").select(
        F.col("vec_id").cast("long").alias("v"), F.round(F.col("embedding")[0].cast("double") * 100000).cast("long").alias("x"), F.round(F.col("embedding")[1].cast("double") * 100000).cast("long").alias("y")
    )
    near = nearest_points(p, 3)
    line = following(p).select(F.col("v").alias("a"), F.col("next").alias("b"))
    pairs = near.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v")).unionByName(line.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))).distinct()
    e = RoadNetwork(p, pairs.selectExpr("u * 1048576 + v as eid", "u", "v", "1L as w")).located_edges()
    length = "greatest(1L, cast(ceil(sqrt(cast(pow(ux - vx, 2) + pow(uy - vy, 2) as double))) as long))"
    return RoadNetwork(p, e.selectExpr("eid", "u", "v", f"{length} as w"))


def following(p: DataFrame, strips: int = 1024) -> DataFrame:
    """``(v, next)``: the vertex after each one in the order of (x, v), found within strips of x and between their ends."""
    got = p.agg(F.min("x").alias("a"), F.max("x").alias("z")).first()
    if got.a is None:
        return p.selectExpr("v", "v as next").where("1 = 0")
    width = (got.z - got.a) // strips + 1
    s = p.select("v", "x", F.expr(f"(x - {got.a}) div {width}").alias("strip"))
    first = s.groupBy("strip").agg(F.min_by("v", F.struct("x", "v")).alias("head"))
    after = first.selectExpr("strip", "lead(head) over (order by strip) as head")  # one row per strip
    s = s.withColumn("next", F.expr("lead(v) over (partition by strip order by x, v)")).join(F.broadcast(after), "strip")
    return s.select("v", F.coalesce("next", "head").alias("next")).where("next is not null")


def nearest_points(p: DataFrame, k: int, per_cell: int = 8, max_rounds: int = 40) -> DataFrame:
    """``(a, b)``: each point's ``k`` nearest others of ``p(v, x, y)``, ties by id.

    Points meet by grid cells; a point whose k-th candidate is nearer than its cell's surroundings
    reach is done, the others go on with cells twice as wide.
    """
    got = p.agg(F.count(F.lit(1)).alias("n"), F.min("x"), F.max("x"), F.min("y"), F.max("y")).first()
    n = got.n
    if n < 2:
        return p.selectExpr("v as a", "v as b").where("1 = 0")
    side = max(1, int((max(got[2] - got[1], got[4] - got[3], 1)) / max((n / per_cell) ** 0.5, 1)))
    todo, done = p, None
    for _ in range(max_rounds):
        cell = lambda c: F.floor(F.col(c) / F.lit(side)).cast("long")
        here = p.select(F.col("v").alias("b"), F.col("x").alias("bx"), F.col("y").alias("by"), cell("x").alias("cx"), cell("y").alias("cy"))
        around = todo.select(F.col("v").alias("a"), "x", "y", F.explode(F.array([F.struct((cell("x") + i).alias("cx"), (cell("y") + j).alias("cy")) for i in (-1, 0, 1) for j in (-1, 0, 1)])).alias("c"))
        met = around.select("a", "x", "y", "c.cx", "c.cy").join(here, ["cx", "cy"]).where("a <> b")
        met = met.selectExpr("a", "b", "(x - bx) * (x - bx) + (y - by) * (y - by) as d2").selectExpr("*", "row_number() over (partition by a order by d2, b) rk").where(f"rk <= {k}")
        sure = met.groupBy("a").agg(F.count(F.lit(1)).alias("n"), F.max("d2").alias("far")).where(f"n >= {min(k, n - 1)} and far <= {side * side}")
        met = stored(met.join(sure.select("a", F.lit(True).alias("sure")), "a", "left").select("a", "b", F.coalesce("sure", F.lit(False)).alias("sure")), "near-points")  # a round's plan holds no earlier one
        part = met.where("sure").select("a", "b")
        done = part if done is None else done.unionByName(part)
        if side > 2 * max(got[2] - got[1], got[4] - got[3], 1):
            break
        todo = stored(todo.join(part.select(F.col("a").alias("v")), "v", "left_anti"), "far-points")
        if todo.isEmpty():
            break
        side *= 2
    return done


def network(spark: SparkSession, sf_dir: str, name: str = "thinned") -> RoadNetwork:
    return irregular_network(spark, sf_dir) if name == "irregular" else grid_network(spark, sf_dir, name)


def query_sites(spark: SparkSession, sf_dir: str, n: int, prefix: int | None = None) -> DataFrame:
    """``(q)``: suppliers scattered over the ``n`` vertices; ``prefix`` takes those of smaller keys only."""
    s = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").cast("long").alias("k"))
    if prefix is not None:
        s = s.where(F.col("k") < prefix)
    return s.select(F.expr(f"(k * 7919) % {n}").alias("q")).distinct()


def spread_batch(spark: SparkSession, sf_dir: str, n: int, size: int) -> DataFrame:
    """``(q)``: up to ``size`` vertices scattered over the ``n`` vertices of the part nets."""
    p = table(spark, sf_dir, "part").select(F.col("p_partkey").cast("long").alias("k")).where(F.col("k") < size)
    return p.select(F.expr(f"(k * 7919) % {n}").alias("q")).distinct()


def corner_batch(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(q)``: the vertices of the first 10 by 10 corner of the part grid."""
    _, s = grid_side(spark, sf_dir)
    return table(spark, sf_dir, "part").selectExpr("cast(p_partkey as long) as q").where(f"q % {s} < 10 and q div {s} < 10")


def facilities(net: RoadNetwork, kind: str = "all", sites: DataFrame | None = None) -> DataFrame:
    """``(f, x, y)``: all vertices, a tenth of them and the sites, or the sites alone."""
    p = net.vertices.select(F.col("v").alias("f"), "x", "y")
    if kind == "all":
        return p
    own = sites.select(F.col("q").alias("f"))
    picked = own if kind == "sites" else own.unionByName(p.where("f % 10 = 0").select("f")).distinct()
    return p.join(picked, "f", "left_semi")


_OBJECTS = {
    "orders": ("orders", "cast(o_orderkey as long)", "m * 48271", "m", "cast(round(o_totalprice * 100) as long)"),
    "events": ("events", "cast(event_id as long)", "m * 48271", "m", "cast(round(value * 100) as long)"),
    "updates": ("events", "cast(user_id as long)", "m * 48271 + event_id * 16807", "event_id", "cast(round(value * 100) as long)"),
}


def place(rows: DataFrame, net: RoadNetwork, n: int, near: DataFrame | None = None) -> DataFrame:
    """Objects ``(m, eid, off, ...)`` from ``rows(m, a, p, z, ...)``: anchor vertex, position among its edges, raw offset.

    With ``near(v)`` only those anchored there, which are all on roads with both ends there; other rows are left before any join of roads.
    """
    e = net.edges
    inc = e.select(F.col("u").alias("a"), "eid", "w").unionByName(e.select(F.col("v").alias("a"), "eid", "w"))
    if near is not None:
        at = near.select(F.col("v").alias("a"))
        rows, inc = rows.join(at, "a", "left_semi"), inc.join(at, "a", "left_semi")
    inc = inc.selectExpr("a", "eid", "w", "row_number() over (partition by a order by eid) - 1 as slot", "count(*) over (partition by a) as degree")
    keep = [c for c in rows.columns if c not in ("a", "p", "z")]
    joined = rows.join(inc.select("a", "degree").distinct(), "a").withColumn("slot", F.col("p") % F.col("degree")).drop("degree").join(inc.drop("degree"), ["a", "slot"])
    return joined.select(*keep, "eid", (F.col("z") % F.col("w")).alias("off"))


def moving_objects(spark: SparkSession, sf_dir: str, net: RoadNetwork, kind: str = "orders", n: int | None = None, near: DataFrame | None = None) -> DataFrame:
    """``(m, eid, off)`` of orders, events or lineitem rows, with ``near(v)`` of those anchored there; updates also have ``ts`` and ``event_id``."""
    n = n or net.vertices.count()
    if kind == "lineitem":
        src = table(spark, sf_dir, "lineitem").selectExpr(
            "*", "cast((cast(l_orderkey as long) * 8 + l_linenumber) * 64 + row_number() over (partition by l_orderkey, l_linenumber order by l_extendedprice, l_partkey, l_suppkey) - 1 as long) as m"
        )
        rows = src.selectExpr("m", f"(m * 48271) % {n} as a", f"m div {n} as p", "cast(round(l_extendedprice * 100) as long) as z")
    else:
        source, m, anchor, pos, z = _OBJECTS[kind]
        extra = ["cast(ts as timestamp) as ts", "cast(event_id as long) as event_id"] if kind == "updates" else []
        src = table(spark, sf_dir, source).selectExpr(f"{m} as m", "*")
        rows = src.selectExpr("m", f"({anchor}) % {n} as a", f"({pos}) div {n} as p", f"{z} as z", *extra)
    return place(rows, net, n, near)
