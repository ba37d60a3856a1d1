"""Table functions for SQL."""

from __future__ import annotations

import re
from collections import OrderedDict

from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


@udtf(returnType="cx: long, cy: long")
class ExpandCells:
    """Grid cells that the box around a circle (x, y, r) meets, for cells of a given side."""

    def eval(self, x: int, y: int, r: int, side: int):
        for cx in range((x - r) // side, (x + r) // side + 1):
            for cy in range((y - r) // side, (y + r) // side + 1):
                yield cx, cy


class _Tiles:
    """A network and its objects in the folder that ``_write_tiles`` made, read tile by tile where a search comes along.

    At most ``held`` tiles are kept. The tile of a vertex is known from the roads that led to it, and
    of a first vertex from the folder's index. ``get``, ``in`` and ``[]`` give the roads of a vertex.
    """

    def __init__(self, path: str, held: int = 32):
        self.path, self.held = path, held
        self.tile_of: dict[int, tuple[int, int] | None] = {}
        self.tiles: OrderedDict[tuple[int, int], tuple[dict, set, dict]] = OrderedDict()

    def _read(self, folder: str, columns: list[str]):
        import glob

        import pyarrow.parquet as pq

        for name in sorted(glob.glob(f"{self.path}/{folder}/*.parquet")):
            t = pq.ParquetFile(name).read(columns)
            yield from zip(*(t.column(c).to_pylist() for c in columns), strict=True)

    def _tile(self, v: int) -> tuple[dict, set, dict] | None:
        if v not in self.tile_of:
            found = ((tx, ty) for u, tx, ty in self._read(f"index/bucket={v % _BUCKETS}", ["v", "tx", "ty"]) if u == v)
            self.tile_of[v] = next(found, None)
        at = self.tile_of[v]
        if at is None:
            return None
        if at in self.tiles:
            self.tiles.move_to_end(at)
            return self.tiles[at]
        folder, out, fac, on = f"tx={at[0]}/ty={at[1]}", {}, set(), {}
        for u, is_f, dst, w, dtx, dty in self._read(f"roads/{folder}", ["v", "is_f", "dst", "w", "dtx", "dty"]):
            self.tile_of[u] = at
            self.tile_of.update(zip(dst, zip(dtx, dty, strict=True), strict=True))
            out[u] = list(zip(dst, w, strict=True))
            if is_f:
                fac.add(u)
        for row in self._read(f"objects/{folder}", ["m", "u", "v", "off", "w"]):
            for u in row[1:3]:
                if u in out:
                    on.setdefault(u, []).append(row)
        self.tiles[at] = out, fac, on
        if len(self.tiles) > self.held:
            self.tiles.popitem(last=False)
        return self.tiles[at]

    def get(self, v: int):
        tile = self._tile(v)
        return None if tile is None else tile[0][v]

    __getitem__ = get

    def __contains__(self, v: int) -> bool:
        return self._tile(v) is not None


class _Facilities:
    """The facilities of ``_Tiles``, asked for by ``in``."""

    def __init__(self, tiles: _Tiles):
        self.tiles = tiles

    def __contains__(self, v: int) -> bool:
        tile = self.tiles._tile(v)
        return tile is not None and v in tile[1]


class _Objects:
    """The objects on the roads at a vertex of ``_Tiles``."""

    def __init__(self, tiles: _Tiles):
        self.tiles = tiles

    def get(self, v: int, default=()):
        tile = self.tiles._tile(v)
        return default if tile is None else tile[2].get(v, default)


class _RknnOf:
    """Objects that have a site among their k nearest facilities, on a network held in the function or in tiles of a shared folder."""

    tables: tuple | str = ()

    def __init__(self):
        from ..operators.halo import Region

        if isinstance(self.tables, str):
            tiles = _Tiles(self.tables)
            v, f, o = tiles, _Facilities(tiles), _Objects(tiles)
        else:
            v, f, o = self.tables
        self.region, self.on = Region.of(v, f), o

    def eval(self, site: int, k: int):
        from ..operators.halo import grow

        lists: dict = {}

        def near(v: int) -> dict:
            if v not in lists:
                lists[v] = {f: d for d, f in self.region.nearest([(0, v)], k, "by_id")}
            return lists[v]

        seen = set()
        for v, _, _, go in grow(self.region, site, k, near, ("stop",), None, None) if site in self.region.out else ():
            for m, a, b, off, w in self.on.get(v, ()) if go else ():
                if m not in seen:
                    seen.add(m)
                    got = self.region.nearest([(off, a), (w - off, b)], k, "by_id")
                    if any(f == site for _, f in got):
                        yield m, next(d for d, f in got if f == site)


#: Parts of the index from vertices to tiles.
_BUCKETS = 256


def _write_tiles(spark: SparkSession, net, facilities, objects, per_tile: int | None = None) -> str:
    """Write roads, objects and an index of vertices in tiles, a folder each, in the shared folder; returns its path for tasks."""
    from uuid import uuid4

    from ..operators.distance import with_ends
    from ..operators.halo import tile_network
    from ..plans.storage import drop_stored, shared_dir

    root = f"{shared_dir(spark)}/rknn-of-{uuid4().hex}"
    local = re.sub("^file:/+", "/", root)
    if not local.startswith("/"):
        raise ValueError("rknn_of reads tiles as files; spark.checkpoint.dir must be a mounted folder for inputs of this size")
    t = tile_network(net, facilities, per_tile)
    at = t.rows.select("v", "tx", "ty")
    to = net.arcs.join(at.select(F.col("v").alias("dst"), F.col("tx").alias("dtx"), F.col("ty").alias("dty")), "dst")
    to = to.groupBy(F.col("src").alias("v")).agg(F.collect_list(F.struct("dst", "w", "dtx", "dty")).alias("to"))
    none = F.array().cast("array<long>")
    roads = t.rows.select("tx", "ty", "v", "is_f").join(to, "v", "left").select("tx", "ty", "v", "is_f", *(F.coalesce(F.col("to")[c], none).alias(c) for c in ("dst", "w", "dtx", "dty")))
    roads.repartition("tx", "ty").write.partitionBy("tx", "ty").parquet(f"{root}/roads")
    # a road between two tiles lies in both
    e = net.edges.join(at.select(F.col("v").alias("u"), F.struct("tx", "ty").alias("a")), "u").join(at.select("v", F.struct("tx", "ty").alias("b")), "v")
    e = e.select("eid", F.explode(F.array_distinct(F.array("a", "b"))).alias("tile")).select("eid", "tile.tx", "tile.ty")
    on = with_ends(objects, net).join(e, "eid").select("tx", "ty", "m", "u", "v", "off", "w")
    on.repartition("tx", "ty").write.partitionBy("tx", "ty").parquet(f"{root}/objects")
    at.withColumn("bucket", F.expr(f"pmod(v, {_BUCKETS})")).repartition("bucket").write.partitionBy("bucket").parquet(f"{root}/index")
    drop_stored(t.rows)
    return local


def register_rknn(spark: SparkSession, net, facilities, objects, limit: int = 2_000_000) -> None:
    """Register ``rknn_of(site, k)`` for SQL: ``(m, net_dist)`` of one site.

    Networks and objects of at most ``limit`` rows go with the function to wherever it is called;
    larger ones are written in tiles to the shared folder, of which a call reads those that its search meets.
    """
    from ..operators.distance import with_ends
    from ..plans.storage import small

    if small(net.arcs, limit) and small(objects, limit):
        out: dict[int, list] = {r.v: [] for r in net.vertices.select("v").collect()}
        for r in net.arcs.collect():
            out[r.src].append((r.dst, r.w))
        on: dict[int, list] = {}
        for r in with_ends(objects, net).collect():
            for v in (r.u, r.v):
                on.setdefault(v, []).append((r.m, r.u, r.v, r.off, r.w))
        held = (out, {r.f for r in facilities.select("f").collect()}, on)
    else:
        held = _write_tiles(spark, net, facilities, objects)
    spark.udtf.register("rknn_of", udtf(type("RknnOf", (_RknnOf,), {"tables": held}), returnType="m: long, net_dist: long"))


def register(spark: SparkSession) -> None:
    spark.udtf.register("expand_cells", ExpandCells)
