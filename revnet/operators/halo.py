"""Searches inside tiles of the plane: exact k nearest facilities and pruned expansions, one task per tile.

A task holds the roads of its tile and of a halo around it. A search that ends inside is exact, as
shortest ways are found in order of length; one that would leave the halo is given back and tried
again with a wider one, and what is still open at a stated region size relaxes in rounds over the
whole network. So a batch reads only the roads around its queries, and a wave needs no exchange for
each step. Within a task k nearest facilities of vertices are found when a wave first reaches them and
are shared by all of its queries; they go on to the exact test.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass
from heapq import heapify, heappop, heappush

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import drop_stored, stored
from .lockstep import RoadArrays, places, ranks_of

#: Regions of more vertices than this are not loaded into one task.
REGION_LIMIT = 400_000


@dataclass
class TiledNetwork:
    """``rows(tx, ty, v, x, y, is_f, dst, w)``: every vertex once, with its arcs, in tiles of ``side``."""

    net: RoadNetwork
    facilities: DataFrame
    rows: DataFrame
    side: int
    spacing: float
    extent: int
    n: int
    f: int

    def first_halo(self, k: int) -> int:
        """A halo that holds most searches for ``k`` facilities, ways being longer than straight lines."""
        return int(2 * self.spacing * (2 + (k * self.n / max(self.f, 1)) ** 0.5)) + 1

    def fits(self, halo: int) -> bool:
        """Whether the roads within ``halo`` of a tile are few enough for a task."""
        wide = min(self.side + 2 * halo, self.extent + 1)
        return (wide / max(self.spacing, 1e-9)) ** 2 <= REGION_LIMIT

    def at(self, df: DataFrame, vertex: str) -> DataFrame:
        """``df`` with the tile of one of its vertex columns."""
        return df.join(self.rows.select(F.col("v").alias(vertex), "tx", "ty"), vertex)


def tile_network(net: RoadNetwork, facilities: DataFrame, per_tile: int | None = None) -> TiledNetwork:
    """Deal a network's vertices over square tiles of about ``per_tile`` vertices (by default a few tiles per core, of 256 to 8,192)."""
    box = net.vertices.agg(F.count(F.lit(1)).alias("n"), F.min("x").alias("x0"), F.max("x").alias("x1"), F.min("y").alias("y0"), F.max("y").alias("y1")).first()
    n, f = box.n, facilities.count()
    wide, high = (max(box.x1 - box.x0, 1), max(box.y1 - box.y0, 1)) if n else (1, 1)
    spacing = (wide * high / max(n, 1)) ** 0.5
    per_tile = per_tile or min(8192, max(256, n // (3 * net.vertices.sparkSession.sparkContext.defaultParallelism)))
    side = max(1, int(spacing * per_tile**0.5))
    out = net.lists()
    own = facilities.select(F.col("f").alias("v"), F.lit(True).alias("is_f")).distinct()
    none = F.array().cast("array<long>")
    rows = net.vertices.join(out, "v", "left").join(own, "v", "left").select(
        F.floor(F.col("x") / side).cast("long").alias("tx"), F.floor(F.col("y") / side).cast("long").alias("ty"), "v", "x", "y",
        F.coalesce("is_f", F.lit(False)).alias("is_f"), F.coalesce("dst", none).alias("dst"), F.coalesce("w", none).alias("w"),
    )
    return TiledNetwork(net, facilities, stored(rows, "tiled"), side, spacing, int(max(wide, high)), n, f)


class Region:
    """Roads and facilities that a task holds."""

    def __init__(self, g: pd.DataFrame):
        self.out = {v: list(zip(t.tolist(), w.tolist(), strict=True)) for v, t, w in zip(g["v"].tolist(), g["dst"], g["w"], strict=True)}
        self.fac = set(g.loc[g["is_f"].astype(bool), "v"].tolist())

    @classmethod
    def of(cls, out: dict[int, list[tuple[int, int]]], fac: set[int]) -> Region:
        """A region from roads by vertex and facilities."""
        new = cls.__new__(cls)
        new.out, new.fac = out, fac
        return new

    def nearest(self, starts: list[tuple[int, int]], k: int, ties: str, full_map: bool = False) -> list[tuple[int, int]] | None:
        """Facilities ``(d, f)`` among the k nearest of ``starts(d, v)``, in order; None if the search leaves the region."""
        heap, done, found, limit = list(starts), set(), [], None
        heapify(heap)
        while heap:
            d, v = heappop(heap)
            if limit is not None and d > limit:
                break
            if v in done:
                continue
            roads = self.out.get(v)
            if roads is None:
                return None
            done.add(v)
            if v in self.fac:
                found.append((d, v))
                if len(found) == k:
                    limit = d
            for t, w in roads:
                if t not in done:
                    heappush(heap, (d + w, t))
        return found if full_map or ties == "inclusive" else found[:k]


def ranks(found: list[tuple[int, int]], ties: str) -> Iterator[tuple[int, int, int]]:
    """``(f, d, rk)`` of facilities in order: by place, or one more than those strictly nearer."""
    last, rk = None, 0
    for i, (d, f) in enumerate(found, 1):
        if ties == "by_id" or d != last:
            last, rk = d, i
        yield f, d, rk


def grow(region: Region, q: int, k: int, near: Callable[[int], dict[int, int] | None], rules: tuple[str, ...], max_radius: int | None, max_hops: int | None) -> list[tuple[int, int, int, bool]] | None:
    """Labels ``(v, d, c, go)`` of the pruned expansion from ``q``, None if it leaves the region.

    ``near`` gives a vertex's k nearest facilities with their distances. A vertex that lacks q there
    is an end: kept, not left (``go`` false); without the stop rule all are left, and ``near`` is asked for the rule ``ancestor`` alone. A hop limit orders the wave by hops; vertices that are
    left have their true distance either way, as their lists hold it.
    """
    heap, seen, out = [(0, 0, 0, q, -1, 0)], set(), []
    stop, ancestor = "stop" in rules, "ancestor" in rules
    while heap:
        _, d, c, v, anc, hops = heappop(heap)
        if v in seen:
            continue
        own = near(v) if stop or ancestor else {}
        if own is None or v not in region.out:
            return None
        if anc >= 0 and ancestor and anc not in own:
            continue
        seen.add(v)
        go = q in own or not stop
        if go and stop:
            d = own[q]
        out.append((v, d, -c, go))
        if not go or (max_hops is not None and hops >= max_hops):
            continue
        if v in region.fac and (stop or (q in own and v != q)):
            anc = v
        for t, w in region.out[v]:
            if t not in seen and (max_radius is None or d + w <= max_radius):
                more = c - (t in region.fac and t != q)
                if "path_count" not in rules or -more < k:
                    heappush(heap, (hops + 1 if max_hops is not None else 0, d + w, more, t, anc, hops + 1))
    return out


_OUT = "kind int, a long, b long, v long, d long, n int"
_FOUND, _OPEN, _LIST, _COUNT = 0, 1, 2, 3


def _frame(rows: list[tuple]) -> pd.DataFrame:
    return pd.DataFrame(rows, columns=["kind", "a", "b", "v", "d", "n"])


def _in_regions(t: TiledNetwork, sources: DataFrame, halo: int, work: Callable[[pd.DataFrame, pd.DataFrame], pd.DataFrame], per_task: int | None, schema: str = _OUT) -> DataFrame:
    """``work`` on the sources ``(tx, ty, ...)`` of each tile with the roads within ``halo`` of it.

    With ``per_task`` a tile's many sources are dealt over tasks; without, they are known to be no more than its vertices.
    """
    if per_task is None:
        load = sources.select("tx", "ty", F.lit(1).alias("parts")).distinct()
    else:
        load = stored(sources.groupBy("tx", "ty").agg(F.ceil(F.count(F.lit(1)) / per_task).cast("int").alias("parts")), "tile-load")
    reach = -(-halo // t.side)
    need = load.select("tx", "ty", "parts", F.explode(F.sequence(F.col("tx") - reach, F.col("tx") + reach)).alias("ux"))
    need = need.select("*", F.explode(F.sequence(F.col("ty") - reach, F.col("ty") + reach)).alias("uy"))
    inside = " and ".join(f"{c} between t{c} * {t.side} - {halo} and (t{c} + 1) * {t.side} + {halo}" for c in "xy")
    roads = t.rows.withColumnRenamed("tx", "ux").withColumnRenamed("ty", "uy").join(need, ["ux", "uy"]).where(inside)
    # columns of their own on this side, as both sides come from the same tiles
    roads = roads.select(F.col("tx").alias("tx"), F.col("ty").alias("ty"), F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), *(c for c in ("v", "is_f", "is_q", "dst", "w") if c in t.rows.columns))
    if per_task is None:
        dealt = sources.withColumn("part", F.lit(0))
    else:
        dealt = sources.join(load, ["tx", "ty"]).withColumn("part", F.pmod(F.xxhash64("a", "b"), F.col("parts")).cast("int")).drop("parts")
    run = lambda s, g: work(s, g) if len(s) else pd.DataFrame(columns=[c.split()[0] for c in schema.split(", ")])
    return dealt.groupBy("tx", "ty", "part").cogroup(roads.groupBy("tx", "ty", "part")).applyInPandas(run, schema)


def _widening(t: TiledNetwork, sources: DataFrame, k: int, work, per_task: int | None, schema: str = _OUT) -> Iterator[tuple[DataFrame, DataFrame | None]]:
    """Results of ``work`` for wider and wider halos; beside the last, the sources ``(a, b, ...)`` left to a search in rounds (None: none)."""
    halo, todo = t.first_halo(k), sources
    while True:
        got = stored(_in_regions(t, todo, halo, work, per_task, schema), "in-tiles")
        left = got.where(F.col("kind") == _OPEN).select("a", "b")
        if left.isEmpty():
            yield got, None
            return
        halo *= 3
        todo = stored(todo.join(left, ["a", "b"], "left_semi"), "open-sources")
        if not t.fits(halo):
            yield got, todo
            return
        yield got, None


def found_by(g: pd.DataFrame, s: np.ndarray, v: np.ndarray, d: np.ndarray, count: int, k: int, ties: str, full_map: bool = False) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """``(s, f, d, left)``: what searches in roads ``g`` find, in order of (s, d, f), and which of them leave the roads."""
    row, f, dist, left, slow = RoadArrays(g).nearest(s, v, d, count, k)
    if ties == "by_id" and not full_map:
        keep = places(row) < k
        row, f, dist = row[keep], f[keep], dist[keep]
    if slow.any():
        region, more = Region(g), [np.zeros((3, 0), np.int64)]
        for i in np.flatnonzero(slow).tolist():
            x, y = np.searchsorted(s, [i, i + 1])
            found = region.nearest(list(zip(d[x:y].tolist(), v[x:y].tolist(), strict=True)), k, ties, full_map)
            if found is None:
                left[i] = True
            elif found:
                more.append(np.array([(i, b, a) for a, b in found], np.int64).T)
        row, f, dist = np.concatenate([np.stack([row, f, dist]), *more], axis=1)
        order = np.lexsort((f, dist, row))
        row, f, dist = row[order], f[order], dist[order]
    return row, f, dist, left


def search_sources(t: TiledNetwork, sources: DataFrame, k: int, ties: str = "by_id", full_map: bool = False, per_task: int | None = 20_000) -> DataFrame:
    """``(a, b, f, d, rk)``: the k nearest facilities of each source ``(a, b, v1, d1, v2, d2)``, one search per source.

    A source stands at one or two vertices (``v2`` null) at given distances; ``a, b`` name it.
    """

    def work(s: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        a, b = s["a"].to_numpy(np.int64), s["b"].to_numpy(np.int64)
        two = np.flatnonzero(s["v2"].notna().to_numpy())
        of = np.concatenate([np.arange(len(s)), two])
        order = np.argsort(of, kind="stable")
        v = np.concatenate([s["v1"].to_numpy(np.int64), s["v2"].to_numpy()[two].astype(np.int64)])[order]
        d = np.concatenate([s["d1"].to_numpy(np.int64), s["d2"].to_numpy()[two].astype(np.int64)])[order]
        row, f, dist, left = found_by(g, of[order], v, d, len(s), k, ties, full_map)
        none = np.zeros(int(left.sum()), np.int64)
        cols = [[np.full(len(row), _FOUND), a[row], b[row], f, dist, ranks_of(row, dist, ties)], [none + _OPEN, a[left], b[left], none, none, none]]
        return pd.DataFrame({c: np.concatenate([x[i] for x in cols]) for i, c in enumerate(_frame([]).columns)})

    out = None
    for got, rest in _widening(t, t.at(sources.withColumnRenamed("v1", "_v"), "_v").withColumnRenamed("_v", "v1"), k, work, per_task):
        part = got.where(F.col("kind") == _FOUND).select("a", "b", F.col("v").alias("f"), "d", F.col("n").alias("rk"))
        out = part if out is None else out.unionByName(part)
        if rest is not None:
            from .flood import ball_knn

            named = rest.withColumn("s", F.struct("a", "b"))
            seeds = named.select("s", F.col("v1").alias("v"), F.col("d1").alias("d")).unionByName(named.where("v2 is not null").select("s", F.col("v2").alias("v"), F.col("d2").alias("d")))
            out = out.unionByName(ball_knn(t.net, t.facilities, seeds, k, ties, full_map).select("s.a", "s.b", "f", "d", "rk"))
    return out


def vertex_sources(vertices: DataFrame) -> DataFrame:
    """Sources of ``search_sources`` for vertices ``(v)``."""
    none = F.lit(None).cast("long")
    return vertices.select(F.col("v").alias("a"), F.lit(-1).cast("long").alias("b"), F.col("v").alias("v1"), F.lit(0).cast("long").alias("d1"), none.alias("v2"), none.alias("d2"))


def halo_knn(t: TiledNetwork, k: int, ties: str = "by_id", vertices: DataFrame | None = None) -> DataFrame:
    """``(v, f, d, rk)``: the k nearest facilities of all vertices, or of ``vertices(v)``, searched tile by tile."""
    rows = search_sources(t, vertex_sources(t.rows if vertices is None else vertices), k, ties, per_task=None)
    return rows.select(F.col("a").alias("v"), "f", "d", "rk")


@dataclass
class TiledExpansion:
    """``labels(q, v, d, c, go)``, the k nearest facilities ``lists(v, f, d, rk)`` found on the way (None if not shared), and searches run for them."""

    labels: DataFrame
    lists: DataFrame | None
    searches: int
    rounds: int
    left: DataFrame | None  # queries whose wave is too wide for tasks
    tables: list


def expand_in_tiles(t: TiledNetwork, queries: DataFrame, k: int, rules: tuple[str, ...] = ("stop",), ties: str = "by_id", share: bool = True, max_radius: int | None = None, max_hops: int | None = None) -> TiledExpansion:
    """Pruned expansions from all queries, tile by tile; the stop rule is always on.

    With ``share`` a vertex's k nearest facilities are searched once per task for all of its queries;
    without, each query searches its own.
    """

    def work(s: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        region = Region(g)
        rows: list[tuple] = []
        known: dict[int, list | None] = {}
        sets: dict[int, dict[int, int] | None] = {}
        made = 0

        def near(v: int) -> dict[int, int] | None:
            nonlocal made
            if v not in sets:
                made += 1
                known[v] = region.nearest([(0, v)], k, ties)
                sets[v] = None if known[v] is None else {f: d for d, f in known[v]}
            return sets[v]

        for q in s["a"].tolist():
            if not share:
                known.clear()
                sets.clear()
            got = grow(region, q, k, near, rules, max_radius, max_hops)
            if got is None:
                rows.append((_OPEN, q, -1, 0, 0, 0))
            else:
                rows += [(_FOUND, q, c, v, d, int(go)) for v, d, c, go in got]
        if share:
            rows += [(_LIST, f, -1, v, d, rk) for v, found in known.items() if found is not None for f, d, rk in ranks(found, ties)]
        rows.append((_COUNT, made, -1, 0, 0, 0))
        return _frame(rows)

    labels = lists = left = None
    searches, rounds, tables = 0, 0, []
    for got, rest in _widening(t, t.at(queries.select(F.col("q").alias("a"), F.lit(-1).cast("long").alias("b"), F.col("q").alias("_v")), "_v").drop("_v"), k, work, None):
        rounds += 1
        tables.append(got)
        part = got.where(F.col("kind") == _FOUND).select(F.col("a").alias("q"), "v", "d", F.col("b").cast("int").alias("c"), (F.col("n") == 1).alias("go"))
        labels = part if labels is None else labels.unionByName(part)
        searches += got.where(F.col("kind") == _COUNT).agg(F.sum("a")).first()[0] or 0
        part = got.where(F.col("kind") == _LIST).select("v", F.col("a").alias("f"), "d", F.col("n").alias("rk"))
        lists = part if lists is None else lists.unionByName(part)
        left = rest
    if share and lists is not None:
        lists = stored(lists.dropDuplicates(["v", "f"]), "lists")  # neighbouring tiles may have met the same vertex
        tables.append(lists)
    return TiledExpansion(labels, lists if share else None, int(searches), rounds, None if left is None else left.select(F.col("a").alias("q")), tables)


def expand_whole(t: TiledNetwork, queries: DataFrame, k: int, rules: tuple[str, ...], ties: str, max_radius: int | None) -> DataFrame:
    """Labels ``(q, v, d, c, go)`` of expansions without the stop rule, each in a task that holds the whole network."""

    def work(s: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        region = Region(g)
        sets: dict[int, dict[int, int]] = {}

        def near(v: int) -> dict[int, int]:
            if v not in sets:
                sets[v] = {f: d for d, f in region.nearest([(0, v)], k, ties)}
            return sets[v]

        return _frame([(_FOUND, q, c, v, d, int(go)) for q in s["a"].tolist() for v, d, c, go in grow(region, q, k, near, rules, max_radius, None)])

    at = t.at(queries.select(F.col("q").alias("a"), F.lit(-1).cast("long").alias("b"), F.col("q").alias("_v")), "_v").drop("_v")
    got = stored(_in_regions(t, at, t.extent + t.side, work, 1), "whole")
    return got.select(F.col("a").alias("q"), "v", "d", F.col("b").cast("int").alias("c"), (F.col("n") == 1).alias("go"))


def expand_free(t: TiledNetwork, queries: DataFrame, max_radius: int | None = None, block: int = 140_000, per_task: int = 4, max_rounds: int = 100_000) -> tuple[DataFrame, int]:
    """Labels ``(q, v, d, c, go)`` of expansions without rules, and rounds, for networks too large for a task.

    The network is cut into blocks of about ``block`` vertices. A round settles the blocks that got shorter ways by
    a local search for ``per_task`` queries a task; labels that got better at roads to other blocks are sent over them.
    So rounds grow with the blocks that a way crosses, not with its roads.
    """
    wide = max(1, int((block / max((t.side / max(t.spacing, 1e-9)) ** 2, 1)) ** 0.5))
    part = F.pmod(F.xxhash64("q"), F.lit(max(1, -(-queries.count() // per_task)))).cast("int")
    place = [F.floor(F.col(x) / wide).cast("long").alias(f"b{x[1]}") for x in ("tx", "ty")]
    spots = stored(t.rows.select("v", "is_f", *place, "dst", "w"), "blocks")
    key, schema = ["bx", "by", "part"], "bx long, by long, part int, q long, v long, d long, c long, sent boolean"

    def settle(own: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        if not len(own) or not len(g):
            return pd.DataFrame(columns=[x.split()[0] for x in schema.split(", ")])
        region, rows = Region(g), []
        for q, of in own.groupby("q"):
            q, best, heap, sent = int(q), {}, [], {}
            for v, d, c, new in zip(of["v"].tolist(), of["d"].tolist(), of["c"].tolist(), of["sent"].tolist(), strict=True):
                if new:
                    heap.append((d, -c, v))
                else:
                    best[v] = (d, -c)
            heapify(heap)
            while heap:
                d, c, v = heappop(heap)
                if v in best and best[v] <= (d, c):
                    continue
                best[v] = (d, c)
                for to, w in region.out[v]:
                    if max_radius is not None and d + w > max_radius:
                        continue
                    if to in region.out:
                        way = (d + w, c - (to in region.fac and to != q))
                        if to not in best or way < best[to]:
                            heappush(heap, (*way, to))
                    elif to not in sent or (d + w, c) < sent[to]:
                        sent[to] = (d + w, c)
            rows += [(q, v, d, -c, False) for v, (d, c) in best.items()] + [(q, v, d, -c, True) for v, (d, c) in sent.items()]
        out = pd.DataFrame(rows, columns=["q", "v", "d", "c", "sent"])
        for i, x in enumerate(key):
            out.insert(i, x, own[x].iloc[0])
        return out

    start = queries.select("q", F.col("q").alias("v"), F.lit(0).cast("long").alias("d"), F.lit(0).cast("long").alias("c"))
    names = [*key, "q", "v", "d", "c", "sent"]
    labels, sent = None, stored(start.join(spots.select("v", "bx", "by"), "v").withColumns({"part": part, "sent": F.lit(True)}).select(names), "block-sent")
    for rounds in range(1, max_rounds):
        touched = stored(sent.select(key).distinct(), "block-open")
        own = sent if labels is None else sent.unionByName(labels.join(touched, key, "left_semi").select(names))
        roads = spots.join(touched, ["bx", "by"]).select(*(F.col(x).alias(x) for x in key), "v", "is_f", "dst", "w")
        got = stored(own.groupBy(key).cogroup(roads.groupBy(key)).applyInPandas(settle, schema), "block-settled")
        new = got.where("not sent")
        old = [labels, sent]
        labels = stored(new if labels is None else labels.join(touched, key, "left_anti").select(names).unionByName(new), "block-labels")
        # of equally short ways the one with most facilities; a vertex's own counts where it is reached
        at = got.where("sent").select("q", "v", "d", "c").join(spots.select("v", "bx", "by", "is_f"), "v")
        at = at.withColumn("c", F.col("c") + (F.col("is_f") & (F.col("v") != F.col("q"))).cast("long")).groupBy("q", "v", "bx", "by").agg(F.min(F.struct("d", (-F.col("c")).alias("c"))).alias("m"))
        best = labels.select("q", "v", F.struct("d", (-F.col("c")).alias("c")).alias("have"))
        better = at.join(best, ["q", "v"], "left").where("have is null or m < have")
        sent = stored(better.select("bx", "by", part.alias("part"), "q", "v", F.col("m.d").alias("d"), (-F.col("m.c")).alias("c"), F.lit(True).alias("sent")), "block-sent")
        forget([x for x in (*old, got, touched) if x is not None])
        if sent.isEmpty():
            return labels.select("q", "v", "d", F.col("c").cast("int").alias("c"), F.lit(True).alias("go")), rounds
    raise RuntimeError("expansions did not settle")


def forget(tables: list) -> None:
    """Delete stored tables that are read no more."""
    for x in tables:
        drop_stored(x)
