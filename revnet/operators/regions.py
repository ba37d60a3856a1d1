"""Influence regions (intervals of edges) and safe distances of objects."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import stored
from .halo import _FOUND, _OPEN, TiledNetwork, _widening, found_by


def influence_region(net: RoadNetwork, labels: DataFrame, queries: DataFrame, k: int, ties: str = "by_id") -> DataFrame:
    """``(q, eid, w, lo, hi, rk, du, dv)``: runs of whole offsets of each edge at which q has the same rank among the k nearest.

    Along an edge a facility's distance is the lesser of two lines, from its distances ``du`` and
    ``dv`` to the ends (null: not in that end's list), so ranks change only where two such lines
    cross. Edges meet the labels of their ends once; the runs of an edge are found from these at
    most 2k labels alone, for edges at which a query of the batch has a label.
    """
    asked = queries.select("q").distinct()
    ends = labels.groupBy("v").agg(F.collect_list(F.struct("f", "d")).alias("l"))
    near = stored(labels.withColumnRenamed("f", "q").join(asked, "q").groupBy("v").agg(F.collect_set("q").alias("own")), "near-ends")
    none = F.array().cast("array<struct<f:bigint,d:bigint>>")
    few = F.array().cast("array<bigint>")
    e = net.edges.join(near.select(F.col("v").alias("u"), F.col("own").alias("ou")), "u", "left").join(near.select("v", F.col("own").alias("ov")), "v", "left").where("ou is not null or ov is not null")
    e = e.join(ends.select(F.col("v").alias("u"), F.col("l").alias("lu")), "u", "left").join(ends.select("v", F.col("l").alias("lv")), "v", "left")
    e = e.select("eid", "w", F.coalesce("lu", none).alias("lu"), F.coalesce("lv", none).alias("lv"), F.array_union(F.coalesce("ou", few), F.coalesce("ov", few)).alias("own"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for i, w, lu, lv, own in zip(b["eid"], b["w"], b["lu"], b["lv"], b["own"], strict=True):
                rows += [(f, i, w, *r) for f, *r in edge_intervals(int(w), [(r["f"], r["d"]) for r in lu], [(r["f"], r["d"]) for r in lv], k, ties, set(own.tolist()))]
            yield pd.DataFrame(rows, columns=["q", "eid", "w", "lo", "hi", "rk", "du", "dv"]).astype({"du": "Int64", "dv": "Int64"})

    return e.mapInPandas(run, "q long, eid long, w long, lo long, hi long, rk int, du long, dv long")


def edge_intervals(w: int, lu: list[tuple[int, int]], lv: list[tuple[int, int]], k: int, ties: str, own: set[int] | None = None) -> list[tuple]:
    """Maximal runs (facility, first, last whole offset, rank, distances to both ends) on an edge of length ``w``, of the facilities in ``own`` or all."""
    facs = sorted({f for f, _ in lu} | {f for f, _ in lv})
    if not facs:
        return []
    far = 1 << 60
    du, dv = dict(lu), dict(lv)
    a = np.array([du.get(f, far) for f in facs])
    z = np.array([dv.get(f, far) for f in facs])
    # whole offsets next to which two of the lines a + x and z + w - x cross
    cross = (z[None, :] + w - a[:, None]).ravel()
    cuts = np.concatenate([cross // 2 + i for i in (-1, 0, 1, 2)])
    cuts = np.unique(np.concatenate([[0, w], cuts[(cuts >= 0) & (cuts <= w)]]))
    d = np.minimum(a[:, None] + cuts[None, :], z[:, None] + w - cuts[None, :])
    if ties == "by_id":
        order = np.argsort(d, axis=0, kind="stable")  # facilities are in order of their ids
        rank = np.empty_like(order)
        np.put_along_axis(rank, order, np.arange(1, len(facs) + 1)[:, None] + np.zeros((1, len(cuts)), np.int64), 0)
    else:
        rank = 1 + (d[:, None, :] > d[None, :, :]).sum(1)
    rank = np.where(d < far, rank, k + 1)
    out = []
    for i, f in enumerate(facs):
        r = rank[i]
        if (own is None or f in own) and (r <= k).any():
            # between neighbouring cuts nothing changes, so a run ends where the next cut has another rank
            turn = np.flatnonzero(r[1:] != r[:-1])
            on, off = np.append(0, turn + 1), np.append(turn, len(r) - 1)
            out += [(f, int(cuts[s]), int(cuts[t]), int(r[s]), du.get(f), dv.get(f)) for s, t in zip(on, off, strict=True) if r[s] <= k]
    return out


_FAR = 1 << 60
_TOGETHER = 500_000  # facilities compared with a query at a time


def edge_runs(w: np.ndarray, u: tuple[np.ndarray, np.ndarray, np.ndarray], v: tuple[np.ndarray, np.ndarray, np.ndarray], asked: np.ndarray, k: int, ties: str, by_rank: bool) -> dict[str, np.ndarray]:
    """Runs of whole offsets at which facilities of ``asked`` (rising) are among the k nearest, of many edges at once.

    ``w`` are the edges' lengths, ``u`` and ``v`` the labels (edge, facility, distance) of their ends. Another
    facility is nearer than q from an end on up to an offset, by the way over that end, or from both ends, so
    the rank of q changes at one or two offsets for each. Rows are (edge, q, lo, hi, rk, du, dv), a distance
    -1 where an end lacks q; without ``by_rank`` a run holds all ranks up to k.
    """
    e, f = np.concatenate([u[0], v[0]]), np.concatenate([u[1], v[1]])
    a = np.concatenate([u[2], np.full(len(v[2]), _FAR)])
    z = np.concatenate([np.full(len(u[2]), _FAR), v[2]])
    order = np.lexsort((f, e))
    e, f, a, z = e[order], f[order], a[order], z[order]
    new = np.flatnonzero(np.append(True, (e[1:] != e[:-1]) | (f[1:] != f[:-1]))[: len(e)])
    e, f = e[new], f[new]
    a, z = (np.minimum.reduceat(x, new) if len(new) else x for x in (a, z))
    first, last = np.searchsorted(e, e, side="left"), np.searchsorted(e, e, side="right")
    own = np.flatnonzero(np.isin(f, asked))
    upto = np.cumsum(last[own] - first[own]) // _TOGETHER
    out = [_runs(own[upto == i], e, f, a, z, w, first, last, k, ties, by_rank) for i in (np.unique(upto) if len(own) else [0])]
    return {c: np.concatenate([x[c] for x in out]) for c in out[0]}


def _runs(own, e, f, a, z, w, first, last, k, ties, by_rank) -> dict[str, np.ndarray]:
    n = last[own] - first[own]
    p = np.repeat(np.arange(len(own)), n)
    g = np.arange(int(n.sum())) + np.repeat(first[own] - (np.cumsum(n) - n), n)
    q = own[p]
    p, g, q = (x[g != q] for x in (p, g, q))
    le = (f[g] < f[q]).astype(np.int64) if ties == "by_id" else np.zeros(len(g), np.int64)  # nearer also if equally far
    length = w[e[q]]
    # from u on up to ``end``, from ``start`` on to v
    end = np.where((a[g] < _FAR) & (a[g] < a[q] + le), np.minimum((z[q] + length - a[g] - 1 + le) >> 1, length), -1)
    start = np.where((z[g] < _FAR) & (z[g] < z[q] + le), np.maximum((z[g] + length - a[q] + 2 - le) >> 1, 0), length + 1)
    whole = start <= end + 1
    here = (end >= 0) | whole
    base = np.bincount(p[here], minlength=len(own))
    stops, starts = here & ~whole, ~whole & (start <= length)
    # at offset 0 stands who is nearer there; then one less where a prefix has ended, one more where a suffix begins
    of = np.concatenate([np.arange(len(own)), p[stops], p[starts]])
    x = np.concatenate([np.zeros(len(own), np.int64), end[stops] + 1, start[starts]])
    step = np.concatenate([base, np.full(int(stops.sum()), -1), np.ones(int(starts.sum()), np.int64)])
    order = np.argsort(of << 40 | x, kind="stable")
    of, x, step = of[order], x[order], step[order]
    level = np.cumsum(step)
    head = np.searchsorted(of, np.arange(len(own)))
    level -= np.append(0, level)[head][of]
    keep = np.flatnonzero(np.append((of[1:] != of[:-1]) | (x[1:] != x[:-1]), True)[: len(of)])
    of, x, rank = of[keep], x[keep], level[keep] + 1
    state = np.where(rank <= k, rank if by_rank else 1, 0)
    new = np.append(True, (of[1:] != of[:-1]) | (state[1:] != state[:-1]))[: len(of)]
    of, x, state = of[new], x[new], state[new]
    stop = np.append(np.where(of[1:] == of[:-1], x[1:] - 1, w[e[own[of[:-1]]]]), w[e[own[of[-1:]]]])
    i = np.flatnonzero((state > 0) & (stop >= x))
    at = own[of[i]]
    return {"edge": e[at], "q": f[at], "lo": x[i], "hi": stop[i], "rk": state[i], "du": np.where(a[at] < _FAR, a[at], -1), "dv": np.where(z[at] < _FAR, z[at], -1)}


def tile_regions(t: TiledNetwork, queries: DataFrame, k: int, ties: str = "by_id", by_rank: bool = True) -> DataFrame:
    """``influence_region`` with the labels of both ends of an edge searched and met in the edge's tile, so that no labels are written.

    Without ``by_rank`` a run holds all offsets at which q is among the k nearest, and ``rk`` says nothing.
    """
    asked = queries.select(F.col("q").alias("v"), F.lit(True).alias("is_q")).distinct()
    marked = replace(t, rows=stored(t.rows.join(asked, "v", "left").withColumn("is_q", F.coalesce("is_q", F.lit(False))), "asked-tiles"))

    def work(s: pd.DataFrame, g: pd.DataFrame) -> pd.DataFrame:
        eid, w = s["a"].to_numpy(np.int64), s["w"].to_numpy(np.int64)
        v, ends = np.unique(np.concatenate([s["u"].to_numpy(np.int64), s["v"].to_numpy(np.int64)]), return_inverse=True)
        row, f, d, left = found_by(g, np.arange(len(v)), v, np.zeros(len(v), np.int64), len(v), k, ties)
        first, last = np.searchsorted(row, np.arange(len(v)), side="left"), np.searchsorted(row, np.arange(len(v)), side="right")
        ends = ends.reshape(2, -1)
        asked = np.sort(g["v"].to_numpy(np.int64)[g["is_q"].to_numpy(bool)])
        open_ = left[ends].any(0)
        none = np.full(int(open_.sum()), -1, np.int64)
        parts = [{"kind": none * 0 + _OPEN, "a": eid[open_], "b": none, **{c: none for c in ("w", "lo", "hi", "rk", "du", "dv")}}]
        whole = np.flatnonzero(~open_)
        for at in range(0, len(whole), 1024):
            i = whole[at : at + 1024]
            labels = []
            for side in (0, 1):
                x, n = first[ends[side, i]], (last - first)[ends[side, i]]
                j = np.arange(int(n.sum())) + np.repeat(x - (np.cumsum(n) - n), n)
                labels.append((np.repeat(np.arange(len(i)), n), f[j], d[j]))
            got = edge_runs(w[i], *labels, asked, k, ties, by_rank)
            e = i[got["edge"]]
            parts.append({"kind": np.full(len(e), _FOUND), "a": eid[e], "b": got["q"], "w": w[e], **{c: got[c] for c in ("lo", "hi", "rk", "du", "dv")}})
        return pd.DataFrame({c: np.concatenate([x[c] for x in parts]) for c in parts[0]})

    edges = t.net.edges.select(F.col("eid").alias("a"), F.lit(-1).cast("long").alias("b"), "u", "v", "w")
    sources = edges.join(t.rows.select(F.col("v").alias("u"), "tx", "ty"), "u")
    schema, out = "kind int, a long, b long, w long, lo long, hi long, rk int, du long, dv long", None
    for got, rest in _widening(marked, sources, k, work, 20_000, schema):
        part = got.where(F.col("kind") == _FOUND).select(F.col("b").alias("q"), F.col("a").alias("eid"), "w", "lo", "hi", "rk", *(F.when(F.col(c) >= 0, F.col(c)).alias(c) for c in ("du", "dv")))
        out = part if out is None else out.unionByName(part)
        if rest is not None:
            from .flood import vertex_knn

            far = replace(t.net, edges=rest.select(F.col("a").alias("eid"), "u", "v", "w"))
            out = out.unionByName(influence_region(far, vertex_knn(t.net, t.facilities, k, ties), queries, k, ties))
    return out


def region_members(region: DataFrame, objects: DataFrame) -> DataFrame:
    """Answers ``(q, m, d, rk)`` by one join of objects with the runs of their edges, each of which gives rank and distance."""
    hit = objects.select("m", "eid", "off").join(region, "eid").where("off between lo and hi")
    return hit.select("q", "m", F.least(F.col("du") + F.col("off"), F.col("dv") + F.col("w") - F.col("off")).alias("d"), "rk")


def safe_slack(knn: DataFrame, k: int) -> DataFrame:
    """``(m, d_k, d_k1, twice_slack)`` from the k + 1 nearest: half of ``twice_slack`` may be moved before the k nearest can change."""
    per = knn.groupBy("m").agg(F.max(F.when(F.col("rk") == k, F.col("d"))).alias("d_k"), F.max(F.when(F.col("rk") == k + 1, F.col("d"))).alias("d_k1"))
    return per.withColumn("twice_slack", F.col("d_k1") - F.col("d_k"))


def must_verify(slack: DataFrame, moved: DataFrame) -> DataFrame:
    """Objects of ``moved(m, distance)`` that moved at least half their slack, or have none."""
    s = moved.join(slack.select("m", "twice_slack"), "m", "left")
    return s.where("twice_slack is null or 2 * distance >= twice_slack").select("m")
