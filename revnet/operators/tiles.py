"""Tile-local relaxation: whole tiles settle in one task, only border labels are exchanged."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..network import RoadNetwork
from ..plans.storage import drop_stored, stored


def tile_knn(net: RoadNetwork, cells: DataFrame, facilities: DataFrame, k: int, max_rounds: int = 100_000) -> DataFrame:
    """``(v, f, d, rk)``: the k nearest facilities of every vertex, ties by id, in rounds that each cross one tile.

    ``cells(v, cell)`` cuts the network into tiles that fit a task. A round settles all labels of a
    tile by a local search from those that are new; labels that got better at vertices with roads to
    other tiles are sent over these roads. Rounds grow with the tiles that a nearest way crosses
    instead of its roads.
    """
    cell_of = stored(cells.select("v", "cell"), "tiles")
    arcs = net.arcs.join(cell_of.select(F.col("v").alias("src"), F.col("cell").alias("cell")), "src").join(cell_of.select(F.col("v").alias("dst"), F.col("cell").alias("to")), "dst")
    inner = stored(arcs.where("cell = to").select("cell", "src", "dst", "w"), "inner-arcs")
    cross = stored(arcs.where("cell <> to").select("src", F.col("dst").alias("v"), "w"), "cross-arcs")
    seeds = facilities.select(F.col("f").alias("v"), "f", F.lit(0).cast("long").alias("d"), F.lit(True).alias("fresh")).join(cell_of, "v")
    labels = stored(seeds.select("cell", "v", "f", "d", "fresh"), "tile-labels")

    def settle(own: pd.DataFrame, roads: pd.DataFrame) -> pd.DataFrame:
        to: dict[int, list[tuple[int, int]]] = {}
        for s, t, w in zip(roads["src"].tolist(), roads["dst"].tolist(), roads["w"].tolist(), strict=True):
            to.setdefault(s, []).append((t, w))
        best: dict[int, dict[int, int]] = {}
        heap, new = [], set()
        for v, f, d, fresh in zip(own["v"].tolist(), own["f"].tolist(), own["d"].tolist(), own["fresh"].tolist(), strict=True):
            if fresh:
                heap.append((d, f, v))
            elif d < best.setdefault(v, {}).get(f, d + 1):
                best[v][f] = d
        heapq.heapify(heap)
        while heap:
            d, f, v = heapq.heappop(heap)
            have = best.setdefault(v, {})
            if f in have and have[f] <= d:
                continue
            if f not in have and len(have) >= k:
                worst = max((x, g) for g, x in have.items())
                if worst <= (d, f):
                    continue
                del have[worst[1]]
                new.discard((v, worst[1]))
            have[f] = d
            new.add((v, f))
            for t, w in to.get(v, ()):
                heapq.heappush(heap, (d + w, f, t))
        rows = [(v, f, d, (v, f) in new) for v, have in best.items() for f, d in have.items()]
        out = pd.DataFrame(rows, columns=["v", "f", "d", "fresh"]).astype({"v": np.int64, "f": np.int64, "d": np.int64, "fresh": bool})
        out.insert(0, "cell", own["cell"].iloc[0] if len(own) else roads["cell"].iloc[0])
        return out

    schema = "cell string, v long, f long, d long, fresh boolean"
    for _ in range(max_rounds):
        settled = stored(labels.groupBy("cell").cogroup(inner.groupBy("cell")).applyInPandas(settle, schema), "settled")
        drop_stored(labels)
        sent = settled.where("fresh").select(F.col("v").alias("src"), "f", "d").join(cross, "src").select("v", "f", (F.col("d") + F.col("w")).alias("d"))
        have = settled.groupBy("v").agg(F.count(F.lit(1)).alias("n"), F.max(F.struct("d", "f")).alias("worst"))
        own = settled.select("v", "f", F.col("d").alias("old"))
        sent = sent.groupBy("v", "f").agg(F.min("d").alias("d")).join(own, ["v", "f"], "left").join(have, "v", "left")
        sent = sent.where((F.col("old").isNotNull() & (F.col("d") < F.col("old"))) | (F.col("old").isNull() & (F.coalesce("n", F.lit(0)) < k)) | (F.col("old").isNull() & (F.struct("d", "f") < F.col("worst"))))
        sent = stored(sent.join(cell_of, "v").select("cell", "v", "f", "d", F.lit(True).alias("fresh")), "tile-messages")
        if sent.isEmpty():
            rk = F.expr("row_number() over (partition by v order by d, f)")
            return settled.select("v", "f", "d", rk.alias("rk"))
        labels = stored(settled.withColumn("fresh", F.lit(False)).unionByName(sent), "tile-labels")
        drop_stored(settled)
    raise RuntimeError("labels did not settle")
