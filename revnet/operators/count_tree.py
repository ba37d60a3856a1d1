"""An aggregate tree over the facilities, and circle counts for many circles at once, one level at a time."""

from __future__ import annotations

import os
import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property
from uuid import uuid4

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from ..functions.geometry import box_bounds2, disc_bounds, smallest_circle
from ..plans.storage import shared_dir, stored


@dataclass
class CountTree:
    """``levels`` of nodes ``(node, parent, cnt, box, disc, first)``, leaves first, a table each; ``points(node, f, x, y, first)`` the leaves' facilities.

    ``first`` marks one child of each parent."""

    levels: list[DataFrame]
    points: DataFrame

    @cached_property
    def files(self) -> str | None:
        """The folder of the tree's arrays, written when first asked for."""
        return pack_tree(self.levels, self.points)

    @property
    def depth(self) -> int:
        return len(self.levels)


def build_count_tree(facilities: DataFrame, fanout: int = 16, leaf_size: int = 32) -> CountTree:
    """Sort-tile packing: strips by x, tiles by y in each strip, then ``fanout`` neighbours to a parent.

    Strip and tile borders are percentiles, so that no task sorts all facilities. Leaves have their
    smallest enclosing circle, upper nodes a circle around their children's.
    """
    n = facilities.count()
    side = max(1, int(np.ceil((n / leaf_size) ** 0.5)))
    cuts = [i / side for i in range(1, side)]
    rows = facilities.select("f", "x", "y")
    if side > 1:
        xs = np.array(rows.agg(F.percentile_approx("x", cuts, 100_000)).first()[0], float)
        strip = F.pandas_udf(lambda x: pd.Series(np.searchsorted(xs, x.to_numpy(float), side="left").astype(np.int32)), "int")
        rows = rows.withColumn("strip", strip("x"))
        ys = stored(rows.groupBy("strip").agg(F.percentile_approx("y", cuts, 10_000).alias("ys")), "tree-strips")
        rows = rows.join(ys, "strip").withColumn("tile", F.size(F.filter("ys", lambda c: c < F.col("y"))))
        # neighbouring strips run in opposite directions, so that following numbers are neighbours
        tile = F.when(F.col("strip") % 2 == 0, F.col("tile")).otherwise(side - 1 - F.col("tile"))
        rows = rows.withColumn("node", (F.col("strip") * side + tile).cast("long"))
    else:
        rows = rows.withColumn("node", F.lit(0).cast("long"))
    points = stored(rows.select("node", "f", "x", "y", F.expr("f = min(f) over (partition by node)").alias("first")), "tree-points")

    def leaves(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for node, xs, ys in zip(b["node"].tolist(), b["xs"], b["ys"], strict=True):
                rows.append((node, len(xs), xs.min(), ys.min(), xs.max(), ys.max(), *smallest_circle(np.stack([xs, ys], 1))))
            yield pd.DataFrame(rows, columns=["node", "cnt", "xmin", "ymin", "xmax", "ymax", "cx", "cy", "cr"])

    schema = "node long, cnt long, xmin long, ymin long, xmax long, ymax long, cx double, cy double, cr double"
    packed = points.groupBy("node").agg(F.collect_list("x").alias("xs"), F.collect_list("y").alias("ys"))  # about ``leaf_size`` to a leaf
    level, levels, width = packed.mapInPandas(leaves, schema), [], side * side
    while True:
        top = width == 1
        level = level.withColumn("parent", F.lit(0).cast("long") if top else F.expr(f"node div {fanout}"))
        level = stored(level.withColumn("first", F.expr("node = min(node) over (partition by parent)")), "tree-level")
        levels.append(level)
        if top:
            return CountTree(levels, points)
        mid = level.groupBy("parent").agg(F.avg("cx").alias("mx"), F.avg("cy").alias("my"))
        reach = F.sqrt((F.col("cx") - F.col("mx")) ** 2 + (F.col("cy") - F.col("my")) ** 2) + F.col("cr")
        level = level.join(mid, "parent").groupBy(F.col("parent").alias("node")).agg(
            F.sum("cnt").alias("cnt"), F.min("xmin").alias("xmin"), F.min("ymin").alias("ymin"), F.max("xmax").alias("xmax"), F.max("ymax").alias("ymax"),
            F.first("mx").alias("cx"), F.first("my").alias("cy"), (F.max(reach) * (1 + 1e-9)).alias("cr"),
        )
        width = -(-width // fanout)


def range_count(tree: CountTree, circles: DataFrame, bound: str = "mbc", count_mode: str = "exact") -> DataFrame:
    """``(id, cnt, nodes)`` of ``circles(id, px, py, r)``: facilities within each, borders included, and tree nodes looked at.

    A node outside is left, one inside adds its stored count, one partly covered goes on to its
    children, at the leaves to its points. ``bound`` takes boxes, circles or the tighter of both;
    ``count_mode`` upper counts partly covered leaves whole, which only ever counts more. Tasks map the
    tree's files in the shared folder and take many circles through it at once; where that folder is
    not mounted, circles meet the tree's tables level by level.
    """
    if tree.files is None:
        return count_by_joins(tree, circles, bound, count_mode)
    names = ["id", "px", "py", "r"]
    folder, depth = tree.files, tree.depth

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packed = PackedTree(folder, depth)
        for b in batches:
            x, y, r = (b.column(i).cast(pa.float64()).to_numpy(zero_copy_only=False) for i in (1, 2, 3))
            cnt, nodes = packed.count(x, y, r, bound, count_mode)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(cnt), pa.array(nodes)], names=["id", "cnt", "nodes"])

    slim = circles.select(*names)
    out = StructType([slim.schema["id"], StructField("cnt", LongType()), StructField("nodes", LongType())])
    return slim.mapInArrow(run, out).groupBy("id").agg(F.sum("cnt").alias("cnt"), F.sum("nodes").alias("nodes"))


_LEVEL = ("node", "parent", "cnt", "xmin", "ymin", "xmax", "ymax", "cx", "cy", "cr")
_PAIRS = 1_000_000  # circles with nodes looked at together


def pack_tree(levels: list[DataFrame], points: DataFrame) -> str | None:
    """Write the tree as arrays that tasks map, rows in order of nodes: their folder, or None where the shared folder is not mounted."""
    spark = points.sparkSession
    folder = re.sub("^file:/+", "/", f"{shared_dir(spark)}/tree-{uuid4().hex}")
    if not folder.startswith("/"):
        return None

    def write(df: DataFrame, name: str, columns: tuple[str, ...]) -> None:
        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            os.makedirs(folder, exist_ok=True)
            part, n = f"{folder}/{name}.{uuid4().hex}", 0
            with open(part, "wb") as f:
                for b in batches:
                    f.write(np.ascontiguousarray(b.to_numpy(np.float64)).tobytes())
                    n += len(b)
            os.replace(part, f"{folder}/{name}")  # appears whole, also of a task that runs twice
            yield pd.DataFrame({"n": [n]})

        rows = df.select(*(F.col(c).cast("double") for c in columns)).repartition(1).sortWithinPartitions("node")
        rows.mapInPandas(run, "n long").collect()

    for i, level in enumerate(levels):
        write(level, f"level-{i}", _LEVEL)
    write(points, "points", ("node", "x", "y"))
    return folder


class PackedTree:
    """The files of ``pack_tree``, mapped, so that processes share their pages."""

    def __init__(self, folder: str, depth: int):
        def rows(name: str, width: int) -> np.ndarray:
            size = os.path.getsize(f"{folder}/{name}") // 8
            return (np.memmap(f"{folder}/{name}", np.float64, "r").view(np.ndarray) if size else np.zeros(0)).reshape(-1, width)

        self.levels = [rows(f"level-{i}", len(_LEVEL)) for i in range(depth)]
        self.points = rows("points", 3)
        # children of a node, or its points, are rows in a run
        self.kids = [self._runs(x[:, 0], self.levels[i - 1][:, 1]) if i else self._runs(x[:, 0], self.points[:, 0]) for i, x in enumerate(self.levels)]

    @staticmethod
    def _runs(nodes: np.ndarray, of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        of = np.ascontiguousarray(of)
        return np.searchsorted(of, nodes, side="left"), np.searchsorted(of, nodes, side="right")

    def count(self, x: np.ndarray, y: np.ndarray, r: np.ndarray, bound: str, count_mode: str) -> tuple[np.ndarray, np.ndarray]:
        """Facilities within each circle and nodes looked at."""
        got, seen = np.zeros(len(x), np.int64), np.zeros(len(x), np.int64)
        every, roots = np.arange(len(x)), len(self.levels[-1])
        # level, circles, and the rows of the level (or points, at level -1) to look at: from, to
        todo = [(len(self.levels) - 1, every, np.zeros(len(x), np.int64), np.full(len(x), roots))]
        while todo:
            level, c, lo, hi = todo.pop()
            n = hi - lo
            if len(c) > 1 and n.sum() > _PAIRS:
                half = len(c) // 2
                todo += [(level, c[half:], lo[half:], hi[half:]), (level, c[:half], lo[:half], hi[:half])]
                continue
            row = np.arange(int(n.sum())) + np.repeat(lo - (np.cumsum(n) - n), n)
            c = np.repeat(c, n)
            if level < 0:
                px, py = self.points[row, 1], self.points[row, 2]
                near = (px - x[c]) * (px - x[c]) + (py - y[c]) * (py - y[c]) <= r[c] * r[c]
                got += np.bincount(c[near], minlength=len(x))
                continue
            seen += np.bincount(c, minlength=len(x))
            low, high = self._distances(self.levels[level], row, x[c], y[c], bound)
            meets = low <= r[c]
            whole = meets if level == 0 and count_mode == "upper" else meets & (high <= r[c])
            got += np.bincount(c[whole], self.levels[level][row[whole], 2], len(x)).astype(np.int64)
            on = meets & ~whole
            lo, hi = self.kids[level]
            todo.append((level - 1, c[on], lo[row[on]], hi[row[on]]))
        return got, seen

    @staticmethod
    def _distances(level: np.ndarray, row: np.ndarray, x: np.ndarray, y: np.ndarray, bound: str) -> tuple[np.ndarray, np.ndarray]:
        """As ``_bounds``, by the same steps."""
        box, disc = (), ()
        if bound != "mbc":
            x0, y0, x1, y1 = (level[row, i] for i in (3, 4, 5, 6))
            dx, dy = np.maximum(np.maximum(x0 - x, 0), x - x1), np.maximum(np.maximum(y0 - y, 0), y - y1)
            fx, fy = np.maximum(np.abs(x - x0), np.abs(x - x1)), np.maximum(np.abs(y - y0), np.abs(y - y1))
            box = np.sqrt(dx * dx + dy * dy), np.sqrt(fx * fx + fy * fy)
        if bound != "mbr":
            dx, dy, cr = x - level[row, 7], y - level[row, 8], level[row, 9]
            d = np.sqrt(dx * dx + dy * dy)
            disc = np.maximum(0.0, d - cr), d + cr
        if bound == "both":
            return np.maximum(box[0], disc[0]), np.minimum(box[1], disc[1])
        return box or disc


def count_by_joins(tree: CountTree, circles: DataFrame, bound: str = "mbc", count_mode: str = "exact") -> DataFrame:
    """``range_count`` as one lazy plan through which each circle goes once: a row that is settled passes the further levels unmatched.

    Levels are tables of their own, so the upper ones are broadcast by their size and only leaves too many
    for that are met by exchange, when circles have spread over them.
    """
    px, py, r = F.col("px"), F.col("py"), F.col("r")
    low, high = _bounds(px, py, bound)
    # settled rows get a spread key that no node has, so that an exchange deals them evenly
    settled = -1 - F.pmod(F.xxhash64("id"), F.lit(1 << 20))
    zero, one = F.lit(0).cast("long"), F.lit(1).cast("long")
    rows = circles.select("id", "px", "py", "r", zero.alias("at"), zero.alias("got"), zero.alias("seen"))
    for level in range(tree.depth - 1, -1, -1):
        met, here = rows.join(tree.levels[level], F.col("at") == F.col("parent"), "left"), F.col("node").isNotNull()
        meets = here & (low <= r)
        whole = meets if level == 0 and count_mode == "upper" else meets & (high <= r)
        # what a node's row has seen goes on with one of its children
        rows = met.select(
            "id", "px", "py", "r", F.when(meets & ~whole, F.col("node")).otherwise(settled).alias("at"),
            (F.col("got") + F.when(whole, F.col("cnt")).otherwise(zero)).alias("got"),
            F.when(here, one + F.when(F.col("first"), F.col("seen")).otherwise(zero)).otherwise(F.col("seen")).alias("seen"),
        )
    if count_mode == "exact":
        met = rows.join(tree.points, F.col("at") == F.col("node"), "left")
        near = F.coalesce((F.col("x") - px) * (F.col("x") - px) + (F.col("y") - py) * (F.col("y") - py) <= r * r, F.lit(False))
        rows = met.select("id", (F.col("got") + near.cast("long")).alias("got"), F.when(F.coalesce("first", F.lit(True)), F.col("seen")).otherwise(zero).alias("seen"))
    return rows.groupBy("id").agg(F.sum("got").alias("cnt"), F.sum("seen").alias("nodes"))


def _bounds(px: Column, py: Column, bound: str) -> tuple[Column, Column]:
    """Least and greatest distance of a point to a node's box, circle, or the tighter of both."""
    box, disc = box_bounds2(px, py, "xmin", "ymin", "xmax", "ymax"), disc_bounds(px, py, "cx", "cy", "cr")
    low = {"mbr": F.sqrt(box[0]), "mbc": disc[0], "both": F.greatest(F.sqrt(box[0]), disc[0])}[bound]
    return low, {"mbr": F.sqrt(box[1]), "mbc": disc[1], "both": F.least(F.sqrt(box[1]), disc[1])}[bound]


def range_search(tree: CountTree, circles: DataFrame, bound: str = "mbc") -> DataFrame:
    """``(id, f)``: the facilities within each circle, borders included."""
    px, py, r = F.col("px"), F.col("py"), F.col("r")
    low, _ = _bounds(px, py, bound)
    rows = circles.select("id", "px", "py", "r", F.lit(0).cast("long").alias("at"))
    for level in range(tree.depth - 1, -1, -1):
        rows = rows.join(tree.levels[level], F.col("at") == F.col("parent")).where(low <= r).select("id", "px", "py", "r", F.col("node").alias("at"))
    hit = rows.join(tree.points, F.col("at") == F.col("node"))
    return hit.where((F.col("x") - px) * (F.col("x") - px) + (F.col("y") - py) * (F.col("y") - py) <= r * r).select("id", "f")
