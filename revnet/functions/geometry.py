"""Plane geometry as column expressions, and Python functions for enclosing circles and grid cells."""

from __future__ import annotations

import math
import random

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


def euclid(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    """Straight-line distance."""
    return F.sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))


def box_bounds2(px: Column, py: Column, xmin: str, ymin: str, xmax: str, ymax: str) -> tuple[Column, Column]:
    """Squared least and greatest distance of a point to a box."""
    zero = F.lit(0)
    dx = F.greatest(F.col(xmin) - px, zero, px - F.col(xmax))
    dy = F.greatest(F.col(ymin) - py, zero, py - F.col(ymax))
    fx = F.greatest(F.abs(px - F.col(xmin)), F.abs(px - F.col(xmax)))
    fy = F.greatest(F.abs(py - F.col(ymin)), F.abs(py - F.col(ymax)))
    return dx * dx + dy * dy, fx * fx + fy * fy


def disc_bounds(px: Column, py: Column, cx: str, cy: str, cr: str) -> tuple[Column, Column]:
    """Least and greatest distance of a point to a disc."""
    d = euclid(px, py, F.col(cx), F.col(cy))
    return F.greatest(F.lit(0.0), d - F.col(cr)), d + F.col(cr)


def _two(a: list[float], b: list[float]) -> tuple[float, float, float]:
    cx, cy = (a[0] + b[0]) / 2, (a[1] + b[1]) / 2
    return cx, cy, math.hypot(a[0] - cx, a[1] - cy)


def _three(a: list[float], b: list[float], c: list[float]) -> tuple[float, float, float] | None:
    ax, ay, bx, by = b[0] - a[0], b[1] - a[1], c[0] - a[0], c[1] - a[1]
    d = 2 * (ax * by - ay * bx)
    if d == 0:
        return None
    ux = (by * (ax * ax + ay * ay) - ay * (bx * bx + by * by)) / d
    uy = (ax * (bx * bx + by * by) - bx * (ax * ax + ay * ay)) / d
    return a[0] + ux, a[1] + uy, math.hypot(ux, uy)


def smallest_circle(points: np.ndarray) -> tuple[float, float, float]:
    """Smallest enclosing circle by incremental insertion, its radius widened a little so that no point lies outside."""
    p = sorted(set(map(tuple, np.asarray(points, float).tolist())))
    random.Random(len(p)).shuffle(p)
    c = (p[0][0], p[0][1], 0.0)

    def out(q: tuple[float, float]) -> bool:
        return math.hypot(q[0] - c[0], q[1] - c[1]) > c[2] * (1 + 1e-12) + 1e-12

    for i in range(1, len(p)):
        if not out(p[i]):
            continue
        c = (p[i][0], p[i][1], 0.0)
        for j in range(i):
            if not out(p[j]):
                continue
            c = _two(p[i], p[j])
            for k in range(j):
                if out(p[k]):
                    c = _three(p[i], p[j], p[k]) or c
    r = max(math.hypot(x - c[0], y - c[1]) for x, y in p)
    return c[0], c[1], r * (1 + 1e-9)


def enclosing_circle(x: Column, y: Column) -> Column:
    """Aggregate of a group's points: array of centre x, centre y and radius of the smallest enclosing circle."""

    def agg(xs: pd.Series, ys: pd.Series) -> list:
        return list(smallest_circle(np.stack([xs.to_numpy(float), ys.to_numpy(float)], 1)))

    agg.__annotations__ = {"xs": pd.Series, "ys": pd.Series, "return": list}
    return F.pandas_udf(agg, "array<double>", F.PandasUDFType.GROUPED_AGG)(x, y)


def cells_of_circle(x: Column, y: Column, r: Column, side: float) -> Column:
    """Array of the grid cells (cx, cy) that the box around a circle meets."""
    low = lambda c: F.floor((c - r) / side).cast("long")
    high = lambda c: F.floor((c + r) / side).cast("long")
    return F.flatten(F.transform(F.sequence(low(x), high(x)), lambda i: F.transform(F.sequence(low(y), high(y)), lambda j: F.struct(i.alias("cx"), j.alias("cy")))))
