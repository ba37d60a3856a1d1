"""Choice between labels of all vertices and an expansion from the queries."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from ..network import RoadNetwork


@dataclass(frozen=True)
class PlanChoice:
    """Chosen plan and the work it was chosen by: vertices settled for labels of all vertices, and by the expansion."""

    plan: str
    label_work: float
    expand_work: float


def choose_plan(net: RoadNetwork, facilities: DataFrame, queries: DataFrame, k: int, objects: DataFrame | None = None, sizes: tuple[int, int] | None = None) -> PlanChoice:
    """Estimate the work of the plans from counts of vertices, facilities, queries and objects.

    A search for the k nearest facilities settles about k * n / F vertices, and labels of all
    vertices take n such searches. An expansion reaches, from each query, the vertices that have it
    among their k nearest, about k * n / F of them and a border around, and searches each distinct
    one; its candidates are tested one by one. Where labels of all vertices are made, few objects
    are ranked by them (flood), and more objects than edges meet the intervals of their edges (region).
    ``sizes`` are the numbers of vertices and facilities, where they are known.
    """
    n, f = sizes or (net.vertices.count(), facilities.count())
    f, b = max(f, 1), queries.count()
    area = k * n / f
    search = 1 + area
    label_work = n * search
    expand_work = min(n, b * (area + 4 * area**0.5)) * search + b * area
    if expand_work < label_work / 2:
        return PlanChoice("expand", label_work, expand_work)
    many = objects is not None and objects.count() > net.edges.count()
    return PlanChoice("region" if many else "flood", label_work, expand_work)
