"""Small worked examples as literal tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .network import RoadNetwork


def example(spark: SparkSession, vertices: list[tuple], edges: list[tuple], facilities: list[int], queries: list[int], objects: list[tuple]) -> tuple[RoadNetwork, DataFrame, DataFrame, DataFrame]:
    """Network, facilities, batch and objects from (v, x, y), (eid, u, v, w), ids and (m, eid, off)."""
    v = spark.createDataFrame(vertices, "v long, x long, y long")
    e = spark.createDataFrame(edges, "eid long, u long, v long, w long")
    f = v.where(v.v.isin(facilities)).selectExpr("v as f", "x", "y")
    return RoadNetwork(v, e), f, spark.createDataFrame([(q,) for q in queries], "q long"), spark.createDataFrame(objects, "m long, eid long, off long")


def delivery(spark: SparkSession):
    """Four sites on a line and four vehicles between them (k = 2)."""
    return example(
        spark, [(1, 4, 0), (2, 0, 0), (3, 12, 0), (4, 8, 0)], [(12, 1, 2, 4), (14, 1, 4, 4), (34, 3, 4, 4)], [1, 2, 3, 4], [1, 2, 3, 4],
        [(1, 12, 1), (2, 14, 1), (3, 34, 3), (4, 34, 1)],
    )


def pruning(spark: SparkSession):
    """Two facilities on a tree; objects stand on its vertices (k = 1)."""
    return example(
        spark, [(0, 0, 0), (1, -6, 0), (3, 2, 0), (4, 5, 0), (5, 5, 2), (6, 7, 0)], [(1, 0, 1, 6), (3, 0, 3, 2), (34, 3, 4, 3), (45, 4, 5, 2), (46, 4, 6, 2)], [0, 5], [0],
        [(1, 1, 6), (3, 3, 2), (4, 34, 3), (5, 45, 2), (6, 46, 2)],
    )


def second_route(spark: SparkSession):
    """A vertex behind a stopped one that is reached again by a longer road (k = 1)."""
    return example(
        spark, [(0, 0, 0), (3, 3, 0), (4, 4, 0), (5, 3, 1)], [(3, 0, 3, 3), (4, 0, 4, 7), (34, 3, 4, 1), (35, 3, 5, 1)], [0, 5], [0],
        [(1, 3, 3), (2, 34, 1), (3, 4, 7), (4, 4, 1)],
    )
