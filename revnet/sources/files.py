"""Road files as sources, results as sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..network import RoadNetwork

VERTEX_SCHEMA = "v long, x long, y long"
EDGE_SCHEMA = "eid long, u long, v long, w long"


def _edges(arcs: DataFrame) -> DataFrame:
    """Undirected edges of arcs ``(a, b, w)``, each once with its smallest weight; loops are left out."""
    e = arcs.select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"), "w").where("u < v and w > 0")
    return e.groupBy("u", "v").agg(F.min("w").alias("w")).select(F.expr("shiftleft(u, 31) + v").alias("eid"), "u", "v", "w")


def read_text_network(spark: SparkSession, coordinates: str, arcs: str) -> RoadNetwork:
    """Network from line files: ``v id x y`` for coordinates, ``a from to weight`` for arcs; other lines are comments.

    Both directions of a road may be listed; ids stay below 2**31.
    """
    field = lambda i: F.split(F.trim("value"), r"\s+")[i].cast("long")
    v = spark.read.text(coordinates).where("trim(value) like 'v %'").select(field(1).alias("v"), field(2).alias("x"), field(3).alias("y"))
    a = spark.read.text(arcs).where("trim(value) like 'a %'").select(field(1).alias("a"), field(2).alias("b"), field(3).alias("w"))
    return RoadNetwork(v, _edges(a))


def read_network(spark: SparkSession, vertices: str, edges: str, kind: str = "parquet") -> RoadNetwork:
    """Network from Parquet, CSV (with header) or JSON files of the two schemas."""
    reader = lambda schema: spark.read.schema(schema).option("header", "true").format(kind)
    return RoadNetwork(reader(VERTEX_SCHEMA).load(vertices), reader(EDGE_SCHEMA).load(edges))


def with_tile(df: DataFrame, vertices: DataFrame, vertex: str, side: int) -> DataFrame:
    """``df`` with the plane tile of one of its vertex columns, to partition files by."""
    t = vertices.select(F.col("v").alias(vertex), F.concat_ws("_", F.floor(F.col("x") / side).cast("string"), F.floor(F.col("y") / side).cast("string")).alias("tile"))
    return df.join(t, vertex)


def write_answers(result: DataFrame, vertices: DataFrame, path: str, side: int = 100_000) -> None:
    """Answers as Parquet, partitioned by the tile of their query, so that a region's answers are read alone."""
    with_tile(result, vertices, "q", side).write.mode("overwrite").partitionBy("tile").parquet(path)


def save_arcs(net: RoadNetwork, table: str, buckets: int) -> DataFrame:
    """Arcs as a table bucketed by their start, so that expansions shuffle only their labels."""
    net.arcs.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)
    return net.arcs.sparkSession.table(table)
