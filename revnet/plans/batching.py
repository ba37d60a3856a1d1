"""Batches of queries that lie close together, so that their searches share more."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def z_order(x: Column, y: Column, bits: int = 16) -> Column:
    """Interleaved bits of two non-negative coordinates: near points have near keys."""
    out = F.lit(0).cast("long")
    for i in range(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftright(x, i).bitwiseAND(F.lit(1)), 2 * i)).bitwiseOR(F.shiftleft(F.shiftright(y, i).bitwiseAND(F.lit(1)), 2 * i + 1))
    return out


def waves(queries: DataFrame, vertices: DataFrame, count: int, bits: int = 16) -> DataFrame:
    """``(q, wave)``: the batch cut along a space-filling order into ``count`` waves of nearly equal size.

    Wave borders are percentiles of the key, so no task sorts the whole batch.
    """
    box = vertices.agg(F.min("x").alias("x0"), F.min("y").alias("y0"), F.max("x").alias("x1"), F.max("y").alias("y1")).first()
    if box.x0 is None:
        return queries.select("q", F.lit(0).alias("wave"))
    cell = max(box.x1 - box.x0, box.y1 - box.y0, 1) // (1 << bits) + 1
    at = queries.select("q").distinct().join(vertices.withColumnRenamed("v", "q"), "q")
    key = z_order(F.expr(f"cast((x - {box.x0}) div {cell} as long)"), F.expr(f"cast((y - {box.y0}) div {cell} as long)"), bits)
    at = at.withColumn("key", key)
    cuts = at.agg(F.percentile_approx("key", [i / count for i in range(1, count)] or [0.5], 10_000).alias("c")).first().c or []
    wave = F.lit(0)
    for c in cuts[: count - 1]:
        wave = wave + F.when(F.col("key") > F.lit(c), 1).otherwise(0)
    return at.select("q", wave.alias("wave"))
