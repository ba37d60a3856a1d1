"""Snapshots of moving objects, and reports on answers."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def snapshot(updates: DataFrame, as_of: str) -> DataFrame:
    """The latest position ``(m, eid, off)`` of every object up to a time; equal times by the greater event id.

    One maximum per object, combined before the exchange, instead of a sort of its history.
    """
    u = updates.where(F.col("ts") <= F.lit(as_of).cast("timestamp"))
    last = u.groupBy("m").agg(F.max_by(F.struct("eid", "off"), F.struct("ts", "event_id")).alias("p"))
    return last.select("m", "p.eid", "p.off")


def as_of_positions(updates: DataFrame, marks: DataFrame) -> DataFrame:
    """``(m, mark, eid, off)``: each object's position at each of ``marks(mark)``, by one pass over the union of both."""
    u = updates.select("m", F.col("ts").alias("t"), "event_id", F.struct("eid", "off").alias("p"))
    ids = updates.select("m").distinct()
    k = ids.join(F.broadcast(marks)).select("m", F.col("mark").alias("t"), F.lit(1 << 62).alias("event_id"), F.lit(None).cast(u.schema["p"].dataType).alias("p"))
    last = F.expr("last(p, true) over (partition by m order by t, event_id rows between unbounded preceding and current row)")
    return u.unionByName(k).withColumn("at", last).where("p is null and at is not null").select("m", F.col("t").alias("mark"), "at.eid", "at.off")


def shortage(result: DataFrame, suppliers: DataFrame, nations: DataFrame, n: int) -> DataFrame:
    """Per nation of the sites: sites, answers, the fewest of one site, and sites without any."""
    own = suppliers.groupBy(F.expr(f"(cast(s_suppkey as long) * 7919) % {n}").alias("q")).agg(F.min("s_nationkey").alias("n_nationkey"))
    per = own.join(result.groupBy("q").agg(F.count(F.lit(1)).alias("answers")), "q", "left").withColumn("answers", F.coalesce("answers", F.lit(0)))
    named = per.join(nations.select("n_nationkey", "n_name"), "n_nationkey")
    return named.groupBy(F.col("n_name").alias("nation")).agg(
        F.count(F.lit(1)).alias("sites"), F.sum("answers").cast("long").alias("answers"), F.min("answers").cast("long").alias("fewest"),
        F.sum((F.col("answers") == 0).cast("long")).alias("empty_sites"),
    )


def order_assignment(result: DataFrame) -> DataFrame:
    """``(m, q, net_dist)``: each answered object's nearest site of the batch, ties by id."""
    best = result.groupBy("m").agg(F.min(F.struct("net_dist", "q")).alias("b"))
    return best.select("m", "b.q", "b.net_dist")
