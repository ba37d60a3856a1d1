"""Measures of a batch run, as tables, and timers."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.batch import BatchRun


def run_stats(run: BatchRun) -> DataFrame:
    """``(metric, value LONG)`` of an expand run: candidates, lookups, searches, hits per 1000, tree nodes, labels, searches of the expansion.

    A lookup is an unresolved pair; ``searches`` are those that the cache really ran for them (of
    edge ends, objects or pairs, by its key), the hit rate is 1 - searches / lookups. ``grow_searches``
    are the searches for k nearest facilities of vertices that the expansion ran. The result must
    have been asked for, as that fills the cache.
    """
    c = run.candidates
    unknown = F.col("verdict") == "UNKNOWN"
    per = c.agg(
        F.count(F.lit(1)).alias("candidates"), F.countDistinct("m").alias("candidate_objects"), F.sum(unknown.cast("long")).alias("lookups"),
        F.countDistinct(F.when(unknown, F.col("m"))).alias("lookup_objects"), F.sum("nodes").alias("tree_nodes"),
    )
    per = per.withColumns({"searches": F.lit(run.cache.filled), "grow_searches": F.lit(run.expansion.searches)})
    per = per.withColumn("hits_per_1000", F.when(F.col("lookups") > 0, F.expr("greatest(0, (lookups - searches) * 1000 div lookups)")).otherwise(0))
    lab = run.expansion.labels.agg(F.count(F.lit(1)).alias("labels"), F.countDistinct("q").alias("queries"))
    row = per.crossJoin(F.broadcast(lab))  # one row each
    names = ["candidates", "candidate_objects", "lookups", "lookup_objects", "searches", "hits_per_1000", "tree_nodes", "labels", "queries", "grow_searches"]
    return row.select(F.explode(F.array([F.struct(F.lit(x).alias("metric"), F.coalesce(F.col(x), F.lit(0)).cast("long").alias("value")) for x in names])).alias("r")).select("r.*")


def explored_per_query(run: BatchRun) -> DataFrame:
    """``(q, vertices)``: labels each query's expansion left."""
    return run.expansion.labels.groupBy("q").agg(F.count(F.lit(1)).alias("vertices"))


def growth(series: DataFrame, group: str = "name", size: str = "size", value: str = "value") -> DataFrame:
    """Ratios to the step before, times 1000, of a series' sizes and values."""
    prev = lambda c: F.expr(f"lag({c}) over (partition by {group} order by {size})")
    return series.withColumn("size_ratio", F.expr(f"{size} * 1000 div lag({size}) over (partition by {group} order by {size})")).withColumn("value_ratio", (F.col(value) * 1000 / prev(value)).cast("long"))


def mean_response(seconds: float, queries: int) -> float:
    """Mean seconds per query of a batch."""
    return seconds / max(queries, 1)


def speed_up(base: float, other: float) -> float:
    """How many times faster ``base`` seconds are than ``other`` seconds."""
    return other / base if base > 0 else float("inf")


def same_answers(a: DataFrame, b: DataFrame) -> bool:
    """Whether two results hold the same rows, as often."""
    return a.exceptAll(b).isEmpty() and b.exceptAll(a).isEmpty()


def timed(make: Callable[[], DataFrame], repeats: int = 1) -> float:
    """Mean seconds to make and fully compute a result, without collecting it."""
    total = 0.0
    for _ in range(repeats):
        at = time.perf_counter()
        make().write.format("noop").mode("overwrite").save()
        total += time.perf_counter() - at
    return total / repeats


def timed_parts(prepare: Callable[[], object], online: Callable[[object], DataFrame]) -> tuple[float, float]:
    """Seconds of the preparation and of the query that uses it."""
    at = time.perf_counter()
    made = prepare()
    prep = time.perf_counter() - at
    return prep, timed(lambda: online(made))
