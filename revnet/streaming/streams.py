"""Streams of position updates: windows, late data, state, joins and batch queries per trigger."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..network import RoadNetwork
from ..operators.batch import run_batch
from ..operators.halo import search_sources, tile_network
from ..operators.regions import must_verify, safe_slack
from ..operators.snapshot import snapshot
from ..operators.verify import object_sources
from ..plans.options import RknnOptions
from ..plans.storage import shared_dir, stored
from ..sources.tables import place


def read_updates(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """A stream of event files, with ``ts`` as a timestamp."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path + "*").withColumn("ts", F.col("ts").cast("timestamp"))


def positions(events: DataFrame, net: RoadNetwork, n: int) -> DataFrame:
    """Events as position updates ``(m, eid, off, ts, event_id)``; works on streams, a join with the static network."""
    rows = events.selectExpr("cast(user_id as long) as m", f"(cast(user_id as long) * 48271 + event_id * 16807) % {n} as a", f"cast(event_id as long) div {n} as p", "cast(round(value * 100) as long) as z", "ts", "cast(event_id as long) as event_id")
    return place(rows, net, n)


def finish(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over all that is there and return its result table.

    Each trigger overwrites its own folder, so a repeated trigger changes nothing. In complete mode
    the last trigger holds the result, otherwise all of them together, with ``batch`` numbering them.
    """
    spark = stream.sparkSession
    top = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    seen: list[int] = []

    def keep(b: DataFrame, i: int) -> None:
        b.withColumn("batch", F.lit(i).cast("long")).write.mode("overwrite").parquet(f"{top}/out/{i}")
        seen.append(i)

    q = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{top}/state").foreachBatch(keep).start()
    q.awaitTermination()
    if not seen:
        return spark.createDataFrame([], stream.schema).withColumn("batch", F.lit(0).cast("long"))
    paths = [f"{top}/out/{i}" for i in ([max(seen)] if mode == "complete" else sorted(set(seen)))]
    return spark.read.parquet(*paths)


def tumbling(events: DataFrame, width: str = "1 hour") -> DataFrame:
    """Updates per window."""
    return events.groupBy(F.window("ts", width).alias("w")).agg(F.count(F.lit(1)).alias("updates")).select("w.start", "updates")


def sliding(events: DataFrame, width: str = "2 hours", step: str = "1 hour") -> DataFrame:
    """Updates per overlapping window and event type."""
    return events.groupBy(F.window("ts", width, step).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("updates")).select("w.start", "event_type", "updates")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    """Runs of a user's updates with no longer gap."""
    return events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("updates")).select("user_id", "w.start", "w.end", "updates")


def deduplicated(events: DataFrame, late: str = "2 days") -> DataFrame:
    """Updates without repeats that come within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


_STATE = "ts timestamp, event_id long, eid long, off long"


def _latest(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    if state.hasTimedOut:
        state.remove()
        return
    best = state.get if state.exists else None
    for b in batches:
        r = b.sort_values(["ts", "event_id"]).iloc[-1]
        new = (r["ts"].to_pydatetime(), int(r["event_id"]), int(r["eid"]), int(r["off"]))
        if best is None or (new[0], new[1]) > (best[0], best[1]):
            best = new
    state.update(best)
    state.setTimeoutTimestamp(max(int(best[0].timestamp() * 1000), state.getCurrentWatermarkMs()) + _KEPT_MS)
    yield pd.DataFrame({"m": [key[0]], "ts": [best[0]], "event_id": [best[1]], "eid": [best[2]], "off": [best[3]]})


_KEPT_MS = 90 * 86_400_000  # an object silent for so long is forgotten


def latest_positions(updates: DataFrame, late: str = "2 days") -> DataFrame:
    """Each object's latest position as state; an update older than the state changes nothing.

    State of an object ends 90 days of event time after its last update, so it is bounded by the objects of that time.
    """
    marked = updates.withWatermark("ts", late)
    return marked.groupBy("m").applyInPandasWithState(_latest, f"m long, {_STATE}", _STATE, "update", GroupStateTimeout.EventTimeTimeout)


def purchases_after_views(events: DataFrame, first: str, then: str, within: str = "1 hour") -> DataFrame:
    """Pairs of a user's events of two kinds, the second at most so long after the first; both sides' state is bounded by watermarks."""
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("u"), F.col("ts").alias("ta"), F.col("event_id").alias("a")).withWatermark("ta", "1 hour")
    b = events.where(F.col("event_type") == then).select("user_id", F.col("ts").alias("tb"), F.col("event_id").alias("b")).withWatermark("tb", "1 hour")
    return a.join(b, F.expr(f"u = user_id and tb >= ta and tb <= ta + interval {within}")).select("a", "b")


def stored_batches(spark: SparkSession, folder: str) -> list[int]:
    """Numbers of the triggers whose tables stand complete in a folder."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = path.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(path):
        return []
    return sorted(int(x.getPath().getName()) for x in fs.listStatus(path) if x.getPath().getName().isdigit() and fs.exists(spark._jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS")))


def _run_triggers(stream: DataFrame, top: str, answer) -> None:
    q = stream.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{top}/progress").foreachBatch(answer).start()
    q.awaitTermination()


def _merged(spark: SparkSession, new: DataFrame, folder: str, i: int) -> DataFrame:
    """Latest positions after trigger ``i``, from the last table before it; written to ``folder/i``."""
    new = new.select("m", "eid", "off", "ts", "event_id")
    before = [x for x in stored_batches(spark, folder) if x < i]
    if before:
        new = new.unionByName(spark.read.parquet(f"{folder}/{before[-1]}"))
    last = new.groupBy("m").agg(F.max(F.struct("ts", "event_id", "eid", "off")).alias("p")).select("m", "p.*")
    last.write.mode("overwrite").parquet(f"{folder}/{i}")
    return spark.read.parquet(f"{folder}/{i}")


def batch_per_trigger(updates: DataFrame, net: RoadNetwork, facilities: DataFrame, queries: DataFrame, options: RknnOptions, folder: str | None = None) -> DataFrame:
    """Answers ``(batch, q, m, net_dist)``: each trigger merges its updates into the positions and asks the batch anew.

    Positions and answers live under ``folder``, a table per trigger, each made from the last one
    before it that stands there; so a repeated trigger makes the same, and a stream that is started
    again with the same folder goes on where it ended. The distance cache starts empty in every trigger.
    """
    spark = updates.sparkSession
    top = folder or f"{shared_dir(spark)}/rknn-stream-{uuid.uuid4().hex}"

    def answer(b: DataFrame, i: int) -> None:
        objects = _merged(spark, b, f"{top}/positions", i).select("m", "eid", "off")
        run = run_batch(net, facilities, queries, objects, options)
        run.result.select(F.lit(i).cast("long").alias("batch"), "q", "m", "net_dist").write.mode("overwrite").parquet(f"{top}/answers/{i}")
        run.close()

    _run_triggers(updates, top, answer)
    done = stored_batches(spark, f"{top}/answers")
    if not done:
        return spark.createDataFrame([], "batch long, q long, m long, net_dist long")
    return spark.read.parquet(*[f"{top}/answers/{i}" for i in done])


_SAFE = "m long, eid long, off long, ts timestamp, event_id long, eid0 long, off0 long, twice_slack long, members string, checked long"


def monitor_safe_regions(updates: DataFrame, net: RoadNetwork, facilities: DataFrame, k: int, folder: str | None = None) -> DataFrame:
    """``(m, eid, off, members, checked)``: each object's latest position and k nearest facilities, and in how many triggers it was searched.

    With its list an object gets its place ``eid0, off0`` and slack. As long as it stays on that road and
    has moved by less than half the slack its set cannot have changed; only the others are searched
    again. State is a table per trigger under ``folder``, as in ``batch_per_trigger``.
    """
    spark = updates.sparkSession
    top = folder or f"{shared_dir(spark)}/safe-stream-{uuid.uuid4().hex}"
    tiled = tile_network(net, facilities)

    def step(b: DataFrame, i: int) -> None:
        at = _merged(spark, b, f"{top}/positions", i)
        before = [x for x in stored_batches(spark, f"{top}/safe") if x < i]
        old = spark.read.schema(_SAFE).parquet(f"{top}/safe/{before[-1]}") if before else spark.createDataFrame([], _SAFE)
        both = at.join(old.select("m", "eid0", "off0", "twice_slack", "members", "checked"), "m", "left")
        moved = both.where("eid = eid0").select("m", F.abs(F.col("off") - F.col("off0")).alias("distance"))
        stay = both.select("m").join(moved, "m", "left")  # another road counts as moved any distance
        must = must_verify(old, stay.withColumn("distance", F.coalesce("distance", F.lit(1 << 60))))
        must = stored(must, "must-verify")
        asked = at.join(must, "m", "left_semi")
        lists = search_sources(tiled, object_sources(asked.select("m", F.lit(-1).cast("long").alias("b"), "eid", "off"), net), k + 1)
        lists = stored(lists.withColumnRenamed("a", "m"), "monitor-lists")
        sets = lists.where(F.col("rk") <= k).groupBy("m").agg(F.concat_ws(",", F.transform(F.array_sort(F.collect_list("f")), lambda x: x.cast("string"))).alias("members"))
        fresh = asked.join(safe_slack(lists, k).select("m", "twice_slack"), "m", "left").join(sets, "m", "left").join(old.select("m", "checked"), "m", "left")
        fresh = fresh.select("m", "eid", "off", "ts", "event_id", F.col("eid").alias("eid0"), F.col("off").alias("off0"), "twice_slack", F.coalesce("members", F.lit("")).alias("members"), (F.coalesce("checked", F.lit(0)) + 1).cast("long").alias("checked"))
        kept = both.join(must, "m", "left_anti").select(fresh.columns)
        kept.unionByName(fresh).write.mode("overwrite").parquet(f"{top}/safe/{i}")

    _run_triggers(updates, top, step)
    done = stored_batches(spark, f"{top}/safe")
    last = spark.read.schema(_SAFE).parquet(f"{top}/safe/{done[-1]}") if done else spark.createDataFrame([], _SAFE)
    return last.select("m", "eid", "off", "members", "checked")


__all__ = ["batch_per_trigger", "deduplicated", "finish", "latest_positions", "monitor_safe_regions", "positions", "purchases_after_views", "read_updates", "sessions", "sliding", "snapshot", "tumbling"]
