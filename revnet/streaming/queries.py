"""Stream queries that run to the end of the event files, with SQL of the same result."""

from __future__ import annotations

from pyspark.sql import functions as F

from .. import oracles as O
from ..plans.options import RknnOptions
from ..workloads import Setting
from . import streams as S

_U = O.prefix(objects="updates", k=None)


def _events(spark, d):
    return S.read_updates(spark, f"{d}/events.parquet")


def st_tumbling(spark, d):
    return S.finish(S.tumbling(_events(spark, d)), "complete").select(F.unix_seconds("start").alias("start"), "updates")


def st_sliding(spark, d):
    return S.finish(S.sliding(_events(spark, d)), "complete").select(F.unix_seconds("start").alias("start"), "event_type", "updates")


def st_session(spark, d):
    out = S.finish(S.sessions(_events(spark, d)), "complete")
    return out.select("user_id", F.unix_micros("start").alias("start"), F.unix_micros("end").alias("end"), "updates")


def st_dedup_late(spark, d):
    e = _events(spark, d)
    twice = e.unionByName(e.where("event_id % 3 = 0"))
    return S.finish(S.deduplicated(twice), "append").groupBy("event_type").agg(F.count(F.lit(1)).alias("updates"))


def st_latest_state(spark, d):
    s = Setting(spark, d)
    got = S.finish(S.latest_positions(S.positions(_events(spark, d), _static(s), s.n)), "update")
    last = got.groupBy("m").agg(F.max(F.struct("batch", "eid", "off")).alias("p"))
    return last.select("m", "p.eid", "p.off")


def _static(s: Setting):
    """The network as the stream's static side."""
    return s.net


def st_stream_static(spark, d):
    s = Setting(spark, d)
    p = S.positions(_events(spark, d), _static(s), s.n)
    return S.finish(p.select("m", "eid", "off", "event_id"), "append").groupBy("eid").agg(F.count(F.lit(1)).alias("updates"), F.sum("off").cast("long").alias("offs"))


def st_stream_stream(spark, d):
    kinds = sorted(r[0] for r in spark.read.parquet(f"{d}/events.parquet").select("event_type").distinct().collect())  # a handful of event types
    return S.finish(S.purchases_after_views(_events(spark, d), kinds[0], kinds[-1]), "append").select("a", "b")


def st_batch_rknn(spark, d):
    s = Setting(spark, d)
    out = S.batch_per_trigger(S.positions(_events(spark, d), _static(s), s.n), s.net, s.facilities, s.sites, RknnOptions(plan="flood"))
    last = out.agg(F.max("batch").alias("batch"))
    return out.join(F.broadcast(last), "batch", "left_semi").select("q", "m", "net_dist")


def st_safe_region(spark, d):
    s = Setting(spark, d)
    got = S.monitor_safe_regions(S.positions(_events(spark, d), _static(s), s.n), s.net, s.facilities, 3)
    return got.select("m", "eid", "off", "members")


def queries() -> dict:
    return {f.__name__: f for f in (st_tumbling, st_sliding, st_session, st_dedup_late, st_latest_state, st_stream_static, st_stream_stream, st_batch_rknn, st_safe_region)}


def oracle_sql() -> dict[str, str]:
    latest = O.prefix(objects="latest", extra=O.ANSWERS).replace(" WHERE ts <= TIMESTAMP '2024-01-16 00:00:00'", "")
    places = O.prefix(objects="latest", k=None).replace(" WHERE ts <= TIMESTAMP '2024-01-16 00:00:00'", "")
    sets = O.prefix(objects="latest", k=3).replace(" WHERE ts <= TIMESTAMP '2024-01-16 00:00:00'", "")
    return {
        "st_safe_region": f"{sets} SELECT m, eid, off, string_agg(CAST(f AS VARCHAR), ',' ORDER BY f) AS members FROM knn JOIN objects USING (m) GROUP BY m, eid, off",
        "st_tumbling": "SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) AS start, count(*) AS updates FROM events GROUP BY 1",
        "st_sliding": """SELECT CAST(epoch(date_trunc('hour', ts)) AS BIGINT) - h * 3600 AS start, event_type, count(*) AS updates
            FROM events, (SELECT unnest([0, 1]) AS h) GROUP BY 1, 2""",
        "st_session": """WITH a AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
            b AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM a)
            SELECT user_id, epoch_us(min(ts)) AS start, epoch_us(max(ts) + INTERVAL 6 HOUR) AS "end", count(*) AS updates FROM b GROUP BY user_id, s""",
        "st_dedup_late": "SELECT event_type, count(*) AS updates FROM events GROUP BY event_type",
        "st_latest_state": f"{places} SELECT m, eid, off FROM objects",
        "st_stream_static": f"{_U} SELECT eid, count(*) AS updates, CAST(sum(off) AS BIGINT) AS offs FROM objects GROUP BY eid",
        "st_stream_stream": """WITH k AS (SELECT min(event_type) AS lo, max(event_type) AS hi FROM events)
            SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR, k
            WHERE a.event_type = lo AND b.event_type = hi""",
        "st_batch_rknn": f"{latest} SELECT q, m, net_dist FROM answers",
    }
