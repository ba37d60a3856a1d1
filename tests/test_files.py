"""Sources, sinks, waves of queries and tile-local relaxation."""

from revnet.metrics import same_answers
from revnet.network import apply_weight_updates
from revnet.operators.baselines import grid_cells
from revnet.operators.batch import batch_rknn
from revnet.operators.flood import vertex_knn
from revnet.operators.tiles import tile_knn
from revnet.plans.batching import waves
from revnet.plans.options import RknnOptions
from revnet.sources.files import read_network, read_text_network, save_arcs, write_answers
from revnet.workloads import Setting

SF = "/root/testdata/sf0.001"


def test_text_files(spark, tmp_path):
    (tmp_path / "co").write_text("c comment\np aux\nv 1 0 0\nv 2 3 0\n v 3 9 0\n")
    (tmp_path / "gr").write_text("c comment\na 1 2 3\na 2 1 3\na 2 3 6\na 3 2 7\na 3 3 1\n")
    net = read_text_network(spark, str(tmp_path / "co"), str(tmp_path / "gr"))
    assert {(r.u, r.v, r.w) for r in net.edges.collect()} == {(1, 2, 3), (2, 3, 6)} and net.vertices.count() == 3
    net.validate()


def test_formats_round_trip(spark, tmp_path):
    net = Setting(spark, SF).net
    for kind in ("parquet", "csv", "json"):
        for name, df in (("v", net.vertices), ("e", net.edges)):
            df.write.option("header", "true").format(kind).save(f"{tmp_path}/{kind}-{name}")
        got = read_network(spark, f"{tmp_path}/{kind}-v", f"{tmp_path}/{kind}-e", kind)
        assert same_answers(got.edges, net.edges.select("eid", "u", "v", "w")) and same_answers(got.vertices, net.vertices)


def test_answers_are_partitioned_by_tile(spark, tmp_path):
    s = Setting(spark, SF)
    res = s.batch(RknnOptions(k=2, plan="flood"))
    write_answers(res, s.net.vertices, f"{tmp_path}/out", 5000)
    back = spark.read.parquet(f"{tmp_path}/out")
    assert back.count() == res.count() and "tile" in back.columns


def test_bucketed_arcs(spark):
    s = Setting(spark, SF)
    got = save_arcs(s.net, "road_arcs_bucketed", 4)
    assert same_answers(got.select("src", "dst", "w"), s.net.arcs)
    spark.sql("drop table road_arcs_bucketed")


def test_waves_cover_the_batch(spark):
    s = Setting(spark, SF)
    got = waves(s.sites, s.net.vertices, 2)
    assert got.count() == s.sites.count() and got.select("wave").distinct().count() == 2
    whole = s.batch(RknnOptions(k=3, plan="flood")).select("q", "m")
    parts = None
    for w in range(2):
        part = batch_rknn(s.net, s.facilities, got.where(f"wave = {w}"), s.objects, RknnOptions(k=3, plan="flood")).select("q", "m")
        parts = part if parts is None else parts.unionByName(part)
    assert same_answers(parts, whole)


def test_streams_go_on_after_a_restart(spark, tmp_path):
    from pyspark.sql import functions as F

    from revnet.streaming import streams as S

    s, events = Setting(spark, SF), spark.read.parquet(f"{SF}/events.parquet")
    cut = events.where("event_id % 3 = 0"), events.where("event_id % 3 <> 0")
    folder, got = f"{tmp_path}/in.parquet", {}
    for part in cut:
        part.coalesce(1).write.mode("append").parquet(folder)
        p = lambda: S.positions(S.read_updates(spark, folder), s.net, s.n)
        got["rknn"] = S.batch_per_trigger(p(), s.net, s.facilities, s.sites, RknnOptions(k=3, plan="flood"), f"{tmp_path}/rknn")
        got["safe"] = S.monitor_safe_regions(p(), s.net, s.facilities, 3, f"{tmp_path}/safe")
    assert S.stored_batches(spark, f"{tmp_path}/rknn/answers") == [0, 1]
    last = S.snapshot(Setting(spark, SF, obj_kind="updates").objects, "2030-01-01 00:00:00")
    want = batch_rknn(s.net, s.facilities, s.sites, last, RknnOptions(k=3, plan="flood")).select("q", "m", "net_dist")
    assert same_answers(got["rknn"].where("batch = 1").select("q", "m", "net_dist"), want)
    safe = got["safe"].select("m", F.explode(F.split("members", ",")).alias("q")).selectExpr("cast(q as long) q", "m").join(s.sites, "q", "left_semi")
    assert same_answers(safe, want.select("q", "m")) and got["safe"].agg(F.max("checked")).first()[0] <= 2


def test_tiles_equal_flood(spark):
    s = Setting(spark, SF)
    want = vertex_knn(s.net, s.facilities, 4)
    for side in (6000,):
        assert same_answers(tile_knn(s.net, grid_cells(s.net, side), s.facilities, 4).select("v", "f", "d", "rk"), want)


def test_weight_updates_make_a_new_snapshot(spark):
    s = Setting(spark, SF)
    up = s.net.edges.limit(1).selectExpr("eid", "w + 5 as w")
    new = apply_weight_updates(s.net, up)
    assert new.edges.exceptAll(s.net.edges.select("eid", "u", "v", "w")).count() == 1
