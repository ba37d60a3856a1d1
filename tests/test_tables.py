"""Queries on the smallest tables: equality of plans, oracles, counters, plans free of products and row UDFs."""

import math
import random
from dataclasses import replace

import duckdb
import pandas as pd
import pytest

from revnet import relational, workloads
from revnet.metrics import growth, run_stats, same_answers
from revnet.operators import baselines as B
from revnet.operators.batch import run_batch
from revnet.operators.count_tree import build_count_tree, range_count, range_search
from revnet.operators.distance import located
from revnet.operators.flood import knn_from_objects, vertex_knn
from revnet.operators.verify import DistanceCache, quick_reject
from revnet.plans.options import FAITHFUL, RknnOptions
from revnet.plans.planner import choose_plan
from revnet.plans.storage import stored
from revnet.sources import tables as T
from revnet.streaming import queries as streams
from revnet.workloads import Setting

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def setting(spark):
    return Setting(spark, SF)


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from read_parquet('{SF}/{t}.parquet')")
    return con


def rows(df: pd.DataFrame) -> list:
    df = df[sorted(df.columns)]
    return sorted(map(tuple, df.astype(str).values.tolist()))


KEYS = ["objects_placed", "batch_rknn_default", "batch_rknn_expand", "batch_rknn_ties", "batch_size_sweep", "obo_vs_shared_counts", "hop_limited", "networks_region", "rknn_table_function", "snapshot_rknn"]


@pytest.mark.parametrize("key", KEYS)
def test_workloads_match_sql(spark, duck, key):
    got = workloads.queries()[key](spark, SF).toPandas()
    assert rows(got) == rows(duck.sql(workloads.oracle_sql()[key]).df())


@pytest.mark.parametrize("key", ["op_asof_position", "op_range_join_grid", "op_udtf_cells", "op_lateral_nearest"])
def test_relational_match_sql(spark, duck, key):
    got = relational.queries()[key](spark, SF).toPandas()
    assert rows(got) == rows(duck.sql(relational.oracle_sql()[key]).df())


@pytest.mark.parametrize("key", ["st_session", "st_latest_state", "st_batch_rknn", "st_safe_region"])
def test_streams_match_sql(spark, duck, key):
    got = streams.queries()[key](spark, SF).toPandas()
    assert rows(got) == rows(duck.sql(streams.oracle_sql()[key]).df())


def test_variants_agree_and_sharing_saves(setting):
    s, base = setting, None
    stats = {}
    shared = RknnOptions(plan="expand", cache_key="object")
    for name, o in {"flood": RknnOptions(plan="flood"), "shared": shared, "single": replace(shared, share=False), "plain": replace(shared, quick=False),
                    "vertex": RknnOptions(plan="expand"), "box": replace(shared, bound="mbr"), "faithful": FAITHFUL}.items():
        run = s.run(o)
        got = stored(run.result.select("q", "m", "net_dist"), "answers")
        base = got if base is None else base
        assert same_answers(got, base), name
        if run.candidates is not None:
            stats[name] = {r.metric: r.value for r in run_stats(run).collect()}
            assert run.cache.filled == stats[name]["searches"]
        run.close()
    assert stats["shared"]["searches"] < stats["single"]["searches"] == stats["single"]["lookups"]
    assert stats["shared"]["searches"] == stats["shared"]["lookup_objects"] < stats["plain"]["searches"]
    assert stats["shared"]["searches"] == stats["box"]["searches"]  # exact counts do not depend on the nodes' shape
    assert stats["shared"]["grow_searches"] < stats["single"]["grow_searches"] == stats["single"]["labels"]
    assert stats["vertex"]["searches"] == 0  # the expansion has met all lists that the exact test needs
    assert stats["shared"]["candidates"] < stats["faithful"]["candidates"]


def test_whole_rows_agree_across_plans(setting):
    for ties in ("by_id", "inclusive"):
        runs = [setting.batch(RknnOptions(k=4, plan=p, ties=ties, ranks=True)).select("q", "m", "net_dist", "rk") for p in ("flood", "region", "expand")]
        assert same_answers(runs[0], runs[1]) and same_answers(runs[0], runs[2])


def test_searches_too_wide_for_tasks_go_on_in_rounds(setting, monkeypatch):
    from revnet.operators import halo

    s = setting
    want = s.batch(RknnOptions(k=3, plan="flood"))
    monkeypatch.setattr(halo, "REGION_LIMIT", 1)
    monkeypatch.setattr(halo.TiledNetwork, "first_halo", lambda self, k: 1500)
    tight = halo.tile_network(s.net, s.facilities, 16)
    for o in (RknnOptions(k=3, plan="expand"), RknnOptions(k=3, plan="expand", cache_key="object")):
        assert same_answers(run_batch(s.net, s.facilities, s.sites, s.objects, o, tiled=tight).result, want)
    assert same_answers(halo.halo_knn(tight, 3).select("v", "f", "d", "rk"), vertex_knn(s.net, s.facilities, 3))


def test_baselines_agree(setting):
    s = setting
    base = s.batch(RknnOptions(k=3, plan="flood"))
    for got in (
        B.naive_rknn(s.net, s.facilities, s.sites, s.objects, 3), B.eager_expand_rknn(s.net, s.facilities, s.sites, s.objects, 3),
        B.hub_rknn(s.net, B.build_hub_labels(s.net, 32), s.facilities, s.sites, s.objects, 3), B.hub_rknn(s.net, B.build_hub_labels(s.net, 32, 80), s.facilities, s.sites, s.objects, 3),
        B.shortcut_rknn(s.net, [B.grid_cells(s.net, 3000), B.grid_cells(s.net, 6000)], s.facilities, s.sites, s.objects, 3),
    ):
        assert same_answers(got.select("q", "m", "net_dist"), base)


def test_networks_answer_their_largest_batch_alone(spark, duck, monkeypatch):
    """Baselines on all nets get the queries that are reported, not all sites, and no objects off the roads they meet."""
    monkeypatch.setattr(workloads, "NETS", ("thinned",))
    asked, placed = [], []

    def method(s, q):
        asked.append((q.count(), s.sites.count()))

        def near(v):
            placed.append((s.objects_near(v).count(), s.objects.count()))
            return s.objects_near(v)

        return B.eager_expand_rknn(s.net, s.facilities, q, near, 10, tiled=s.tiled)

    got = workloads._compared(spark, SF, method, (2, 4))
    assert sorted(map(tuple, got.collect())) == sorted(duck.sql(workloads._networks_sql((2, 4))).select(", ".join(got.columns)).fetchall())
    assert all(0 < n <= 4 < every for n, every in asked)
    assert all(n <= every for n, every in placed) and sum(n for n, _ in placed) < sum(every for _, every in placed)


def test_objects_near_roads_give_the_same_answers(setting):
    s = setting
    o = RknnOptions(k=3, plan="expand", ends=True, quick=False)
    assert same_answers(run_batch(s.net, s.facilities, s.sites, s.objects_near, o, tiled=s.tiled).result, s.batch(o))
    arcs = lambda df: sorted((r.v, *x) for r in df.collect() for x in zip(r.dst, r.w, strict=True))
    assert arcs(type(s.net)(s.net.vertices, s.net.edges).lists()) == sorted(map(tuple, s.net.arcs.select("src", "dst", "w").collect()))


def test_circle_counts_bound_ranks(setting):
    """A circle that just holds q never counts fewer facilities than the network rank says; counts equal the points found."""
    s = setting
    near = knn_from_objects(s.objects, s.net, s.facilities, 5)
    at = near.join(located(s.objects, s.net), "m").selectExpr("struct(m, f) as id", "px", "py", "d * 1.000001 as r", "rk")
    tree = build_count_tree(s.facilities, 4, 8)
    exact = range_count(tree, at, "mbc")
    assert exact.join(at.select("id", "rk"), "id").where("cnt < rk").isEmpty()
    for bound in ("mbr", "both"):
        assert same_answers(range_count(tree, at, bound).select("id", "cnt"), exact.select("id", "cnt"))
    assert range_count(tree, at, "mbc", "upper").join(exact.withColumnRenamed("cnt", "e"), "id").where("cnt < e").isEmpty()
    found = range_search(tree, at).groupBy("id").count()
    assert found.join(exact, "id").where("count <> cnt").isEmpty()


def test_quick_reject_is_sound(setting):
    from revnet.operators.distance import network_distance
    from revnet.operators.verify import candidates
    from revnet.operators.expand import pruned_expand

    s = setting
    lab = pruned_expand(s.net, s.facilities, s.sites, 3, ("path_count",)).labels
    cand = candidates(lab, s.objects, s.net)
    marks = network_distance(s.net, s.net.vertices.where("v % 60 = 0").selectExpr("v as s", "v", "0L as d"))
    marks = stored(marks, "marks")
    cand = stored(cand, "cand")
    cand = cand.select("q", "m")
    out = quick_reject(cand, s.objects, s.net, marks, s.facilities, 3)
    true = run_batch(s.net, s.facilities, s.sites, s.objects, RknnOptions(k=3, plan="flood")).result
    assert out.join(true, ["q", "m"], "left_semi").isEmpty()


def test_cache_hits_and_clearing(setting):
    s = setting
    c = DistanceCache(s.net, s.facilities, 4, key="object")
    first = s.objects.where("m < 50")
    assert c.fill(first) == 50 and c.fill(first) == 0
    assert c.hits(s.objects).count() == 50 and c.missing(s.objects.where("m < 60")).count() == 10
    assert c.export().count() == 50
    c.clear()
    assert c.lookup(first).isEmpty()


def test_answers_grow_with_k_and_add_up(setting):
    s = setting
    everyone = s.facilities.selectExpr("f as q")
    two = run_batch(s.net, s.facilities, everyone, s.objects, RknnOptions(k=2, plan="flood")).result
    three = run_batch(s.net, s.facilities, everyone, s.objects, RknnOptions(k=3, plan="flood")).result
    assert two.count() == 2 * s.objects.count()
    assert two.select("q", "m").exceptAll(three.select("q", "m")).isEmpty()


def test_planner_prefers_floods_for_wide_batches(setting):
    s = setting
    assert choose_plan(s.net, s.facilities, s.facilities.selectExpr("f as q"), 10).plan == "flood"
    assert choose_plan(s.net, s.facilities, s.sites.limit(1), 2).plan == "expand"
    assert choose_plan(s.net, s.facilities, s.facilities.selectExpr("f as q"), 10, s.objects).plan == "region"


def test_growth_ratios(spark):
    df = spark.createDataFrame([("a", 10, 5), ("a", 100, 20)], "name string, size long, value long")
    assert growth(df).where("size = 100").first().value_ratio == 4000


def test_plans_have_no_products_and_push_filters(spark, setting):
    s = setting
    run = run_batch(s.net, s.facilities, s.sites, s.objects, RknnOptions(plan="flood"))
    text = run.result._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "NestedLoop" not in text and "BatchEvalPython" not in text
    box = T.table(spark, SF, "part").where("p_partkey between 5 and 9").select("p_partkey")
    plan = box._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(p_partkey)" in plan and "ReadSchema: struct<p_partkey" in plan


def test_vertex_knn_of_irregular_net(spark):
    s = Setting(spark, SF, "irregular")
    assert vertex_knn(s.net, s.facilities, 4).groupBy("v").count().where("count <> 4").isEmpty()


def test_nearest_site_far_and_tied(spark):
    from revnet.operators.nearest import nearest_site

    r = random.Random(4)
    at = [(v, r.randrange(400), r.randrange(400)) for v in range(60)] + [(90, 50_000, 50_000), (91, 50_000, 50_000), (92, -7, -9)]
    spots = [(m, r.randrange(-500, 3000), r.randrange(-500, 3000)) for m in range(300)] + [(900, 49_000, 51_000), (901, at[0][1], at[0][2])]
    got = nearest_site(spark.createDataFrame(spots, "m long, px long, py long"), spark.createDataFrame(at, "v long, x long, y long"))
    want = [(m, *min(((px - x) ** 2 + (py - y) ** 2, v) for v, x, y in at)[::-1]) for m, px, py in spots]
    assert sorted((x.m, x.q, x.d2) for x in got.collect()) == want
    none = spark.createDataFrame([], "v long, x long, y long")
    assert nearest_site(spark.createDataFrame(spots, "m long, px long, py long"), none).count() == 0


def test_tree_leaves_are_made_in_batches(spark, monkeypatch):
    from revnet.functions.geometry import smallest_circle
    from revnet.operators import count_tree

    plans = []
    monkeypatch.setattr(count_tree, "stored", lambda df, label: plans.append(df._jdf.queryExecution().toString()) or stored(df, label))
    r = random.Random(1)
    at = [(i, r.randrange(6000), r.randrange(6000)) for i in range(3000)]
    tree = build_count_tree(spark.createDataFrame(at, "f long, x long, y long"))
    assert not any("FlatMapGroupsInPandas" in p for p in plans)  # no frame of its own for each leaf
    leaves = {x.node: x for x in tree.levels[0].collect()}
    inside = tree.points.collect()
    assert len(inside) == 3000 == sum(x.cnt for x in leaves.values())
    assert all(math.hypot(p.x - leaves[p.node].cx, p.y - leaves[p.node].cy) <= leaves[p.node].cr for p in inside)
    assert smallest_circle([(5, 5)] * 4)[:2] == (5, 5)


def test_bounded_overlay_distances_are_the_near_ones(setting):
    s = setting
    cells, q = B.grid_cells(s.net, 3000), s.sites.selectExpr("q as s").limit(4)
    got = B.overlay_distance(s.net, cells, q, bound=4000)
    assert same_answers(got, B.overlay_distance(s.net, cells, q).where("d <= 4000")) and not got.isEmpty()


def test_hub_labels_widen_until_all_lists_are_whole(setting):
    s = setting
    got = B.hub_rknn_widening(s.net, s.facilities, s.sites, s.objects, 3, bound=900, cell=32)
    assert same_answers(got.select("q", "m", "net_dist"), s.batch(RknnOptions(k=3, plan="flood")))


def test_bounded_hub_labels_of_wide_cells_come_from_tiles(setting, monkeypatch):
    """Cells too large for a task are searched around their hubs, without rounds; their cells come in one plan of joins."""
    s = setting
    want = s.batch(RknnOptions(k=3, plan="flood"))
    cuts = B.separator_levels(s.net, 16, 100)
    one = B.separator_levels(s.net, 16)
    assert cuts[2] == one[2] == 4 and same_answers(cuts[1], one[1]) and same_answers(cuts[0], one[0])
    inside = cuts[1].groupBy("cell").count().agg({"count": "max"}).first()[0]
    assert inside <= 16
    ends = cuts[1].select("v", "cell").toPandas().set_index("v")["cell"].to_dict()
    hubs = {tuple(r) for r in cuts[0].collect()}
    for r in s.net.edges.collect():
        a, b, level = ends[r.u], ends[r.v], cuts[2]
        while a != b:
            a, b, level = a >> 1, b >> 1, level - 1
        assert (r.u, level, a) in hubs
    monkeypatch.setattr(B, "network_distance", None)  # no rounds
    bound = 6000
    labels = B.build_hub_labels(s.net, 16, 5000, bound, cuts, tile_vertices=30)
    lists = B.hub_knn(labels, s.facilities, 3)
    near = lists.where(f"d <= {bound}")
    assert same_answers(near.select("v", "f", "d"), vertex_knn(s.net, s.facilities, 3).where(f"d <= {bound}").select("v", "f", "d"))
    monkeypatch.setattr(B, "build_hub_labels", lambda net, cell, bound, separators, f=B.build_hub_labels: f(net, cell, 5000, bound, separators, 30))
    assert same_answers(B.hub_rknn_widening(s.net, s.facilities, s.sites, s.objects, 3, cell=16).select("q", "m", "net_dist"), want)


def test_expansions_without_stops_cross_large_networks_in_blocks(spark, setting, monkeypatch):
    """Networks too large for a task: no rounds over single roads, and the labels, candidates and answers of small ones."""
    from revnet.operators import expand as X
    from revnet.operators.halo import expand_free, tile_network

    s = setting
    q = stored(s.sites.limit(3), "three")
    rules = ((), ("path_count",), ("ancestor",))
    opts = {r: RknnOptions(k=3, plan="expand", rules=r, ends=True, quick=False) for r in rules}
    want = {r: s.run(o, q) for r, o in opts.items()}
    stats = {r: sorted(map(tuple, run_stats(x).where("metric in ('labels', 'candidates')").collect())) for r, x in want.items()}
    free, wide = X.expand(s.tiled, q, 3, ()).labels, X.expand(s.tiled, q, 3, (), max_radius=4000).labels
    monkeypatch.setattr(X, "REGION_LIMIT", 10)
    monkeypatch.setattr(X, "pruned_expand", None)
    for r, o in opts.items():
        got = s.run(o, q)
        assert same_answers(got.result, want[r].result), r
        assert sorted(map(tuple, run_stats(got).where("metric in ('labels', 'candidates')").collect())) == stats[r], r
        assert same_answers(got.expansion.labels, want[r].expansion.labels), r
    t = tile_network(s.net, s.facilities, 9)
    got, rounds = expand_free(t, q, block=40, per_task=2)
    assert same_answers(got, free) and 2 < rounds < 30
    assert same_answers(expand_free(t, q, 4000, block=40)[0], wide)


def test_expansions_without_stops_run_in_tasks(setting, monkeypatch):
    from revnet.operators import expand as X

    s = setting
    q, lists = s.sites.limit(3), vertex_knn(s.net, s.facilities, 3)
    want = {r: X.pruned_expand(s.net, s.facilities, q, 3, r, "by_id", lists).labels for r in (("path_count",), ("ancestor",))}
    monkeypatch.setattr(X, "pruned_expand", None)
    for rules, labels in want.items():
        assert same_answers(X.expand(s.tiled, q, 3, rules).labels.select("q", "v", "d"), labels.select("q", "v", "d")), rules


def test_table_function_reads_tiles_of_large_networks(spark, setting):
    """Above its limit the function takes roads and objects from tiles in the shared folder and answers the same."""
    from revnet.functions.tables import register_rknn

    s = setting
    call = "select site as q, m, net_dist from values (0L), (7L), (150L), (999999L) t(site), lateral rknn_of(site, 10)"
    register_rknn(spark, s.net, s.facilities, s.objects)
    want = stored(spark.sql(call), "held")
    register_rknn(spark, s.net, s.facilities, s.objects, limit=100)
    got = stored(spark.sql(call), "tiles")
    assert not want.isEmpty() and same_answers(got, want)


def test_table_function_forgets_tiles(spark, setting):
    """Searches that cross more tiles than are kept find the same."""
    from revnet.functions.tables import _Facilities, _Objects, _Tiles, _write_tiles
    from revnet.operators.halo import Region

    s = setting
    tiles = _Tiles(_write_tiles(spark, s.net, s.facilities, s.objects, 16), held=1)
    whole = Region.of({r.v: [] for r in s.net.vertices.collect()}, {r.f for r in s.facilities.collect()})
    for r in s.net.arcs.collect():
        whole.out[r.src].append((r.dst, r.w))
    paged = Region.of(tiles, _Facilities(tiles))
    for v in (0, 55, 199):
        assert paged.nearest([(0, v)], 150, "by_id") == whole.nearest([(0, v)], 150, "by_id")
    assert len(tiles.tiles) == 1 and sum(len(_Objects(tiles).get(v)) for v in whole.out) == 2 * s.objects.count()


def test_circle_counts_from_mapped_files_equal_joins(spark, setting, monkeypatch):
    """Counts and nodes looked at are those of the tree's tables, for all shapes and modes, also in small slices and for ids that repeat."""
    from revnet.operators import count_tree

    s = setting
    at = located(s.objects, s.net).selectExpr("m as id", "px", "py", "cast(m * 13 % 9000 as double) as r")
    at = at.unionByName(at.where("id < 5")).unionByName(spark.createDataFrame([(-1, 0.0, 0.0, None), (-2, 0.0, 0.0, 1e9)], at.schema))
    at, tree = stored(at, "circles"), build_count_tree(s.facilities, 4, 8)
    assert tree.files is not None
    packed = count_tree.PackedTree(tree.files, tree.depth)
    frame = at.toPandas()
    x, y, r = (frame[c].to_numpy(float) for c in ("px", "py", "r"))
    for bound in ("mbc", "mbr", "both"):
        for mode in ("exact", "upper"):
            got = range_count(tree, at, bound, mode)
            assert "Join" not in got._jdf.queryExecution().toString()  # before, every circle met every level by a join
            assert same_answers(got, count_tree.count_by_joins(tree, at, bound, mode)), (bound, mode)
        whole = packed.count(x, y, r, bound, "exact")
        monkeypatch.setattr(count_tree, "_PAIRS", 50)
        assert all((a == b).all() for a, b in zip(packed.count(x, y, r, bound, "exact"), whole))
        monkeypatch.undo()
