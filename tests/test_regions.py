"""Runs of many edges at once, and regions searched in tiles, equal those of single edges."""

import random

import numpy as np
import pytest

from revnet.metrics import same_answers
from revnet.operators import halo, regions
from revnet.operators.flood import vertex_knn
from revnet.plans.storage import stored
from revnet.workloads import Setting


@pytest.mark.parametrize("ties", ["by_id", "inclusive"])
def test_runs_of_many_edges_equal_single_ones(monkeypatch, ties):
    monkeypatch.setattr(regions, "_TOGETHER", 100)
    r, edges = random.Random(3), []
    for i in range(300):
        k = r.randint(1, 6)
        edges.append((r.randint(1, 12), [(f, r.randint(0, 15)) for f in r.sample(range(12), r.randint(0, 6))], [(f, r.randint(0, 15)) for f in r.sample(range(12), r.randint(0, 6))]))
    asked = np.array([1, 4, 5, 9])
    w = np.array([x[0] for x in edges])
    ends = [tuple(np.array([(i, f, d) for i, x in enumerate(edges) for f, d in x[side]]).T) for side in (1, 2)]
    for k in (1, 3, 8):
        want = [(i, *x) for i, (n, u, v) in enumerate(edges) for x in regions.edge_intervals(n, u, v, k, ties, set(asked.tolist()))]
        got = regions.edge_runs(w, *ends, asked, k, ties, True)
        rows = [tuple(int(got[c][i]) for c in ("edge", "q", "lo", "hi", "rk")) + tuple(None if got[c][i] < 0 else int(got[c][i]) for c in ("du", "dv")) for i in range(len(got["edge"]))]
        assert sorted(rows, key=str) == sorted(want, key=str)
        held = {(e, q, x) for e, q, lo, hi, *_ in want for x in range(lo, hi + 1)}
        got = regions.edge_runs(w, *ends, asked, k, ties, False)
        one = [(int(e), int(q), x) for e, q, lo, hi in zip(got["edge"], got["q"], got["lo"], got["hi"]) for x in range(lo, hi + 1)]
        assert len(one) == len(set(one)) and set(one) == held and len(got["edge"]) <= len(want)


def test_regions_of_tiles_equal_those_of_labels(spark, monkeypatch):
    s = Setting(spark, "/root/testdata/sf0.001")
    want = stored(regions.influence_region(s.net, vertex_knn(s.net, s.facilities, 4), s.sites, 4), "want")
    assert same_answers(regions.tile_regions(halo.tile_network(s.net, s.facilities, 16), s.sites, 4), want)
    monkeypatch.setattr(halo, "REGION_LIMIT", 1)
    monkeypatch.setattr(halo.TiledNetwork, "first_halo", lambda self, k: 1500)
    assert same_answers(regions.tile_regions(halo.tile_network(s.net, s.facilities, 16), s.sites, 4), want)


def test_auto_plan_needs_no_tree_where_the_expansion_has_all_lists(spark, monkeypatch):
    from revnet.operators import batch
    from revnet.plans.options import RknnOptions
    from revnet.sources import tables as T

    s = Setting(spark, "/root/testdata/sf0.001")
    few = stored(T.spread_batch(spark, s.sf_dir, s.n, 3), "few")
    want = stored(s.batch(RknnOptions(plan="flood", k=2), few), "want")
    monkeypatch.setattr(batch, "build_count_tree", lambda *a: pytest.fail("a tree was built"))
    run = s.run(RknnOptions(plan="auto", k=2), few)
    assert run.plan == "expand" and not want.isEmpty() and same_answers(run.result, want)
    assert run.cache.filled == 0
