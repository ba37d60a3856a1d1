"""Worked examples, edge cases and validation on literal networks."""

import itertools

import pytest

from revnet.examples import delivery, example, pruning, second_route
from revnet.network import validate_inputs
from revnet.operators.batch import as_pairs, batch_rknn, monochromatic, one_by_one, run_batch
from revnet.operators.count_tree import build_count_tree
from revnet.operators.flood import knn, vertex_knn
from revnet.operators.verify import candidates, quick_verify
from revnet.plans.options import RknnOptions

PLANS = [RknnOptions(k=1, plan=p) for p in ("flood", "region")] + [RknnOptions(k=1, plan="expand", rules=r) for r in ((), ("stop", "ancestor"), ("path_count",))]


def pairs(df):
    return {(r.q, r.m) for r in df.collect()}


def with_k(o, k):
    return RknnOptions(**{**o.__dict__, "k": k})


@pytest.mark.parametrize("o", PLANS, ids=lambda o: f"{o.plan}-{'-'.join(o.rules)}")
def test_delivery(spark, o):
    net, fac, q, objs = delivery(spark)
    assert pairs(batch_rknn(net, fac, q, objs, with_k(o, 2))) == {(1, 1), (1, 2), (2, 1), (3, 3), (3, 4), (4, 2), (4, 3), (4, 4)}


@pytest.mark.parametrize("o", PLANS, ids=lambda o: f"{o.plan}-{'-'.join(o.rules)}")
def test_pruning_answers(spark, o):
    net, fac, q, objs = pruning(spark)
    assert {m for _, m in pairs(batch_rknn(net, fac, q, objs, o))} == {1, 3}


def test_pruning_leaves_far_vertices(spark):
    net, fac, q, objs = pruning(spark)
    run = run_batch(net, fac, q, objs, RknnOptions(k=1, plan="expand", rules=("stop",)))
    assert {r.v for r in run.expansion.labels.collect()} == {0, 1, 3, 4}
    labels = run.expansion.labels
    got = quick_verify(candidates(labels, objs, net), objs, net, build_count_tree(fac), 1)
    assert {r.m: (r.cnt, r.verdict) for r in got.collect() if r.m in (1, 3, 4)} == {1: (1, "YES"), 3: (1, "YES"), 4: (2, "UNKNOWN")}


def test_second_route(spark):
    net, fac, q, objs = second_route(spark)
    for o in (PLANS[0], PLANS[3]):
        assert {m for _, m in pairs(batch_rknn(net, fac, q, objs, o))} == {4}
    run = run_batch(net, fac, q, objs, RknnOptions(k=1, plan="expand", rules=("stop",)))
    assert {(r.v, r.d) for r in run.expansion.labels.collect()} >= {(4, 7)}  # longer than the true distance, harmless


def test_ties_by_id_and_inclusive(spark):
    net, fac, q, objs = example(spark, [(i, i, 0) for i in range(4)], [(i, i, i + 1, 1) for i in range(3)], [0, 3], [0, 3], [(1, 1, 0), (2, 1, 1)])
    middle = objs.where("m = 1").selectExpr("9 as m", "1L as eid", "0L as off")
    assert pairs(batch_rknn(net, fac, q, middle, RknnOptions(k=1, plan="flood"))) == {(0, 9)}
    net2, fac2, q2, o2 = example(spark, [(0, 0, 0), (1, 2, 0), (2, 4, 0)], [(0, 0, 1, 2), (1, 1, 2, 2)], [0, 2], [0, 2], [(5, 0, 2)])
    for plan in ("flood", "expand", "region"):
        assert pairs(batch_rknn(net2, fac2, q2, o2, RknnOptions(k=1, plan=plan))) == {(0, 5)}
        assert pairs(batch_rknn(net2, fac2, q2, o2, RknnOptions(k=1, plan=plan, ties="inclusive"))) == {(0, 5), (2, 5)}


def test_disconnected_and_large_k(spark):
    net, fac, q, objs = example(spark, [(0, 0, 0), (1, 3, 0), (10, 50, 0), (11, 53, 0)], [(0, 0, 1, 3), (10, 10, 11, 4)], [0, 10, 11], [0, 10, 11], [(1, 0, 3), (2, 10, 1)])
    want = {(0, 1), (10, 2), (11, 2)}
    for plan in ("flood", "expand", "region"):
        assert pairs(batch_rknn(net, fac, q, objs, RknnOptions(k=5, plan=plan))) == want
    assert sorted((r.m, r.rk) for r in knn(objs, net, fac, 5).collect()) == [(1, 1), (2, 1), (2, 2)]


def test_empty_batch_no_objects_and_repeats(spark):
    net, fac, q, objs = delivery(spark)
    for plan in ("flood", "expand", "region"):
        o = RknnOptions(k=2, plan=plan)
        assert batch_rknn(net, fac, q.limit(0), objs, o).isEmpty()
        assert batch_rknn(net, fac, q, objs.limit(0), o).isEmpty()
        assert batch_rknn(net, fac, q.union(q), objs, o).count() == 8
    got = as_pairs(batch_rknn(net, fac, q, objs.where("m = 1"), RknnOptions(k=1, plan="flood")), q)
    assert {r.q: (r.n_members, r.members) for r in got.collect()} == {1: (1, [1]), 2: (0, []), 3: (0, []), 4: (0, [])}


def test_one_by_one_equals_batch(spark):
    net, fac, q, objs = delivery(spark)
    assert pairs(one_by_one(net, fac, [1, 4], objs, RknnOptions(k=2))) == pairs(batch_rknn(net, fac, q.where("q in (1, 4)"), objs, RknnOptions(k=2)))


def test_hop_limit_keeps_true_distances(spark):
    net, fac, q, objs = example(spark, [(0, 0, 0), (1, 1, 1), (2, 2, 0)], [(1, 0, 1, 2), (2, 0, 2, 10), (12, 1, 2, 2)], [0], [0], [(5, 2, 10)])
    for quick in (True, False):
        got = batch_rknn(net, fac, q, objs, RknnOptions(k=1, plan="expand", max_hops=1, quick=quick)).collect()
        assert [(r.m, r.net_dist) for r in got] == [(5, 4)]
    assert batch_rknn(net, fac, q, objs, RknnOptions(k=1, plan="expand", max_hops=0)).count() == 1
    path, f1, q1, o1 = example(spark, [(i, i, 0) for i in range(4)], [(i, i, i + 1, 1) for i in range(3)], [0], [0], [(i, i, 1) for i in range(3)])
    for hops, want in ((0, {0}), (1, {0, 1}), (2, {0, 1, 2})):
        assert {m for _, m in pairs(batch_rknn(path, f1, q1, o1, RknnOptions(k=1, plan="expand", max_hops=hops)))} == want


def test_exclude_self_asks_facilities(spark):
    net, fac, q, objs = delivery(spark)
    for plan in ("auto", "flood"):
        assert pairs(batch_rknn(net, fac, q, objs, RknnOptions(k=1, plan=plan, exclude_self=True))) == {(2, 1), (1, 2), (1, 4), (4, 3)}


def test_monochromatic_drops_itself(spark):
    net, fac, q, _ = delivery(spark)
    assert pairs(monochromatic(net, fac, q, 1)) == {(2, 1), (1, 2), (1, 4), (4, 3)}


@pytest.mark.parametrize("bad", [{"k": 0}, {"ties": "x"}, {"plan": "x"}, {"rules": ("x",)}, {"bound": "x"}, {"plan": "flood", "max_radius": 5}, {"plan": "expand", "exclude_self": True}])
def test_options_are_checked(bad):
    with pytest.raises(ValueError):
        RknnOptions(**bad)


def test_inputs_are_checked(spark):
    net, fac, q, objs = delivery(spark)
    net.validate()
    validate_inputs(net, fac, q, objs)
    with pytest.raises(ValueError):
        validate_inputs(net, fac.where("f <> 1"), q, objs)
    with pytest.raises(ValueError):
        validate_inputs(net, fac, q, objs.selectExpr("m", "eid", "off + 9 as off"))


def test_against_all_pairs_on_small_nets(spark):
    """Every plan against distances by brute force, with ties and sparse facilities."""
    for n, step, k in ((8, 2, 2),):
        ids = list(range(n))
        edges = [(i, i, i + 1, 2 + i % 3) for i in range(n - 1)] + [(100 + i, i, i + 3, 5) for i in range(0, n - 3, 2)]
        fac_ids = ids[::step]
        objs = [(10 * e + j, e, min(j, w)) for e, _, _, w in edges for j in (0, 1, w)]
        net, fac, q, o = example(spark, [(i, 2 * i, i % 2) for i in ids], edges, fac_ids, fac_ids, objs)
        far = 10**9
        d = {(a, b): 0 if a == b else far for a, b in itertools.product(ids, ids)}
        for _, u, v, w in edges:
            d[u, v] = d[v, u] = min(w, d[u, v])
        for m, a, b in itertools.product(ids, ids, ids):
            d[a, b] = min(d[a, b], d[a, m] + d[m, b])
        ends = {e: (u, v, w) for e, u, v, w in edges}
        want = set()
        for m, e, off in objs:
            u, v, w = ends[e]
            near = sorted((min(off + d[u, f], w - off + d[v, f]), f) for f in fac_ids)[:k]
            want |= {(f, m) for _, f in near}
        o = o.distinct()
        for opt in (RknnOptions(k=k, plan="flood"), RknnOptions(k=k, plan="region"), RknnOptions(k=k, plan="expand"), RknnOptions(k=k, plan="expand", rules=("stop", "ancestor"), bound="both", cache_key="object"), RknnOptions(k=k, plan="expand", rules=(), quick=False)):
            assert pairs(batch_rknn(net, fac, q, o, opt)) == want, opt
        assert vertex_knn(net, fac, k).count() == n * min(k, len(fac_ids))
