"""Searches in steps together find what single searches with a heap find."""

import random

import numpy as np
import pandas as pd
import pytest

from revnet.operators import lockstep
from revnet.operators.halo import Region, ranks


def _net(seed: int, side: int = 15, cut: int = 0) -> pd.DataFrame:
    r = random.Random(seed)
    n = side * side
    roads: dict[int, dict[int, int]] = {v: {} for v in range(n)}
    for v in range(n):
        for t in (v + 1, v + side):
            if t < n and (t != v + 1 or t % side) and r.random() < 0.9:
                roads[v][t] = roads[t][v] = r.randint(1, 4)
    for t in range(1, n, 2):
        roads[0][t] = roads[t][0] = 9  # many roads at a vertex
    ids = [v for v in range(n - cut)]
    return pd.DataFrame({"v": [3 * v for v in ids], "is_f": [r.random() < 0.4 for _ in ids], "dst": [np.array([3 * t for t in roads[v]], np.int64) for v in ids], "w": [np.array(list(roads[v].values()), np.int64) for v in ids]})


@pytest.mark.parametrize("seed,cut,k,wide,cells", [(1, 0, 5, 4096, 8_000_000), (2, 30, 5, 4096, 100), (3, 0, 500, 4096, 2_000), (4, 20, 12, 40, 8_000_000)])
def test_searches_together_equal_single_ones(monkeypatch, seed, cut, k, wide, cells):
    monkeypatch.setattr(lockstep, "WIDE", wide)
    monkeypatch.setattr(lockstep, "CELLS", cells)
    g, r = _net(seed, cut=cut), random.Random(seed)
    region, arrays = Region(g), lockstep.RoadArrays(g)
    starts = [[(r.randint(0, 5), 3 * r.randrange(225)) for _ in range(r.randint(1, 2))] for _ in range(60)]
    starts.append([(0, 100_000)])
    s = np.array([i for i, x in enumerate(starts) for _ in x])
    for _ in range(2):  # what a first call has touched is forgotten
        row, f, d, left, slow = arrays.nearest(s, np.array([v for x in starts for _, v in x]), np.array([d for x in starts for d, _ in x]), len(starts), k)
        assert slow.any() == (wide == 40)
        for ties in ("by_id", "inclusive"):
            rk = lockstep.ranks_of(row, d, ties)
            for i, x in enumerate(starts):
                want = region.nearest(x, k, ties)
                if not slow[i]:
                    assert left[i] == (want is None)
                    got = [(int(a), int(b), int(c)) for a, b, c in zip(f[row == i], d[row == i], rk[row == i])]
                    assert (got[:k] if ties == "by_id" else got) == ([] if want is None else list(ranks(want, ties)))
