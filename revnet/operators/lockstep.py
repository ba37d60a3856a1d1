"""Many searches of a region at once in numpy: each has a queue of its own, and all take their next step together."""

from __future__ import annotations

import numpy as np
import pandas as pd

_FAR = np.iinfo(np.int64).max
CELLS = 8_000_000  # tentative distances held at a time: searches of a chunk times vertices of the region
WIDE = 4096  # searches with longer queues are left to a heap


class RoadArrays:
    """Roads and facilities that a task holds, by place: vertices are numbered in order of their ids, ends of roads outside included."""

    def __init__(self, g: pd.DataFrame):
        v = g["v"].to_numpy(np.int64)
        n = np.array([len(x) for x in g["dst"]], np.int64)
        none = np.zeros(0, np.int64)
        dst = np.concatenate([none, *g["dst"]]).astype(np.int64)
        self.w = np.concatenate([none, *g["w"]]).astype(np.int64)
        self.ids = np.unique(np.concatenate([v, dst]))
        size, at = len(self.ids), np.searchsorted(self.ids, v)
        self.dst = np.searchsorted(self.ids, dst)
        self.degree, self.start = np.zeros(size, np.int64), np.zeros(size, np.int64)
        self.inside, self.fac = np.zeros(size, bool), np.zeros(size, bool)
        self.degree[at], self.start[at], self.inside[at], self.fac[at] = n, np.cumsum(n) - n, True, g["is_f"].to_numpy(bool)
        self.bits = int(size).bit_length()
        self._best = np.zeros(0, np.int64)

    def nearest(self, s: np.ndarray, v: np.ndarray, d: np.ndarray, count: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """``(s, f, d, left, slow)``: facilities within the distance of the ``k``-th of each search, in order of (s, d, f).

        Search ``s`` (0 to ``count`` - 1, rising) starts at vertices ``v`` at distances ``d``. ``left`` marks
        searches that leave the region and ``slow`` those with queues too long for steps in common; neither has rows.
        """
        place = np.minimum(np.searchsorted(self.ids, v), max(len(self.ids) - 1, 0))
        left, slow = np.zeros(count, bool), np.zeros(count, bool)
        known = self.ids[place] == v if len(self.ids) else np.zeros(len(v), bool)
        left[s[~known]] = True
        s, place, d = s[known], place[known], d[known]
        size = max(len(self.ids), 1)
        per = max(16, min(4096, CELLS // size))
        if len(self._best) < per * size:
            self._best = np.full(per * size, _FAR)
        found = [np.zeros((2, 0), np.int64)]
        for at in range(0, count, per):
            x, y = np.searchsorted(s, [at, at + per])
            if y > x:
                row, key = self._chunk(s[x:y] - at, place[x:y], d[x:y], min(per, count - at), k, left[at : at + per], slow[at : at + per])
                found.append(np.stack([row + at, key]))
        row, key = np.concatenate(found, axis=1)
        keep = ~(left | slow)[row]
        row, key = row[keep], key[keep]
        return row, self.ids[key & ((1 << self.bits) - 1)] if len(key) else key, key >> self.bits, left, slow

    def _chunk(self, s, v, d, n, k, left, slow) -> tuple[np.ndarray, np.ndarray]:
        """Rows and keys (distance, place) of what is found; ``left`` and ``slow`` are set."""
        bits, size, best = self.bits, len(self.ids), self._best
        mask = (1 << bits) - 1
        who, fill = np.arange(n), np.zeros(n, np.int64)
        got, limit = np.zeros(n, np.int64), np.full(n, _FAR >> bits)
        queue = np.full((n, 32), _FAR)
        touched, rows, keys = [], [], []

        def push(i, t, dist):  # i: rising places in ``who``
            nonlocal queue, fill
            flat = who[i] * size + t
            ok = np.flatnonzero(dist < best[flat])
            i, flat, dist, t = i[ok], flat[ok], dist[ok], t[ok]
            best[flat] = dist
            touched.append(flat)
            new = np.bincount(i, minlength=len(who))
            col = fill[i] + np.arange(len(i)) - np.repeat(np.cumsum(new) - new, new)
            fill = fill + new
            if fill.max(initial=0) > queue.shape[1]:
                queue = np.concatenate([queue, np.full(queue.shape, _FAR)], axis=1)
                if fill.max() > queue.shape[1]:  # very many roads at a vertex
                    queue = np.concatenate([queue, np.full((len(who), int(fill.max())), _FAR)], axis=1)
            queue[i, col] = dist << bits | t

        push(s, v, d)
        while len(who):
            wide = int(fill.max())
            if wide > WIDE:
                slow[who] = True
                break
            at = queue[:, :wide].argmin(1) if wide else np.zeros(len(who), np.int64)
            line = np.arange(len(who))
            key = queue[line, at]
            dist = key >> bits
            live = (key < _FAR) & (dist <= limit)
            if 2 * np.count_nonzero(live) < len(who):  # the others have ended
                i = np.flatnonzero(live)
                who, fill, got, limit, queue = who[i], fill[i], got[i], limit[i], queue[i]
                continue
            queue[line, at] = _FAR
            i = np.flatnonzero(live)
            t = key[i] & mask
            flat = who[i] * size + t
            new = best[flat] >= 0
            i, t, flat = i[new], t[new], flat[new]
            best[flat] = -1
            out = ~self.inside[t]
            if out.any():
                left[who[i[out]]] = True
                limit[i[out]] = -1
                i, t = i[~out], t[~out]
            hit = self.fac[t]
            h = i[hit]
            rows.append(who[h])
            keys.append(key[h])
            got[h] += 1
            full = h[got[h] == k]
            limit[full] = dist[full]
            deg = self.degree[t]
            road = np.arange(int(deg.sum())) + np.repeat(self.start[t] - (np.cumsum(deg) - deg), deg)
            push(np.repeat(i, deg), self.dst[road], np.repeat(dist[i], deg) + self.w[road])
        for flat in touched:
            best[flat] = _FAR
        if not rows:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        row, key = np.concatenate(rows), np.concatenate(keys)
        order = np.lexsort((key, row))
        return row[order], key[order]


def places(s: np.ndarray) -> np.ndarray:
    """Place of each row, from 0, within its run of equal ``s``."""
    n = np.arange(len(s))
    first = np.append(True, s[1:] != s[:-1])[: len(s)]
    return n - np.maximum.accumulate(np.where(first, n, 0)) if len(s) else n


def ranks_of(s: np.ndarray, d: np.ndarray, ties: str) -> np.ndarray:
    """Ranks of facilities in order of (s, d, f): by place, or one more than those strictly nearer."""
    rank = places(s) + 1
    if ties == "by_id" or not len(s):
        return rank
    new = np.append(True, (s[1:] != s[:-1]) | (d[1:] != d[:-1]))
    return rank[np.maximum.accumulate(np.where(new, np.arange(len(s)), 0))]
