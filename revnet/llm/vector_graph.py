"""Near-duplicate vectors over a robust-pruned flat graph.

Vectors so close to a common centre that all of them link with one another are gathered into balls
first, so that a large group of near copies becomes few nodes. The nodes (ball centres and single
vectors) go to their nearest shards, overlapping; each shard builds a robust-pruned neighbour graph
and the adjacency lists of a node are united. Every node searches the graphs of these shards from its own
place, and those of others across whose border its links can lie from the nearest of some entry nodes, greedily,
with a list that widens while nodes within range keep coming; many searches of a shard take their steps together.
Found pairs are verified in double precision; no pair below the cosine is ever linked.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import connected_components, materialize

_EPS = 1e-9


def unit_rows(vectors) -> tuple[np.ndarray, np.ndarray]:
    """Normalised rows and a mask of usable ones: not null, not zero, all components finite."""
    good = np.array([v is not None and len(v) > 0 and all(x is not None for x in v) for v in vectors], bool)
    dims = max((len(v) for v, g in zip(vectors, good, strict=True) if g), default=1)
    x = np.zeros((len(good), dims))
    for i in np.flatnonzero(good):
        if len(vectors[i]) != dims:
            raise ValueError("vectors of different lengths")
        x[i] = vectors[i]
    good &= np.isfinite(x).all(1)
    x[~good] = 0
    big = np.abs(x).max(1)
    good &= big > 0
    x[good] /= big[good][:, None]  # no overflow or underflow of the squares
    n = np.sqrt((x * x).sum(1))
    x[good] /= n[good][:, None]
    return x, good


def _angles(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.arccos(np.clip(a @ b.T, -1, 1))


def centroids(sample: np.ndarray, k: int, rounds: int = 8, seed: int = 3) -> np.ndarray:
    """Spherical k-means centres of a bounded sample."""
    rng = np.random.default_rng(seed)
    c = sample[rng.choice(len(sample), min(k, len(sample)), replace=False)]
    for _ in range(rounds):
        at = (sample @ c.T).argmax(1)
        s = np.zeros_like(c)
        np.add.at(s, at, sample)
        n = np.sqrt((s * s).sum(1))
        c = np.where(n[:, None] > 1e-12, s / np.maximum(n, 1e-12)[:, None], c)
    return c


# --- balls ----------------------------------------------------------------------------------


def gather(x: np.ndarray, link: float) -> list[np.ndarray]:
    """Centres of groups within a block: single-pass leaders at the link's angle, then their means."""
    left, out = np.arange(len(x)), []
    while len(left):
        near = x[left] @ x[left[0]] >= np.cos(link)
        group = left[near]
        if len(group) > 1:
            m = x[group].mean(0)
            out.append(m / max(np.sqrt((m * m).sum()), 1e-12))
        left = left[~near]
    return out


# --- graph ----------------------------------------------------------------------------------


def robust_prune(x: np.ndarray, p: int, cand: np.ndarray, dist: np.ndarray, degree: int, alpha: float) -> list[int]:
    """Neighbours of ``p`` from candidates by rising distance, without those that a kept one covers."""
    out: list[int] = []
    alive = cand != p
    far = alpha * _angles(x[cand], x[cand]) > dist
    for j in np.argsort(dist, kind="stable").tolist():
        if not alive[j]:
            continue
        out.append(int(cand[j]))
        if len(out) >= degree:
            break
        alive &= far[j]
    return out


def build_graph(x: np.ndarray, degree: int = 24, pool: int = 64, alpha: float = 1.2, block: int = 512) -> list[list[int]]:
    """Robust-pruned adjacency of one shard: nearest ``pool`` and some far nodes as candidates, edges made mutual."""
    n = len(x)
    rng = np.random.default_rng(n)
    adj: list[list[int]] = [[] for _ in range(n)]
    for at in range(0, n, block):
        d = -(x[at : at + block] @ x.T)
        for r in range(len(d)):
            near = np.argpartition(d[r], min(pool, n - 1))[: pool + 1] if n > pool + 1 else np.arange(n)
            cand = np.unique(np.concatenate([near, rng.integers(0, n, min(16, n))]))
            adj[at + r] = robust_prune(x, at + r, cand, np.arccos(np.clip(-d[r][cand], -1, 1)), degree, alpha)
    back: list[list[int]] = [[] for _ in range(n)]
    for i, nb in enumerate(adj):
        for j in nb:
            back[j].append(i)
    for i in range(n):
        both = np.array(sorted(set(adj[i]) | set(back[i])), np.int64)
        adj[i] = both.tolist() if len(both) <= 2 * degree else robust_prune(x, i, both, _angles(x[both], x[i][None, :])[:, 0], 2 * degree, alpha)
    return adj


class ShardGraph:
    """A shard's nodes ``x`` with their radii and neighbours, searched by many queries together.

    Each search is greedy with a list of its own; all take their next step at once: they leave their ``step`` best nodes
    not left yet, and meet those nodes' neighbours. Work goes with the nodes met, whatever the shard holds.
    """

    def __init__(self, x: np.ndarray, adj: list[list[int]], rad: np.ndarray, entries: int = 64, rows: int = 256, step: int = 4):
        n = len(x)
        self.x, self.rad, self.rows, self.step = x, rad, rows, step
        self.degree = np.array([len(a) for a in adj], np.int64)
        self.start = np.cumsum(self.degree) - self.degree
        self.to = np.concatenate([np.zeros(0, np.int64), *(np.array(a, np.int64) for a in adj)])
        # searches from outside start at the nearest two of the medoid and some nodes of the shard
        picked = np.random.default_rng(n).choice(n, min(entries, n), replace=False)
        self.entry = np.unique(np.append(picked, (x @ x.mean(0)).argmax()))
        self._stamp = np.zeros(rows * n, np.int32)

    def search(self, q: np.ndarray, reach: np.ndarray, own: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """``(row, node, angle)``: nodes met within ``reach`` and their radius of the queries, from the places ``own`` (-1: outside).

        A search whose list of ``width`` ends half full of such nodes is made again with one twice as wide.
        """
        out = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        todo = np.arange(len(q))
        while len(todo):
            again = []
            for at in range(0, len(todo), self.rows):
                part = todo[at : at + self.rows]
                r, node, angle, full = self._chunk(q[part], reach[part], own[part], width)
                keep = ~full[r]
                out.append((part[r[keep]], node[keep], angle[keep]))
                again.append(part[full])
            todo, width = np.concatenate(again), 2 * width
        return tuple(np.concatenate(c) for c in zip(*out, strict=True))

    def _chunk(self, q, reach, own, width):
        n, m = len(self.x), len(q)
        seen = np.zeros(m * n, bool)
        least = np.cos(np.minimum(reach + self.rad.max(initial=0), np.pi)) - 1e-9
        ids, sim, fresh = np.zeros((m, width), np.int64), np.full((m, width), -2.0), np.zeros((m, width), bool)
        who, full, out = np.arange(m), np.zeros(m, bool), []
        near = self.entry[np.argsort(-(q @ self.x[self.entry].T), axis=1)[:, :2]]
        starts = np.where(own[:, None] >= 0, own[:, None], near)
        r, c = np.repeat(who, starts.shape[1]), starts.ravel()
        while True:
            # meet the nodes ``c`` of the rows ``r`` (rising) that were not met before, each once
            flat = who[r] * n + c
            new = np.flatnonzero(~seen[flat])
            flat = flat[new]
            self._stamp[flat] = np.arange(len(flat))
            once = self._stamp[flat] == np.arange(len(flat))
            r, c, flat = r[new[once]], c[new[once]], flat[once]
            seen[flat] = True
            s = np.einsum("ij,ij->i", self.x[c], q[who[r]])
            h = np.flatnonzero(s >= least[who[r]])
            angle = np.arccos(np.clip(s[h], -1, 1))
            ok = angle <= reach[who[r[h]]] + self.rad[c[h]]
            out.append((who[r[h[ok]]], c[h[ok]], angle[ok]))
            if len(r):
                count = np.bincount(r, minlength=len(who))
                at = width + np.arange(len(r)) - np.repeat(np.cumsum(count) - count, count)
                wide = ((0, 0), (0, int(count.max())))
                ids, sim, fresh = np.pad(ids, wide), np.pad(sim, wide, constant_values=-2.0), np.pad(fresh, wide)
                ids[r, at], sim[r, at], fresh[r, at] = c, s, True
                best = np.argpartition(-sim, width - 1, axis=1)[:, :width]
                ids, sim, fresh = (np.take_along_axis(a, best, 1) for a in (ids, sim, fresh))
            live = fresh.any(1)
            if not live.all():
                e = ~live
                hits = (sim[e] > -2) & (np.arccos(np.clip(sim[e], -1, 1)) <= reach[who[e]][:, None] + self.rad[ids[e]])
                full[who[e]] = (2 * hits.sum(1) >= width) & (width < 2 * n)
                who, ids, sim, fresh = who[live], ids[live], sim[live], fresh[live]
            if not len(who):
                return *(np.concatenate(x) for x in zip(*out, strict=True)), full
            ahead = np.where(fresh, sim, -3.0)
            pick = np.argpartition(-ahead, min(self.step, width) - 1, axis=1)[:, : self.step]
            r, k = np.nonzero(np.take_along_axis(fresh, pick, 1))
            v = ids[r, pick[r, k]]
            fresh[r, pick[r, k]] = False
            deg = self.degree[v]
            c = self.to[np.arange(int(deg.sum())) + np.repeat(self.start[v] - (np.cumsum(deg) - deg), deg)]
            r = np.repeat(r, deg)


def shard_borders(x: np.ndarray, cents: np.ndarray, gaps: np.ndarray, overlap: int) -> tuple[np.ndarray, np.ndarray]:
    """Angles of rows to the planes between their own centre and each other one, and their ``overlap`` nearest shards."""
    s = x @ cents.T
    gap = gaps[s.argmax(1)]
    border = np.arcsin(np.clip((s.max(1)[:, None] - s) / np.maximum(gap, 1e-12), 0, 1))
    border[gap < 1e-12] = 0
    return border, np.argsort(-s, axis=1, kind="stable")[:, :overlap]


def centre_gaps(cents: np.ndarray) -> np.ndarray:
    return np.sqrt(np.maximum(2 - 2 * cents @ cents.T, 0))


def border_band(sample: np.ndarray, apart: np.ndarray, cents: np.ndarray, link: float, overlap: int, meet: float = 0.9999, draws: int = 20_000, seed: int = 5) -> float:
    """The angle to a border within which a node searches the shard behind it.

    Half of ``link`` is enough for any pair: the way between nodes of two shards crosses the plane between
    the centres, so one of the two is within half their angle. In many dimensions little of that way
    leads to the plane, and half of ``link`` takes in most shards. So partners are made for rows ``apart``,
    on which the centres were not fitted, the full ``link`` away in the directions of differences between two of the
    shard's rows, and the band is the one in which the share ``meet`` of these pairs have a shard in common;
    nearer pairs do so more often. Too few rows for that give half of ``link``.
    """
    if len(apart) < 64:
        return link / 2
    rng = np.random.default_rng(seed)
    own = (sample @ cents.T).argmax(1)
    by = np.argsort(own, kind="stable")
    first, size = np.searchsorted(own[by], np.arange(len(cents))), np.bincount(own, minlength=len(cents))
    gaps, need = centre_gaps(cents), []
    block = max(1, min(1024, 4_000_000 // len(cents)))
    for at in range(0, draws, block):
        x = apart[rng.integers(0, len(apart), min(block, draws - at))]
        c = (x @ cents.T).argmax(1)
        x, c = x[size[c] > 0], c[size[c] > 0]
        one, two = (sample[by[first[c] + (rng.random(len(c)) * size[c]).astype(np.int64)]] for _ in range(2))
        z = one - two
        u = z - (x * z).sum(1)[:, None] * x
        n = np.sqrt((u * u).sum(1))
        x, u = x[n > 1e-6], u[n > 1e-6] / n[n > 1e-6][:, None]
        if not len(x):
            continue
        y = np.cos(link) * x + np.sin(link) * u
        (bx, tx), (by_, ty) = shard_borders(x, cents, gaps, overlap), shard_borders(y, cents, gaps, overlap)
        wide = np.minimum(np.take_along_axis(bx, ty, 1).min(1), np.take_along_axis(by_, tx, 1).min(1))
        wide[(tx[:, :, None] == ty[:, None, :]).any((1, 2))] = 0
        need.append(wide)
    return min(link / 2, float(np.quantile(np.concatenate(need), meet))) if need else link / 2


def probed_shards(x: np.ndarray, radius: np.ndarray, cents: np.ndarray, link: float, overlap: int, band: float | None = None, gaps: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (row, shard) to search: the ``overlap`` nearest shards and those whose border is within ``band`` (by default half of ``link``) and the row's radius."""
    border, top = shard_borders(x, cents, centre_gaps(cents) if gaps is None else gaps, overlap)
    take = border <= ((link / 2 if band is None else band) + radius + 1e-7)[:, None]
    np.put_along_axis(take, top, True, axis=1)
    return np.nonzero(take)


# --- the operator ---------------------------------------------------------------------------


def near_vectors(vectors: DataFrame, cosine: float = 0.9, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = 2000, overlap: int = 2, sample_rows: int = 20_000, degree: int = 24) -> DataFrame:
    """``(id_col, n_links, component_id, kept)`` for every row.

    ``n_links`` counts the other rows with cosine >= ``cosine`` that the search found, each verified
    in double precision; ``component_id`` is the smallest id reachable by links; ``kept`` marks it.
    Null, empty and zero vectors and those with null or non-finite components link with nothing.
    Equal vectors link (cosine 1). Rows with a null id are left out; repeated rows, and different
    vectors of one id, count as rows of their own. An empty table gives an empty result; other columns are ignored. Vectors of different
    lengths raise an error. The centres of the shards are fitted on at most ``sample_rows`` rows; all
    rows are indexed and searched. Pairs at the very limit of ``cosine`` share a shard in 9,999 of 10,000 cases by
    the sample (see ``border_band``), nearer ones more often; ``audit_recall`` counts what is found.
    """
    spark = vectors.sparkSession
    link = float(np.arccos(cosine))
    slim = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v")).where("id is not null")
    n = slim.count()
    shards = max(1, -(-n // shard_rows))
    picked = slim.select("id").orderBy(F.xxhash64("id"), "id").limit(sample_rows)
    s, good = unit_rows(slim.join(F.broadcast(picked), "id", "left_semi").limit(sample_rows).toArrow().to_pandas().sort_values("id")["v"].tolist() if n else [])
    if not good.any():
        return vectors.select(id_col, F.lit(0).cast("long").alias("n_links"), F.col(id_col).cast("long").alias("component_id"), F.lit(True).alias("kept")).where(F.col(id_col).isNotNull())
    apart = np.arange(int(good.sum())) % 4 == 3  # kept from the fit, to try it on
    fitted, apart = s[good][~apart], s[good][apart]
    centre = spark.sparkContext.broadcast(centroids(fitted, min(shards, len(fitted) // 6 + 1)))

    # 1. normalise; deal rows to blocks of their nearest centre, a centre's many rows over several blocks
    def normal(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            x, ok = unit_rows(b["v"].tolist())
            at = (x @ centre.value.T).argmax(1) if ok.any() else np.zeros(len(x), np.int64)
            yield pd.DataFrame({"id": b["id"], "key": b["key"], "ok": ok, "c": at, "x": list(x.astype("<f8"))}).assign(x=lambda f: [r.tobytes() for r in f["x"]])

    # rows get numbers that rise with their ids, so the smallest number of a component is of its smallest id, and an id's many rows are parted
    tie = slim.withColumn("tie", F.monotonically_increasing_id())
    numbered = tie.repartitionByRange("id", "tie").sortWithinPartitions("id", "tie").select(F.monotonically_increasing_id().alias("id"), F.col("id").alias("key"), "v")
    rows = materialize(numbered.mapInPandas(normal, "id long, key long, ok boolean, c int, x binary"), "vectors")
    per = rows.where("ok").groupBy("c").agg(F.count(F.lit(1)).alias("n"))
    salts = {int(r.c): max(1, -(-int(r.n) // shard_rows)) for r in per.collect()}  # one entry per centre
    salt = F.create_map(*[F.lit(v) for k, w in salts.items() for v in (k, w)])
    blocks = rows.where("ok").withColumn("salt", F.pmod(F.xxhash64("id"), salt[F.col("c")]))

    # 2. candidate ball centres: of each block first, then of the blocks' centres of one shard
    half = link / 2 - 1e-6

    def block_centres(b: pd.DataFrame) -> pd.DataFrame:
        got = gather(np.stack([np.frombuffer(v) for v in b["x"]]), link)
        return pd.DataFrame({"c": np.full(len(got), b["c"].iloc[0]), "x": [g.tobytes() for g in got]})

    def shard_centres(b: pd.DataFrame) -> pd.DataFrame:
        x = np.stack([np.frombuffer(v) for v in b["x"]])
        merged, left = [], np.arange(len(x))
        while len(left):
            near = x[left] @ x[left[0]] >= np.cos(half)
            m = x[left[near]].mean(0)
            merged.append(m / max(np.sqrt((m * m).sum()), 1e-12))
            left = left[~near]
        return pd.DataFrame({"c": np.full(len(merged), b["c"].iloc[0]), "bx": [np.stack(merged).tobytes()] * len(merged)}).head(1)

    first = blocks.groupBy("c", "salt").applyInPandas(block_centres, "c int, x binary")
    balls = first.groupBy("c").applyInPandas(shard_centres, "c int, bx binary")

    # 3. a row within half the link's angle of a centre is in its ball, so all rows of a ball link
    def join_ball(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            ball, angle = np.full(len(b), -1), np.zeros(len(b))
            for c, g in b.reset_index(drop=True).groupby("bx", dropna=True):
                x = np.stack([np.frombuffer(v) for v in g["x"]])
                a = _angles(x, np.frombuffer(c).reshape(-1, x.shape[1]))
                k = a.argmin(1)
                best = a[np.arange(len(x)), k]
                ball[g.index[best <= half]] = k[best <= half]
                angle[g.index[best <= half]] = best[best <= half]
            yield pd.DataFrame({"id": b["id"], "c": b["c"], "ball": ball, "angle": angle, "x": b["x"]})

    placed = rows.where("ok").join(balls, "c", "left").mapInPandas(join_ball, "id long, c int, ball int, angle double, x binary")
    # a node is a ball, or a row on its own; its number is the smallest row id in it
    placed = materialize(placed, "placed")
    group = placed.where("ball >= 0").groupBy("c", "ball").agg(F.min("id").alias("node"), F.count(F.lit(1)).alias("size"), F.max("angle").alias("radius"))
    members = placed.join(group.select("c", "ball", "node", "size"), ["c", "ball"], "left").withColumn("node", F.coalesce("node", "id"))
    members = materialize(members.select("id", "node", F.coalesce("size", F.lit(1)).alias("size"), "x"), "members")
    lone = placed.where("ball < 0").select("id", F.col("id").alias("node"), F.lit(1).cast("long").alias("size"), F.lit(0.0).alias("radius"), "x")

    def ball_rows(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            dims = centre.value.shape[1]
            x = [np.frombuffer(c).reshape(-1, dims)[k].tobytes() for c, k in zip(b["bx"], b["ball"], strict=True)]
            yield pd.DataFrame({"node": b["node"], "size": b["size"], "radius": b["radius"], "x": x})

    centres = group.join(balls, "c").mapInPandas(ball_rows, "node long, size long, radius double, x binary")
    nodes = materialize(lone.select("node", "size", "radius", "x").unionByName(centres), "nodes")

    # 4. overlapping shards of nodes; those of one centre are dealt over several shards that are probed together
    k = centre.value.shape[0]
    cents = centre.value
    gaps, band = centre_gaps(cents), border_band(fitted, apart, cents, link, min(overlap, k))

    def route(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if b.empty:
                continue
            x = np.stack([np.frombuffer(v) for v in b["x"]])
            s = x @ cents.T
            top = np.argsort(-s, axis=1, kind="stable")[:, : min(overlap, k)]
            i = np.repeat(np.arange(len(b)), top.shape[1])
            yield pd.DataFrame({"shard": top.ravel(), "node": b["node"].to_numpy()[i], "radius": b["radius"].to_numpy()[i], "x": b["x"].to_numpy()[i]})

    routed = materialize(nodes.mapInPandas(route, "shard int, node long, radius double, x binary"), "routed")
    load = {int(r.shard): max(1, -(-int(r.n) // (2 * overlap * shard_rows))) for r in routed.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}
    cuts = F.create_map(*[F.lit(v) for a, w in load.items() for v in (a, w)])
    routed = routed.withColumn("cut", F.pmod(F.xxhash64(F.lit("cut"), "node"), cuts[F.col("shard")]))

    def adjacency(b: pd.DataFrame) -> pd.DataFrame:
        x = np.stack([np.frombuffer(v) for v in b["x"]])
        adj, ids = build_graph(x, degree), b["node"].to_numpy()
        return pd.DataFrame({"node": ids, "near": [ids[a].tolist() for a in adj]})

    lists = routed.groupBy("shard", "cut").applyInPandas(adjacency, "node long, near array<long>")
    # a node stands in `overlap` shards at most, so its united list is bounded
    graph = materialize(lists.groupBy("node").agg(F.array_distinct(F.flatten(F.collect_list("near"))).alias("near")), "graph")

    # 5. every node searches all cuts of its shards and of those behind near borders; a shard's many searches are dealt over several tasks
    def probe(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in (whole.iloc[at : at + 1024] for whole in batches for at in range(0, len(whole), 1024)):
            i, shard = probed_shards(np.stack([np.frombuffer(v) for v in b["x"]]), b["radius"].to_numpy(), cents, link, min(overlap, k), band, gaps)
            yield pd.DataFrame({"shard": shard, "node": b["node"].to_numpy()[i], "radius": b["radius"].to_numpy()[i], "x": b["x"].to_numpy()[i]})

    probes = nodes.mapInPandas(probe, "shard int, node long, radius double, x binary")
    asks = {int(r.shard): max(1, -(-int(r.n) // (8 * shard_rows))) for r in probes.groupBy("shard").agg(F.count(F.lit(1)).alias("n")).collect()}
    deals = F.create_map(*[F.lit(v) for a, w in asks.items() for v in (a, w)])
    asked = probes.select("shard", "node", "radius", "x", F.explode(F.sequence(F.lit(0), (cuts[F.col("shard")] - 1).cast("int"))).alias("cut"))
    both = routed.select("shard", "cut", "node", "radius", "x", F.lit(True).alias("stored")).join(graph, "node", "left")
    both = both.withColumn("deal", F.explode(F.sequence(F.lit(0), deals[F.col("shard")] - 1)))
    asked = asked.withColumn("deal", F.pmod(F.xxhash64(F.lit("deal"), "node"), deals[F.col("shard")]).cast("int"))
    asked = asked.select("shard", F.col("cut").cast("long").alias("cut"), "deal", "node", "radius", "x", F.lit(False).alias("stored"), F.lit(None).cast("array<long>").alias("near"))
    work = both.select(asked.columns).unionByName(asked)

    def search(b: pd.DataFrame) -> pd.DataFrame:
        st, q = b[b["stored"]], b[~b["stored"]]
        ids = st["node"].to_numpy()
        x, rad = np.stack([np.frombuffer(v) for v in st["x"]]) if len(st) else np.zeros((0, 1)), st["radius"].to_numpy()
        a, z, angle = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
        if len(st) and len(q):
            at = {int(i): j for j, i in enumerate(ids)}
            adj = [[at[i] for i in near if i in at] for near in st["near"]]  # united lists, as far as they lie in this shard
            graph = ShardGraph(x, adj, rad)
            asked, y = q["node"].to_numpy(), np.stack([np.frombuffer(v) for v in q["x"]])
            reach, place = link + q["radius"].to_numpy() + _EPS, np.array([at.get(int(i), -1) for i in asked])
            # a node of this graph starts at its own place, where its links are near
            for who, width in ((np.flatnonzero(place >= 0), 16), (np.flatnonzero(place < 0), 24)):
                row, hit, d = graph.search(y[who], reach[who], place[who], width)
                row = who[row]
                other = ids[hit] != asked[row]
                a, z, angle = np.concatenate([a, asked[row[other]]]), np.concatenate([z, ids[hit[other]]]), np.concatenate([angle, d[other]])
        return pd.DataFrame({"a": np.minimum(a, z), "b": np.maximum(a, z), "angle": angle})

    pairs = work.groupBy("shard", "cut", "deal").applyInPandas(search, "a long, b long, angle double").groupBy("a", "b").agg(F.min("angle").alias("angle"))
    info = nodes.select("node", "size", "radius")
    pairs = pairs.join(info.select(F.col("node").alias("a"), F.col("size").alias("na"), F.col("radius").alias("ra")), "a")
    pairs = materialize(pairs.join(info.select(F.col("node").alias("b"), F.col("size").alias("nb"), F.col("radius").alias("rb")), "b"), "node-pairs")

    # 6. verify: some pairs of nodes link throughout, the others are compared member by member in blocks
    whole = pairs.where(F.col("angle") + F.col("ra") + F.col("rb") <= link - 1e-7)
    part = pairs.where(F.col("angle") + F.col("ra") + F.col("rb") > link - 1e-7)
    inside = members.select("id", "node", F.col("size") - 1).toDF("id", "node", "own")
    all_of = whole.select(F.col("a").alias("node"), F.col("nb").alias("n")).unionByName(whole.select(F.col("b").alias("node"), F.col("na").alias("n")))
    all_of = all_of.groupBy("node").agg(F.sum("n").alias("n"))
    found = materialize(_verified(part, members, cosine), "verified")
    counts = found.groupBy("id").agg(F.sum("n").alias("n"))
    n_links = inside.join(all_of, "node", "left").withColumnRenamed("n", "n_all").join(counts, "id", "left").withColumnRenamed("n", "n_some")
    linked = whole.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(found.select(F.col("node").alias("u"), F.col("other").alias("v")))
    comp = connected_components(linked)
    keys = rows.select("id", "key")
    named = nodes.select("node").join(comp, "node", "left").select("node", F.coalesce("component", "node").alias("first"))
    named = named.join(keys.select(F.col("id").alias("first"), F.col("key").alias("component_id")), "first").drop("first")  # one row per node; a large component's are split by AQE
    out = n_links.join(named, "node").join(keys, "id").select(
        F.col("key").alias(id_col), (F.col("own") + F.coalesce("n_all", F.lit(0)) + F.coalesce("n_some", F.lit(0))).cast("long").alias("n_links"), "component_id",
    )
    bad = rows.where("not ok").select(F.col("key").alias(id_col), F.lit(0).cast("long").alias("n_links"), F.col("key").alias("component_id"))
    return out.unionByName(bad).withColumn("kept", F.col(id_col) == F.col("component_id"))


def _verified(part: DataFrame, members: DataFrame, cosine: float, block: int = 1024) -> DataFrame:
    """Links of members across pairs of nodes: ``(id, n, node, other)``, per member and pair the number found.

    Members of a node are cut into blocks of about ``block``; a pair of nodes becomes pairs of
    blocks, each compared in one matrix product, so no list of member pairs is ever made.
    """
    cut = F.pmod(F.xxhash64(F.lit("block"), "id"), F.ceil(F.col("size") / block)).cast("int")
    packed = members.withColumn("cut", cut).groupBy("node", "cut").agg(F.collect_list(F.struct("id", "x")).alias("m"))
    grid = part.select("a", "b", F.explode(F.sequence(F.lit(0), F.ceil(F.col("na") / block).cast("int") - 1)).alias("i"), F.ceil(F.col("nb") / block).cast("int").alias("jb"))
    grid = grid.select("a", "b", "i", F.explode(F.sequence(F.lit(0), F.col("jb") - 1)).alias("j"))
    left = packed.select(F.col("node").alias("a"), F.col("cut").alias("i"), F.col("m").alias("ma"))
    right = packed.select(F.col("node").alias("b"), F.col("cut").alias("j"), F.col("m").alias("mb"))

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            ids, counts, node, other = [], [], [], []
            for a, z, ma, mb in zip(b["a"], b["b"], b["ma"], b["mb"], strict=True):
                hit = np.stack([np.frombuffer(r["x"]) for r in ma]) @ np.stack([np.frombuffer(r["x"]) for r in mb]).T >= cosine
                for rows, n, own, oth in ((ma, hit.sum(1), a, z), (mb, hit.sum(0), z, a)):
                    for r, c in zip(rows, n, strict=True):
                        if c:
                            ids.append(r["id"])
                            counts.append(int(c))
                            node.append(own)
                            other.append(oth)
            yield pd.DataFrame({"id": np.array(ids, np.int64), "n": np.array(counts, np.int64), "node": np.array(node, np.int64), "other": np.array(other, np.int64)})

    return grid.join(left, ["a", "i"]).join(right, ["b", "j"]).select("a", "b", "ma", "mb").mapInPandas(compare, "id long, n long, node long, other long")


def audit_recall(vectors: DataFrame, result: DataFrame, cosine: float = 0.9, every: int = 100, id_col: str = "vec_id", vec_col: str = "embedding", block: int = 4096) -> DataFrame:
    """Exact link counts of the ids divisible by ``every``, beside those found: ``(id, exact, found)``.

    The queries are compared with all rows in blocks, as matrix products where the rows are.
    """
    slim = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("v")).where("id is not null")
    asked = slim.where(f"id % {every} = 0").withColumn("g", F.pmod(F.xxhash64("id"), F.lit(1 + slim.count() // (every * block))))
    sets = asked.groupBy("g").agg(F.collect_list(F.struct("id", "v")).alias("q"))

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            x, ok = unit_rows(b["v"].tolist())
            for q in b["q"].iloc[:1]:
                y, good = unit_rows([r["v"] for r in q])
                hit = (y @ x.T >= cosine) & good[:, None] & ok[None, :]
                ids = np.array([r["id"] for r in q])
                own = ids[:, None] == b["id"].to_numpy()[None, :]
                yield pd.DataFrame({"id": ids, "exact": (hit & ~own).sum(1)})

    exact = None
    for row in sets.select("g").collect():
        part = slim.crossJoin(F.broadcast(sets.where(F.col("g") == row.g).select("q"))).mapInPandas(count, "id long, exact long")
        exact = part if exact is None else exact.unionByName(part)
    exact = exact.groupBy("id").agg(F.sum("exact").alias("exact"))
    return exact.join(result.select(F.col(id_col).alias("id"), F.col("n_links").alias("found")), "id")


def vector_duplicates(spark, sf_dir: str) -> DataFrame:
    """Query op6: links and components of all embeddings."""
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
