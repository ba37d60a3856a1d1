"""SimHash near-duplicates by the generalised pigeonhole principle.

Bits that vary together are put into the same part; each fingerprint gets its own threshold per
part (from -1, not probed, upwards) by dynamic programming over estimated candidate counts, with
the thresholds adding up to ``distance - parts + 1``. Two fingerprints within ``distance`` then
agree with the probe of at least one part. Candidates meet in buckets, are verified on all 64
bits, and each bucket gives back a spanning forest of its verified links instead of all pairs.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._common import connected_components, discard, materialize

BITS = 64
_CHUNK = 1 << 15


def fingerprint(text: bytes | None, shingle: int = 3) -> int:
    """Unsigned 64-bit SimHash of one text: majority of each bit over all word shingles."""
    words = text.lower().split() if text else []  # bytes: A-Z and ASCII white space only
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.empty_like(ends)
    starts[0] = 0
    starts[1:] = ends[:-1] + 1
    digest = xxhash.xxh64_intdigest
    n = len(words) - shingle + 1
    first, last = starts[:n].tolist(), ends[shingle - 1 :].tolist()
    counts = np.zeros(BITS, np.int64)
    for at in range(0, n, _CHUNK):
        hashes = np.array([digest(joined[a:b], 42) for a, b in zip(first[at : at + _CHUNK], last[at : at + _CHUNK], strict=True)], dtype="<u8")
        bits = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(axis=0, dtype=np.int64)
    return int((1 << np.flatnonzero(2 * counts > n).astype(object)).sum()) if (2 * counts > n).any() else 0


def with_fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """``(id_col, fp LONG)`` for every row; null or wordless texts have fingerprint 0."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (whole.slice(at, 256) for whole in batches for at in range(0, whole.num_rows, 256)):
            fps = np.fromiter((fingerprint(t, shingle) for t in b.column(1).to_pylist()), dtype=np.uint64, count=b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps.view(np.int64))], names=["id", "fp"])

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("binary").alias("t"))
    return slim.mapInArrow(run, "id long, fp long").withColumnRenamed("id", id_col)


# --- plan: parts and thresholds ------------------------------------------------------------


def choose_parts(n: int, distance: int) -> int:
    """Number of parts from the number of distinct fingerprints: wider parts once buckets would fill."""
    for parts in range(distance + 1, 2, -1):
        if n <= 64 << (BITS // parts):
            return parts
    return 2


def group_bits(ones: np.ndarray, both: np.ndarray, n: int, parts: int) -> list[list[int]]:
    """Equal-sized parts; correlated bits meet in one part, so that the other parts stay selective.

    ``ones`` counts each bit, ``both`` each pair of bits, over all ``n`` fingerprints.
    """
    p = ones / max(n, 1)
    cov = both / max(n, 1) - np.outer(p, p)
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs(cov / np.outer(sd, sd))
    np.fill_diagonal(corr, 0)
    free, out = set(range(BITS)), []
    for i in range(parts):
        want = (BITS - sum(map(len, out))) // (parts - i)
        left = sorted(free)
        seed = left[int(np.argmax(corr[np.ix_(left, left)].sum(1)))]
        part = [seed]
        free.discard(seed)
        while len(part) < want:
            left = sorted(free)
            best = left[int(np.argmax(corr[np.ix_(left, part)].sum(1)))]
            part.append(best)
            free.discard(best)
        out.append(sorted(part))
    return out


def project(fps: np.ndarray, bits: list[int]) -> np.ndarray:
    """The given bits of each fingerprint as one small number."""
    out = np.zeros(len(fps), np.int64)
    for i, b in enumerate(bits):
        out |= ((fps >> np.uint64(b)) & np.uint64(1)).astype(np.int64) << i
    return out


def ball_masks(width: int, t: int) -> np.ndarray:
    """All flips of at most ``t`` of ``width`` bits."""
    masks = [sum(1 << b for b in c) for k in range(t + 1) for c in itertools.combinations(range(width), k)]
    return np.array(masks, np.int64)


def allocate(costs: list[np.ndarray], total: int) -> np.ndarray:
    """Per-row thresholds of least summed cost: ``costs[i][r, t+1]`` is part i at threshold t >= -1.

    Dynamic programming over the parts; thresholds of a row add up to ``total``.
    """
    rows, steps = costs[0].shape
    need = total + len(costs)  # thresholds are shifted by one, so that none is negative
    best = np.full((rows, need + 1), np.inf)
    best[:, 0] = 0
    back = []
    for c in costs:
        nxt, arg = np.full_like(best, np.inf), np.zeros((rows, need + 1), np.int8)
        for s in range(need + 1):
            for t in range(min(steps, s + 1)):
                v = best[:, s - t] + c[:, t]
                better = v < nxt[:, s]
                nxt[better, s] = v[better]
                arg[better, s] = t
        best = nxt
        back.append(arg)
    out, s, r = np.zeros((rows, len(costs)), np.int64), np.full(rows, need), np.arange(rows)
    for i in range(len(costs) - 1, -1, -1):
        out[:, i] = back[i][r, s] - 1
        s = s - back[i][r, s]
    return out


class Plan:
    """Parts, and estimated candidates of a probe by part, threshold and (folded) part value."""

    FOLD = 16  # histograms have at most 2**16 cells whatever the part's width

    def __init__(self, parts: list[list[int]], hist: list[np.ndarray], distance: int):
        self.parts, self.distance, self.total = parts, distance, distance - len(parts) + 1
        self.costs = []
        for bits, h in zip(parts, hist, strict=True):
            width, cells = len(bits), len(h)
            scale = 2.0 ** (width - np.log2(cells))
            idx, table = np.arange(cells), [np.zeros(cells)]
            for t in range(self.total + len(parts)):
                masks = ball_masks(width, t) if t <= 2 else np.arange(0)
                if t > 2 or len(masks) > 600:
                    table.append(np.full(cells, np.inf))
                    continue
                near = np.zeros(cells)
                for m in masks:
                    near += h[idx ^ (int(m) & (cells - 1))] / scale
                table.append(near + 2.0 * len(masks))  # reading candidates, and sending the probes
            self.costs.append(np.stack(table, 1))

    def thresholds(self, fps: np.ndarray) -> np.ndarray:
        costs = []
        for bits, table in zip(self.parts, self.costs, strict=True):
            costs.append(table[project(fps, bits) & (len(table) - 1)])
        return allocate(costs, self.total)

    def probes(self, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Rows (part, value, index into fps, is a probe): all stored entries and all probes."""
        t = self.thresholds(fps)
        part, value, who, probe = [], [], [], []
        for i, bits in enumerate(self.parts):
            v = project(fps, bits)
            for k in range(-1, int(t[:, i].max(initial=-1)) + 1):
                rows = np.flatnonzero(t[:, i] == k)
                if not len(rows):
                    continue
                masks = ball_masks(len(bits), max(k, 0))
                value.append((v[rows][:, None] ^ masks[None, :]).ravel())
                who.append(np.repeat(rows, len(masks)))
                # the first mask is the value itself: the stored entry, a probe too unless k is -1
                probe.append(np.full(len(rows) * len(masks), k >= 0))
                part.append(np.full(len(rows) * len(masks), i))
        if not part:
            z = np.zeros(0, np.int64)
            return z, z, z, z.astype(bool)
        return np.concatenate(part), np.concatenate(value), np.concatenate(who), np.concatenate(probe)


def make_plan(fps: DataFrame, distance: int, parts: int | None = None) -> Plan | None:
    """Count bits, pairs of bits and part values over all distinct fingerprints; fixed-size results only."""

    def pair_counts(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        both, n = np.zeros((BITS, BITS)), 0
        for b in batches:
            for at in range(0, len(b), 8192):
                x = np.unpackbits(b["fp"].to_numpy(np.int64)[at : at + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(np.float32)
                both += x.T @ x
                n += len(x)
        yield pd.DataFrame({"k": np.arange(BITS * BITS + 1), "c": np.append(both.ravel(), n).astype(np.int64)})

    got = fps.select("fp").mapInPandas(pair_counts, "k int, c long").groupBy("k").agg(F.sum("c").alias("c")).toArrow().to_pandas().sort_values("k")
    if got.empty or int(got.c.iloc[-1]) == 0:
        return None
    n, both = int(got.c.iloc[-1]), got.c.to_numpy(float)[:-1].reshape(BITS, BITS)
    groups = group_bits(np.diag(both), both, n, parts or choose_parts(n, distance))

    def values(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cells = [np.zeros(1 << min(len(g), Plan.FOLD), np.int64) for g in groups]
        for b in batches:
            x = b["fp"].to_numpy(np.int64).view(np.uint64)
            for g, h in zip(groups, cells, strict=True):
                h += np.bincount(project(x, g) & (len(h) - 1), minlength=len(h))
        for i, h in enumerate(cells):
            k = np.flatnonzero(h)
            yield pd.DataFrame({"part": np.full(len(k), i), "k": k, "c": h[k]})

    got = fps.select("fp").mapInPandas(values, "part int, k long, c long").groupBy("part", "k").agg(F.sum("c").alias("c")).toArrow().to_pandas()
    hist = []
    for i, g in enumerate(groups):
        h = np.zeros(1 << min(len(g), Plan.FOLD))
        own = got[got.part == i]
        h[own.k.to_numpy(np.int64)] = own.c.to_numpy(float)
        hist.append(h)
    return Plan(groups, hist, distance)


# --- candidates, verification, components ---------------------------------------------------


def bucket_forest(fps: np.ndarray, probe: np.ndarray, distance: int) -> list[tuple[int, int]]:
    """Spanning forest of the links within one bucket (indices); at least one end of a link is a probe.

    Grows one component at a time and compares only with fingerprints not yet reached, so a bucket
    of near copies costs about its size and no list of pairs is ever made.
    """
    order = np.argsort(~probe, kind="stable")
    left, out = order, []
    while len(left):
        x, left = left[0], left[1:]
        if not probe[x]:
            break  # only stored entries are left: they meet their probes in other buckets
        todo = [x]
        while todo and len(left):
            y = todo.pop()
            hit = np.bitwise_count(fps[left] ^ fps[y]) <= distance
            if hit.any():
                found = left[hit]
                out.extend((int(y), int(z)) for z in found)
                todo.extend(found.tolist())
                left = left[~hit]
    return out


def link_forest(fps: DataFrame, distance: int = 3, parts: int | None = None, heavy: int = 4096) -> DataFrame:
    """Links ``(fa, fb)`` between distinct fingerprints ``(fp)``, enough to connect all within ``distance``.

    Buckets of over ``heavy`` entries are divided again by the pigeonhole principle on the bits
    outside the shared part, so that no bucket of unrelated fingerprints grows with the corpus.
    """
    plan = make_plan(fps, distance, parts)
    schema = "part int, value long, fp long, probe boolean"
    if plan is None:
        return fps.sparkSession.createDataFrame([], "fa long, fb long")

    def spread(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            x = b["fp"].to_numpy(np.int64)
            for at in range(0, len(x), 20000):
                y = x[at : at + 20000]
                part, value, who, probe = plan.probes(y.view(np.uint64))
                yield pd.DataFrame({"part": part, "value": value, "fp": y[who], "probe": probe})

    entries = materialize(fps.select("fp").mapInPandas(spread, schema), "gph-entries")
    counts = entries.groupBy("part", "value").agg(F.count(F.lit(1)).alias("n"), F.max("probe").alias("any"))
    counts = counts.where("any and n > 1").select("part", "value", "n")
    e = entries.join(counts, ["part", "value"])
    groups, sub_parts = plan.parts, distance + 1

    def divide(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rest = [[b for b in range(BITS) if b not in g] for g in groups]
        cut = [[r[j::sub_parts] for j in range(sub_parts)] for r in rest]
        for b in batches:
            small = b[b.n <= heavy]
            if len(small):
                yield pd.DataFrame({"part": small.part, "value": small.value, "sub": -1, "subvalue": 0, "fp": small.fp, "probe": small.probe})
            large = b[b.n > heavy]
            for i, own in large.groupby("part"):
                x = own.fp.to_numpy(np.int64).view(np.uint64)
                for j, bits in enumerate(cut[int(i)]):
                    # members of a bucket may differ by a probe's flips inside the part, never by more outside than `distance`
                    yield pd.DataFrame({"part": own.part, "value": own.value, "sub": j, "subvalue": project(x, bits), "fp": own.fp, "probe": own.probe})

    placed = e.mapInPandas(divide, "part int, value long, sub int, subvalue long, fp long, probe boolean")
    keys = ["part", "value", "sub", "subvalue"]
    placed = placed.repartition(*keys).sortWithinPartitions(*keys)

    def verify(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        def links(run: pd.DataFrame) -> pd.DataFrame:
            x = run.fp.to_numpy(np.int64).view(np.uint64)
            k = run[keys].to_numpy(np.int64)
            cuts = np.flatnonzero((k[1:] != k[:-1]).any(1)) + 1
            probe, fa, fb = run.probe.to_numpy(bool), [], []
            for a, z in zip(np.append(0, cuts).tolist(), np.append(cuts, len(k)).tolist(), strict=True):
                if z - a > 1:
                    for i, j in bucket_forest(x[a:z], probe[a:z], distance):
                        fa.append(x[a + i])
                        fb.append(x[a + j])
            pair = np.array([fa, fb], np.uint64).reshape(2, -1).view(np.int64)
            return pd.DataFrame({"fa": pair[0], "fb": pair[1]})

        held: list[pd.DataFrame] = []
        for b in batches:
            if b.empty:
                continue
            k = b[keys].to_numpy(np.int64)
            last = int(np.flatnonzero(np.append(True, (k[1:] != k[:-1]).any(1)))[-1])  # the last bucket may go on
            if last:
                yield links(pd.concat([*held, b.iloc[:last]]))
                held = []
            elif held and not (held[-1][keys].iloc[-1].to_numpy(np.int64) == k[0]).all():
                yield links(pd.concat(held))
                held = []
            held.append(b.iloc[last:])
        if held:
            yield links(pd.concat(held))

    return placed.mapInPandas(verify, "fa long, fb long")


def simhash_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", distance: int = 3, shingle: int = 3, parts: int | None = None) -> DataFrame:
    """``(id_col, fp, component_id)`` per row of ``docs``; the component is its smallest id.

    Null and wordless texts have fingerprint 0 and link like any other. Equal fingerprints are one
    node, so copies cost one probe. Repeated rows give repeated results; rows with a null id are
    returned with their fingerprint's component, which such ids never name. An empty table gives
    an empty result; other columns are ignored.
    """
    fp = materialize(with_fingerprints(docs, id_col, text_col, shingle), "simhash-fp")
    nodes = materialize(fp.groupBy("fp").agg(F.min(id_col).alias("node")), "simhash-nodes")
    links = link_forest(nodes.select("fp"), distance, parts).distinct()
    a = nodes.select(F.col("fp").alias("fa"), F.col("node").alias("u"))
    b = nodes.select(F.col("fp").alias("fb"), F.col("node").alias("v"))
    comp = connected_components(links.join(a, "fa").join(b, "fb").select("u", "v").where("u is not null and v is not null"))
    of_fp = nodes.join(comp, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    return fp.join(of_fp, "fp").select(id_col, "fp", "component_id")


def near_duplicates(spark, sf_dir: str) -> DataFrame:
    """Query op3: fingerprints and components of all documents."""
    out = simhash_components(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
