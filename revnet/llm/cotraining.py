"""Quality classifier by co-training of two views: text content and page metadata.

Each view is a logistic regression. In every round each labels the unlabelled pool, and the labels it
is surest of, of both classes, join the other view's training set, with weights that fall to zero as
its calibrated probability nears a toss-up; so a weak view teaches too, but little. At the end both
views are calibrated on held-back labels and combined into one probability, with which every
document is scored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import append_columns
from ._learn import fit_calibration, fit_logistic, fold, labelled_sample, sigmoid

HASHED = 512
DENSE = 24
_META = 96
_PUNCT = re.compile(r"[^\w\s]{2,}")


def _classes() -> np.ndarray:
    """One class number for each byte: letters by case, digits, spaces, lines, marks, controls, others."""
    c = np.zeros(256, np.int64)
    c[:] = 7
    c[0:32] = 6
    c[33:127] = 5
    c[ord("a") : ord("z") + 1] = 0
    c[ord("A") : ord("Z") + 1] = 1
    c[ord("0") : ord("9") + 1] = 2
    c[32], c[10] = 3, 4
    return c


_CLASS = _classes()


def content_features(text: str | None, known: dict[str, int]) -> np.ndarray:
    """Shape of the text and hashed words, all bounded whatever its length; no text gives zeros but for a flag."""
    x = np.zeros(DENSE + HASHED, np.float32)
    raw = (text or "").encode("utf-8", "surrogatepass")
    words = (text or "").split()
    if not words:
        x[0] = 1
        return x
    kinds = np.bincount(_CLASS, weights=np.bincount(np.frombuffer(raw, np.uint8), minlength=256), minlength=8) / len(raw)
    x[1:9] = kinds
    n = len(words)
    distinct = set(words)
    lines = text.split("\n")
    same = sum(map(str.__eq__, words, words[1:]))
    joined = " ".join(words)
    x[9] = len(distinct) / n
    x[10] = min(1.0, (n - len(distinct)) / max(n**0.5, 1) / 8)
    x[11] = same / n
    x[12] = len(raw) / n / 16
    x[13] = 1 - len(set(lines)) / len(lines)
    x[14] = min(1.0, len(lines) / n * 5)
    x[15] = len(_PUNCT.findall(joined)) / n
    x[16] = joined.count(" | ") / n
    x[17] = joined.count("!") / n
    x[18] = np.log1p(n) / 10
    x[19] = sum(map(str.isupper, distinct)) / len(distinct)
    x[20] = joined.count(".") / n
    x[21] = joined.count("http") / n * 5
    x[22] = max(map(len, distinct)) > 60
    idx = []
    for w in distinct:
        i = known.get(w)
        if i is None:
            i = known[w] = xxhash.xxh32_intdigest(w.lower()) % HASHED
        idx.append(i)
    x[DENSE:] = np.bincount(idx, minlength=HASHED) / len(distinct) ** 0.5 / 8
    if len(known) > 150_000:
        known.clear()
    return x


def metadata_features(lang: str | None, source: str | None, n_chars: float | None) -> np.ndarray:
    """Language and source by hashed cells, declared length by buckets; nulls have cells of their own."""
    x = np.zeros(_META, np.float32)
    x[xxhash.xxh32_intdigest(f"l{lang}") % 16] = 1
    x[16 + xxhash.xxh32_intdigest(f"s{source}") % 48] = 1
    if n_chars is None or not np.isfinite(n_chars) or n_chars < 0:
        x[64] = 1
    else:
        x[65] = np.log1p(n_chars) / 12
        x[66 + min(int(np.log2(n_chars + 1)), _META - 67)] = 1
    return x


@dataclass
class CoTrained:
    """Weights of both views, their calibrations, and of their combination."""

    content: tuple[np.ndarray, float]
    metadata: tuple[np.ndarray, float]
    combine: tuple[np.ndarray, float]
    view_calibration: list[tuple[np.ndarray, float]]
    log: list[dict] = field(default_factory=list)

    def score(self, c: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Calibrated probabilities of quality: of the content view, the metadata view, and both."""
        zc, zm = c @ self.content[0] + self.content[1], m @ self.metadata[0] + self.metadata[1]
        pc, pm = (sigmoid(np.clip(z, -15, 15) * w[0] + b) for z, (w, b) in zip((zc, zm), self.view_calibration, strict=True))
        both = np.stack([np.clip(zc, -15, 15), np.clip(zm, -15, 15)], 1) @ self.combine[0] + self.combine[1]
        return pc, pm, sigmoid(both)


def surest(p: np.ndarray, taken: dict[int, float], most: int) -> list[tuple[int, float]]:
    """``(row, label)`` of the up to ``most`` rows surest of each class that are not ``taken``, from probabilities of 1.

    Shares of the classes follow the probabilities' own: a class gets ``most`` times its mean
    probability over that of the commoner class, one at least. Ties go to earlier rows; a row gets one label.
    """
    free = np.array([i for i in range(len(p)) if i not in taken], np.int64)
    if not len(free):
        return []
    mean = float(np.clip(p.mean(), 1e-6, 1 - 1e-6))
    out: list[tuple[int, float]] = []
    used: set[int] = set()
    for label, conf, own in ((1.0, p, mean), (0.0, 1 - p, 1 - mean)):
        n = max(1, round(most * own / max(mean, 1 - mean)))
        order = free[np.argsort(-conf[free], kind="stable")]
        picked = [i for i in order.tolist() if i not in used][:n]
        used.update(picked)
        out += [(i, label) for i in picked]
    return out


def co_train(c: np.ndarray, m: np.ndarray, y: np.ndarray, pool_c: np.ndarray, pool_m: np.ndarray, rounds: int = 4, most: int | None = None) -> CoTrained:
    """Co-train from labelled rows and an unlabelled pool; every fifth labelled row is held back to calibrate.

    In each round each view hands the other the up to ``most`` rows of the commoner class and its
    share of the other of which it is surest (see ``surest``), with half the calibrated margin as weight.
    By default ``most`` is what lets the pool last for all rounds.
    """
    most = most or max(1, len(pool_c) // (2 * max(1, rounds)))
    held = np.arange(len(y)) % 5 == 4
    views, pools = (c, m), (pool_c, pool_m)
    given: list[dict[int, tuple[float, float]]] = [{}, {}]  # labels and weights that each view has been given
    log, fits = [], []
    for r in range(rounds + 1):
        fits, cal = [], []
        for v in (0, 1):
            idx = np.fromiter(given[v], np.int64, len(given[v]))
            extra = np.array(list(given[v].values()), np.float64).reshape(-1, 2)
            x = np.concatenate([views[v][~held], pools[v][idx]])
            t = np.concatenate([y[~held], extra[:, 0]])
            w = np.concatenate([np.ones(int((~held).sum())), extra[:, 1]])
            fits.append(fit_logistic(x, t, w.astype(np.float32)))
            cal.append(fit_calibration(views[v][held] @ fits[v][0] + fits[v][1], y[held]) if held.any() else (np.ones(1, np.float32), 0.0))
        if r == rounds:
            break
        passed = []
        for v in (0, 1):
            z = np.clip(pools[v] @ fits[v][0] + fits[v][1], -15, 15)
            p = sigmoid(z * cal[v][0][0] + cal[v][1])
            new = surest(p, given[1 - v], most)
            given[1 - v].update({i: (label, 0.5 * max(0.0, 2 * float(p[i] if label else 1 - p[i]) - 1)) for i, label in new})
            passed.append(len(new))
        log.append({"round": r, "content_to_metadata": passed[0], "metadata_to_content": passed[1]})
    z = np.stack([v[held] @ w + b for v, (w, b) in zip(views, fits, strict=True)], 1) if held.any() else np.zeros((0, 2))
    combine = fit_calibration(z, y[held]) if held.any() else (np.ones(2, np.float32), 0.0)
    return CoTrained(fits[0], fits[1], combine, cal, log)


def fit(docs: DataFrame, labels: DataFrame, use: Column | None = None, max_rows: int = 5000, pool_rows: int = 3000, max_bytes: int = 400_000, rounds: int = 4, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality") -> CoTrained:
    """Fit on at most ``max_rows`` labelled rows and ``pool_rows`` unlabelled ones, chosen by id hash, of texts up to ``max_bytes``.

    Without any label, as with an empty table, the model answers 0.5 throughout; without unlabelled
    rows the views stay apart until they are combined.
    """
    cols = [F.col(text_col).alias("_text"), *(F.col(x).alias(f"_{x}") for x in ("lang", "source", "n_chars"))]
    use = F.lit(True) if use is None else use
    lab = labelled_sample(docs, labels, label_col, cols, use, max_rows, max_bytes, id_col, text_col)
    named = labels.select(F.col(id_col).alias("_id")).where("_id is not null").distinct()
    ids = docs.select(F.col(id_col).alias("_id")).where("_id is not null").distinct().join(named, "_id", "left_anti")
    picked = ids.orderBy(F.xxhash64(F.lit("pool"), "_id"), "_id").limit(pool_rows)
    small = docs.where(F.coalesce(F.octet_length(text_col), F.lit(0)) <= max_bytes)
    pool = small.join(F.broadcast(picked), small[id_col] == picked["_id"]).select("_id", F.lit(-1).alias("_label"), *cols)
    pdf = _featured(lab.unionByName(pool)).toArrow().to_pandas().sort_values(["_id"], kind="stable")
    c = np.stack([np.frombuffer(x, np.float32) for x in pdf["c"]]) if len(pdf) else np.zeros((0, DENSE + HASHED), np.float32)
    m = np.stack([np.frombuffer(x, np.float32) for x in pdf["m"]]) if len(pdf) else np.zeros((0, _META), np.float32)
    y = pdf["_label"].to_numpy(np.int64)
    lab_rows = y >= 0
    if not lab_rows.any():
        zero = lambda n: (np.zeros(n, np.float32), 0.0)
        return CoTrained(zero(c.shape[1]), zero(_META), zero(2), [zero(1), zero(1)])
    return co_train(c[lab_rows], m[lab_rows], y[lab_rows].astype(np.float64), c[~lab_rows], m[~lab_rows], rounds)


def _featured(rows: DataFrame) -> DataFrame:
    """Feature vectors of both views as bytes, computed where the rows are."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        known: dict[str, int] = {}
        for b in batches:
            c = [content_features(t if isinstance(t, str) else None, known).tobytes() for t in b["_text"]]
            m = [metadata_features(a, s, n).tobytes() for a, s, n in zip(b["_lang"], b["_source"], b["_n_chars"], strict=True)]
            yield pd.DataFrame({"_id": b["_id"], "_label": b["_label"], "c": c, "m": m})

    return rows.mapInPandas(run, "_id long, _label int, c binary, m binary")


def scored(docs: DataFrame, model: CoTrained, cut: float = 0.5, text_col: str = "text", keep: list[str] | None = None, prefix: str = "") -> DataFrame:
    """``docs`` (or its columns ``keep``) with content_score, metadata_score, score and keep, named after ``prefix``.

    Scores are calibrated probabilities of quality 1; ``keep`` holds from ``cut`` on, a score of just
    ``cut`` included. Null or empty texts and null metadata are features of their own. Repeated rows
    repeat, an empty table gives an empty result.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def make():
        model, known = sent.value, {}

        def work(text, lang, source, n_chars):
            c = np.stack([content_features(t, known) for t in text])
            m = np.stack([metadata_features(*x) for x in zip(lang, source, n_chars, strict=True)])
            pc, pm, p = (np.asarray(x, np.float64) for x in model.score(c, m))
            got = {"content_score": pa.array(pc), "metadata_score": pa.array(pm), "score": pa.array(p), "keep": pa.array(p >= cut)}
            return {prefix + k: v for k, v in got.items()}

        return work

    inputs = [F.col(text_col), F.col("lang").cast("string"), F.col("source").cast("string"), F.col("n_chars").cast("double")]
    return append_columns(docs, inputs, make, ", ".join(f"{prefix}{x}" for x in ("content_score double", "metadata_score double", "score double", "keep boolean")), keep)


def classify(docs: DataFrame, model: CoTrained, cut: float = 0.5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id_col, content_score, metadata_score, score, keep)`` of every row's whole text and metadata; see ``scored``."""
    return scored(docs, model, cut, text_col, [id_col])


def learned_rows(id_col: str = "_id") -> Column:
    """Rows whose labels may be learned: CRC-32 of the id modulo 5 is not 1."""
    return fold(F.col(id_col), 5) != 1


def quality(spark, sf_dir: str) -> DataFrame:
    """Query op2: quality of all documents."""
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = classify(docs, fit(docs, labels, learned_rows()))
    return out.withColumn("held_out", ~learned_rows("doc_id"))
