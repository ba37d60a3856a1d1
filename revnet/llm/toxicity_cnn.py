"""Toxicity by a convolutional text classifier trained in numpy.

A word's embedding is the mean of hashed rows of the word and of its leading 3 to 8 characters;
filters of several widths run over the embeddings of a whole text, their largest values feed a
logistic output, and Platt scaling makes it a probability. Thresholds are calibrated by language.
"""

from __future__ import annotations

import itertools
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import append_columns
from ._learn import Adam, fit_calibration, fold, labelled_sample, sigmoid

_WORD = re.compile(rb"[0-9a-z_\x80-\xff]+")
WIDTHS = (1, 2, 3)
PAD = max(WIDTHS) - 1
_LENGTHS = (3, 4, 5, 6, 7, 8)
_CELLS = len(_LENGTHS) + 1
_MASK = (1 << 24) - 1


def words(text: str | None) -> list[bytes]:
    """Lower-case words as UTF-8 bytes."""
    return _WORD.findall(text.lower().encode("utf-8", "surrogatepass")) if text else []


def buckets(word: bytes) -> list[int]:
    """Hash cells of a word: itself and its beginnings of 3 to 8 bytes, by one running checksum."""
    out, crc, at = [], 0, 0
    for n in _LENGTHS:
        if n > len(word):
            break
        crc = zlib.crc32(word[at:n], crc)
        at = n
        out.append((crc * 0x9E3779B1 + n) & _MASK)
    out.append((zlib.crc32(word[at:], crc) * 0x85EBCA6B + 1) & _MASK)
    return out


class Cnn:
    """The classifier; cells not seen in training have a zero row."""

    def __init__(self, rows: dict[int, int], table: np.ndarray, params: dict[str, np.ndarray]):
        self.rows, self.table, self.p = rows, table, params
        self.scale, self.shift = 1.0, 0.0
        self.thresholds: dict[str, float] = {}
        self._reset()

    def _reset(self) -> None:
        self.known: dict[bytes, int] = {}
        self.vectors = np.zeros((4096, self.table.shape[1]), np.float32)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("known", "vectors")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self._reset()

    def embed(self, tokens: list[bytes], store: int = 150_000) -> np.ndarray:
        """Embeddings of a text's words between zero rows; words are kept in a bounded store."""
        if len(self.known) > store:
            self._reset()
        known = self.known
        idx = list(map(known.get, tokens))
        if None in idx:
            first, cells, many = len(known), [], []
            for t, i in enumerate(idx):
                if i is None:
                    w = tokens[t]
                    i = known.get(w)
                    if i is None:
                        i = known[w] = len(known)
                        own = buckets(w)
                        cells += own
                        many.append(len(own))
                    idx[t] = i
            self._add(first, cells, many)
        x = np.zeros((len(idx) + 2 * PAD, self.table.shape[1]), np.float32)
        if idx:
            x[PAD:-PAD] = self.vectors[idx]
        return x

    def _add(self, first: int, cells: list[int], many: list[int]) -> None:
        """Vectors of new words, numbered from ``first``, from the cells of all of them and the number that each has."""
        while first + len(many) > len(self.vectors):
            self.vectors = np.concatenate([self.vectors, np.zeros_like(self.vectors)])
        rows = np.fromiter(map(self.rows.get, cells, itertools.repeat(-1)), np.int64, len(cells))  # the last row is zero
        n = np.array(many)
        self.vectors[first : first + len(n)] = np.add.reduceat(self.table[rows], np.cumsum(n) - n) / n[:, None].astype(np.float32)

    def pooled(self, x: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """Largest filter values and, by width, their places."""
        best, place = [], []
        for w in WIDTHS:
            n = len(x) - w + 1
            z = x[:n] @ self.p[f"f{w}"][0]
            for j in range(1, w):
                z += x[j : j + n] @ self.p[f"f{w}"][j]
            at = z.argmax(0)
            place.append(at)
            best.append(z[at, np.arange(z.shape[1])])
        return np.concatenate(best) + self.p["fb"], place

    def logit(self, tokens: list[bytes]) -> float:
        return float(np.maximum(self.pooled(self.embed(tokens))[0], 0) @ self.p["o"] + self.p["ob"][0])

    def score(self, text: str | None) -> float:
        return float(sigmoid(np.float64(self.scale * self.logit(words(text)) + self.shift)))


def train(texts: list[str | None], y: np.ndarray, langs: list[str | None], dims: int = 8, filters: int = 12, epochs: int = 3, seed: int = 7, least: int = 4, prior: float = 8.0) -> Cnn:
    """Train on whole texts; a fifth of them calibrates the output and the languages' thresholds."""
    rng = np.random.default_rng(seed)
    held = np.arange(len(y)) % 5 == 4
    number: dict[bytes, int] = {}
    docs = [np.fromiter((number.setdefault(w, len(number)) for w in words(t)), np.int64) for t in texts]
    cells = np.full((max(len(number), 1), _CELLS), -1, np.int64)
    for w, i in number.items():
        b = buckets(w)
        cells[i, : len(b)] = b
    many = (cells >= 0).sum(1)
    ids, cells = np.unique(cells, return_inverse=True)
    cells = cells.reshape(-1, _CELLS)
    df, pos = np.zeros(len(ids), np.int64), np.zeros(len(ids), np.int64)
    for i in np.flatnonzero(~held):
        seen = np.unique(cells[np.unique(docs[i])])
        df[seen] += 1
        if y[i]:
            pos[seen] += 1
    keep = (df >= least) & (ids >= 0)
    row = np.where(keep, np.cumsum(keep) - 1, int(keep.sum()))  # the last row stays zero
    cells = row[cells]
    rate = float(np.clip(y[~held].mean() if (~held).any() else 0.5, 0.01, 0.99))
    p = (pos[keep] + prior * rate) / (df[keep] + prior)
    table = rng.normal(0, 0.02, (int(keep.sum()) + 1, dims)).astype(np.float32)
    table[:-1, 0] = np.log(p / (1 - p)) - np.log(rate / (1 - rate))  # starts from the cell's log odds, drawn to the overall rate
    table[-1] = 0
    params = {f"f{w}": rng.normal(0, 0.3, (w, dims, filters)).astype(np.float32) for w in WIDTHS}
    for w in WIDTHS:
        params[f"f{w}"][:, 0, :] = np.abs(params[f"f{w}"][:, 0, :]) + 0.2
    k = filters * len(WIDTHS)
    params |= {"fb": np.zeros(k, np.float32), "o": rng.normal(0.1, 0.05, k).astype(np.float32), "ob": np.array([-3.0], np.float32)}
    model = Cnn({int(b): r for r, b in enumerate(ids[keep])}, table, params)
    opt = Adam(params, 0.01)
    second = np.full(len(table), 1e-3, np.float32)  # Adagrad sums of the embedding rows
    share = (1 / np.maximum(many, 1)).astype(np.float32)

    def embedded(i: int) -> np.ndarray:
        x = np.zeros((len(docs[i]) + 2 * PAD, dims), np.float32)
        if len(docs[i]):
            own, back = np.unique(docs[i], return_inverse=True)
            x[PAD:-PAD] = (table[cells[own]].sum(1) * share[own][:, None])[back]
        return x

    order = np.flatnonzero(~held)
    for _ in range(epochs):
        rng.shuffle(order)
        for at in range(0, len(order), 32):
            grads = {key: np.zeros_like(v) for key, v in params.items()}
            rows, steps = [], []
            batch = order[at : at + 32]
            for i in batch:
                x = embedded(i)
                z, place = model.pooled(x)
                h = np.maximum(z, 0)
                d = float(sigmoid(h @ params["o"] + params["ob"][0]) - y[i]) / len(batch)
                grads["o"] += d * h
                grads["ob"] += d
                dz = d * params["o"] * (z > 0)
                grads["fb"] += dz
                for c, w in enumerate(WIDTHS):
                    g = dz[c * filters : (c + 1) * filters, None]
                    for j in range(w):
                        grads[f"f{w}"][j] += (g * x[place[c] + j]).T
                        t = place[c] + j - PAD
                        ok = (t >= 0) & (t < len(docs[i])) & (g[:, 0] != 0)
                        if ok.any():
                            own = docs[i][t[ok]]
                            rows.append(cells[own].ravel())
                            steps.append(np.repeat((g * params[f"f{w}"][j].T)[ok] * share[own][:, None], _CELLS, axis=0))
            opt.step(grads)
            if rows:
                r, back = np.unique(np.concatenate(rows), return_inverse=True)
                g = np.zeros((len(r), dims), np.float32)
                np.add.at(g, back, np.concatenate(steps))
                second[r] += (g * g).mean(1)
                table[r] -= 0.02 * g / np.sqrt(second[r])[:, None]
                table[-1] = 0
    idx = np.flatnonzero(held)
    z = np.array([np.maximum(model.pooled(embedded(i))[0], 0) @ params["o"] + params["ob"][0] for i in idx]) if len(idx) else np.zeros(0)
    if len(idx) and 0 < y[idx].sum() < len(idx):
        w, b = fit_calibration(z, y[idx])
        model.scale, model.shift = float(max(w[0], 1e-3)), b
    p = sigmoid(model.scale * z + model.shift)
    model.thresholds = {"": best_threshold(p, y[idx])}
    for lang in {x for x in langs if x}:
        own = np.array([langs[i] == lang for i in idx], bool)
        if own.sum() >= 50 and y[idx][own].sum() >= 5:
            model.thresholds[lang] = best_threshold(p[own], y[idx][own])
    return model


def best_threshold(p: np.ndarray, y: np.ndarray) -> float:
    """Middle of the gap around the cut of highest F1; 0.5 without positives."""
    if not y.sum():
        return 0.5
    order = np.argsort(-p)
    ps, hit = p[order], np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(p) + 1) + y.sum())
    i = int(f1.argmax())
    return float((ps[i] + (ps[i + 1] if i + 1 < len(ps) else 0)) / 2)


def fit(docs: DataFrame, labels: DataFrame, use: Column, max_rows: int = 6000, max_bytes: int = 400_000, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", label_col: str = "toxic") -> Cnn:
    """Fit on at most ``max_rows`` labelled rows for which ``use`` (of ``_id``) holds."""
    pdf = labelled_sample(docs, labels, label_col, [F.col(text_col).alias("_text"), F.col(lang_col).alias("_lang")], use, max_rows, max_bytes, id_col, text_col)
    pdf = pdf.toArrow().to_pandas().sort_values("_id", kind="stable")
    langs = [x if isinstance(x, str) else None for x in pdf["_lang"]]
    texts = [x if isinstance(x, str) else None for x in pdf["_text"]]
    return train(texts, pdf["_label"].to_numpy(np.float64), langs)


def scored(docs: DataFrame, model: Cnn, cut: float = 0.3, text_col: str = "text", lang_col: str = "lang", keep: list[str] | None = None, prefix: str = "") -> DataFrame:
    """``docs`` (or its columns ``keep``) with score, predicted, threshold and flagged, named after ``prefix``, for whole texts.

    ``score`` depends on the text alone; ``predicted`` is 1 from ``cut`` on; ``threshold`` is the
    calibrated one of the row's language (unknown or null language: of all) and ``flagged`` applies
    it. Null, empty and wordless texts get the score of no words. Repeated rows repeat.
    """
    sent = docs.sparkSession.sparkContext.broadcast(model)  # its size is bound by the training sample

    def make():
        m = sent.value

        def work(text, lang):
            s = np.fromiter(map(m.score, text), np.float64, len(text))
            th = np.fromiter((m.thresholds.get(x or "", m.thresholds[""]) for x in lang), np.float64, len(lang))
            got = {"score": pa.array(s), "predicted": pa.array((s >= cut).astype(np.int32)), "threshold": pa.array(th), "flagged": pa.array(s >= th)}
            return {prefix + k: v for k, v in got.items()}

        return work

    inputs = [F.col(text_col), F.col(lang_col).cast("string")]
    return append_columns(docs, inputs, make, ", ".join(f"{prefix}{x}" for x in ("score double", "predicted int", "threshold double", "flagged boolean")), keep)


def classify(docs: DataFrame, model: Cnn, cut: float = 0.3, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """``(id_col, score, predicted, threshold, flagged)`` of every row; see ``scored``."""
    return scored(docs, model, cut, text_col, lang_col, [id_col])


def learned_rows(id_col: str = "_id") -> Column:
    """Rows whose labels may be learned: CRC-32 of the id modulo 4 is not 2."""
    return fold(F.col(id_col), 4) != 2


def toxicity(spark, sf_dir: str) -> DataFrame:
    """Query op10: toxicity of all documents."""
    docs, labels = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = classify(docs, fit(docs, labels, learned_rows()))
    return out.select("doc_id", (~learned_rows("doc_id")).alias("held_out"), "score", "predicted", "threshold", "flagged")
