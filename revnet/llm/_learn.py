"""Pieces shared by the classifiers: bounded labelled samples, Adam, logistic fits and calibration."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(id_col: Column, modulus: int) -> Column:
    """CRC-32 of the id as text, modulo ``modulus``; a null id is in fold 0."""
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % modulus, F.lit(0))


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, columns: list[str], use: Column, max_rows: int, max_bytes: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """At most ``max_rows`` labelled rows of ``docs``, those of smallest id hash: ``(id, label, *columns)``.

    Only the ids are ordered; a list of at most ``max_rows`` ids is then joined to the documents.
    Texts of over ``max_bytes`` are left out of the sample (never out of the scoring).
    """
    own = labels.select(F.col(id_col).alias("_id"), F.col(label).cast("int").alias("_label")).where("_id is not null and _label is not null")
    own = own.where(use).groupBy("_id").agg(F.max("_label").alias("_label"))
    picked = own.orderBy(F.xxhash64("_id"), "_id").limit(max_rows)
    have = docs.where(F.coalesce(F.octet_length(text_col), F.lit(0)) <= max_bytes)
    return have.join(F.broadcast(picked), have[id_col] == picked["_id"]).select(F.col("_id"), F.col("_label"), *columns)


class Adam:
    """Adam steps over a dict of arrays."""

    def __init__(self, params: dict[str, np.ndarray], rate: float):
        self.p, self.rate, self.t = params, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}

    def step(self, grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] += 0.1 * (g - self.m[k])
            self.v[k] += 0.001 * (g * g - self.v[k])
            self.p[k] -= self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)


def sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -40, 40)))


def fit_logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray | None = None, l2: float = 1e-3, steps: int = 200, rate: float = 0.05) -> tuple[np.ndarray, float]:
    """Weights and bias of a logistic regression by full-batch Adam."""
    w = np.ones(len(y), np.float32) if weight is None else weight
    w = w / max(w.sum(), 1e-9)
    base = np.clip(float((w * y).sum()), 1e-4, 1 - 1e-4)
    p = {"w": np.zeros(x.shape[1], np.float32), "b": np.array([np.log(base / (1 - base))], np.float32)}
    opt = Adam(p, rate)
    for _ in range(steps):
        g = w * (sigmoid(x @ p["w"] + p["b"][0]) - y)
        opt.step({"w": (x.T @ g + l2 * p["w"]).astype(np.float32), "b": np.array([g.sum()], np.float32)})
    return p["w"], float(p["b"][0])


def fit_calibration(z: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, float]:
    """Platt scaling of one or several logits (columns of ``z``), kept finite by smoothed targets."""
    z = np.clip(z, -15, 15).reshape(len(y), -1).astype(np.float32)
    pos, neg = y.sum(), len(y) - y.sum()
    target = np.where(y > 0, (pos + 1) / (pos + 2), 1 / (neg + 2))
    w, b = fit_logistic(z, target, l2=1e-4, steps=600, rate=0.05)
    return np.maximum(w, 0), b
