"""Quality by naive-Bayes support vectors: indicators scaled by class log-count ratios, hinge loss by dual coordinate descent.

At most ``most`` labelled rows train the model; a logistic curve on out-of-fold margins turns margins into scores.
Defined cases: null and empty texts score by the intercept; without two classes the score is the constant share of label 1.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .features import SPACE, flat, indicators, sample, sigmoid, total, with_columns

MOST = 6000


def train(rows: list[np.ndarray], y: np.ndarray, c: float = 0.01, rounds: int = 8, seed: int = 3) -> tuple[np.ndarray, float]:
    ids, bounds = flat(rows)
    row = np.repeat(np.arange(len(y)), np.diff(bounds))
    p, n = (np.bincount(ids, weights=m[row], minlength=SPACE) + 1.0 for m in ((y == 1).astype(float), (y == 0).astype(float)))
    ratio = np.log((p / p.sum()) / (n / n.sum()))
    w, bias, sign = np.zeros(SPACE), 0.0, np.where(y == 1, 1.0, -1.0)
    alpha, norm = np.zeros(len(y)), np.array([float((ratio[r] ** 2).sum()) + 1 for r in rows])
    # one side must not outweigh the other by its number
    top = np.where(y == 1, c * len(y) / max(1, 2 * (y == 1).sum()), c * len(y) / max(1, 2 * (y == 0).sum()))
    order = np.random.default_rng(seed)
    for _ in range(rounds):
        for i in order.permutation(len(y)):
            r = ratio[rows[i]]
            slope = sign[i] * (float(w[rows[i]] @ r) + bias) - 1
            new = min(max(alpha[i] - slope / norm[i], 0.0), top[i])
            if new != alpha[i]:
                step = (new - alpha[i]) * sign[i]
                w[rows[i]] += step * r
                bias += step
                alpha[i] = new
    return w * ratio, bias


def fit(docs: DataFrame, labels: DataFrame, most: int = MOST, folds: int = 3) -> tuple[np.ndarray, float, float, float]:
    """Weights, intercept, and slope and shift of the logistic curve."""
    rows, found = sample(docs, labels, ["quality"], most)
    y = found[:, 0]
    if len(set(y.tolist())) < 2:
        share = float(y.mean()) if len(y) else 0.5
        return np.zeros(SPACE), 0.0, 1.0, float(np.log((share + 1e-9) / (1 - share + 1e-9)))
    margin, fold = np.zeros(len(y)), np.arange(len(y)) % folds
    for f in range(folds):
        inside, outside = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
        w, b = train([rows[i] for i in inside], y[inside])
        margin[outside] = total(w, *flat([rows[i] for i in outside])) + b
    a, s = 1.0, 0.0
    for _ in range(50):  # Newton steps of a two-parameter logistic fit
        p = sigmoid(a * margin + s)
        h = p * (1 - p) + 1e-6
        grad = np.array([((p - y) * margin).sum() + 1e-3 * a, (p - y).sum()])
        hess = np.array([[(h * margin**2).sum() + 1e-3, (h * margin).sum()], [(h * margin).sum(), h.sum()]])
        step = np.linalg.solve(hess, grad)
        a, s = a - np.clip(step[0], -1, 1), s - np.clip(step[1], -1, 1)
    return (*train(rows, y), max(float(a), 1e-3), float(s))


def scored(docs: DataFrame, model: tuple, text_col: str = "text", name: str = "score") -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(texts: pa.Array) -> list[pa.Array]:
        w, b, a, s = shared.value
        return [pa.array(sigmoid(a * (total(w, *indicators(texts)) + b) + s))]

    return with_columns(docs, text_col, [name], T.DoubleType(), run)


def report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """``doc_id, held_out, score, predicted``; rows whose id hash leaves 2 modulo 4 never train."""
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2, F.lit(False))
    marked = scored(docs.select("doc_id", "text"), fit(docs, labels.where(~held)))
    return marked.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
