"""Toxicity by a classifier chain: logistic models in a fixed order, later ones fed with the probabilities of earlier ones.

Training uses at most ``most`` labelled rows. The probabilities that a later model learns from are out of fold: each comes from a
model that has not seen the row. The models (one weight array each) travel to the tasks; every document is scored in one pass.

Defined cases: null and empty texts score by the intercepts; without labels, or with one class only, a category has the
constant share of its labels (none: 0). Null labels are left out of training. Other columns are carried along, whatever their names.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .features import SPACE, flat, indicators, sample, sigmoid, total, with_columns
from .runtime import fresh

MOST = 4000
RATIO = 20.0
CHAIN = ["low_quality", "toxic"]


def telling(p: np.ndarray, n: np.ndarray, share: float) -> np.ndarray:
    """Features whose rows (``p`` with the label, ``n`` without) differ from the overall share by a likelihood ratio that chance seldom reaches."""
    k = np.maximum(p + n, 1)
    found = np.maximum(p, 1e-9) * np.log(np.maximum(p, 1e-9) / (k * share)) + np.maximum(n, 1e-9) * np.log(np.maximum(n, 1e-9) / (k * (1 - share)))
    return (2 * found > RATIO) & (p + n >= 3)


def logistic(rows: list[np.ndarray], extra: np.ndarray, y: np.ndarray, l2: float = 0.1, steps: int = 150) -> tuple[np.ndarray, np.ndarray]:
    """Weights of the telling indicators, scaled by their log-odds, and of [1, extra...]; adaptive gradient steps."""
    ids, bounds = flat(rows)
    w, v = np.zeros(SPACE), np.zeros(extra.shape[1] + 1)
    dense = np.column_stack([np.ones(len(y)), extra])
    share = float(y.mean()) if len(y) else 0.0
    if not len(y) or share in (0.0, 1.0):
        v[0] = 40 * (2 * share - 1)
        return w, v
    every = np.repeat(np.arange(len(y), dtype=np.int32), np.diff(bounds))
    p, n = (np.bincount(ids, weights=c[every], minlength=SPACE) for c in (y.astype(float), 1.0 - y))
    used = np.flatnonzero(telling(p, n, share))
    place = np.full(SPACE, -1, np.int32)
    place[used] = np.arange(len(used))
    inverse = place[ids]
    row, inverse = every[inverse >= 0], inverse[inverse >= 0]
    bounds = np.searchsorted(row, np.arange(len(y) + 1))
    gain = np.abs(np.log((p + 0.5) / (y.sum() + 1) * ((1 - y).sum() + 1) / (n + 0.5)))[used]
    x, gx, gv = np.zeros(len(used)), np.full(len(used), 1e-6), np.full(len(v), 1e-6)
    v[0] = np.log(share / (1 - share))
    for _ in range(steps):
        s = np.concatenate([[0.0], np.cumsum((x * gain)[inverse])])
        error = sigmoid(s[bounds[1:]] - s[bounds[:-1]] + dense @ v) - y
        g = np.bincount(inverse, weights=error[row], minlength=len(used)) * gain + l2 * x
        h = dense.T @ error
        gx, gv = gx + g * g, gv + h * h
        x, v = x - 0.1 * g / np.sqrt(gx), v - 0.1 * h / np.sqrt(gv)
    w[used] = x * gain
    return w, v


def probability(model: tuple[np.ndarray, np.ndarray], ids: np.ndarray, bounds: np.ndarray, extra: np.ndarray) -> np.ndarray:
    w, v = model
    return sigmoid(total(w, ids, bounds) + v[0] + extra @ v[1:])


def best_threshold(p: np.ndarray, y: np.ndarray) -> float:
    """The cut with the best harmonic mean of precision and recall, midway between its neighbours on a log-odds scale; 0.5 without two classes."""
    if len(set(y.tolist())) < 2:
        return 0.5
    order = np.argsort(-p, kind="stable")
    hit = np.cumsum(y[order])
    score = 2 * hit / (np.arange(1, len(y) + 1) + y.sum())
    score[:-1][p[order][1:] == p[order][:-1]] = 0  # equal probabilities go together
    k = int(score.argmax())
    q = np.clip(p[order], 1e-12, 1 - 1e-12)
    odds = np.log(q / (1 - q))
    return float(sigmoid((odds[k] + odds[min(k + 1, len(y) - 1)]) / 2))


@dataclass(frozen=True)
class Chain:
    """Models in order and, for each category, the threshold that its out-of-fold probabilities name."""

    models: list[tuple[np.ndarray, np.ndarray]]
    thresholds: list[float]


def chained(rows: list[np.ndarray], y: np.ndarray, folds: int = 3) -> Chain:
    fold = np.arange(len(rows)) % folds
    extra, models, thresholds = np.zeros((len(rows), 0)), [], []
    for k in range(y.shape[1]):
        models.append(logistic(rows, extra, y[:, k]))
        out = np.zeros(len(rows))
        for f in range(folds):
            inside, outside = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
            m = logistic([rows[i] for i in inside], extra[inside], y[inside, k])
            out[outside] = probability(m, *flat([rows[i] for i in outside]), extra[outside])
        thresholds.append(best_threshold(out, y[:, k]))
        extra = np.column_stack([extra, out])
    return Chain(models, thresholds)


def fit(docs: DataFrame, labels: DataFrame, targets: list[str], most: int = MOST, folds: int = 3, id_col: str = "doc_id", text_col: str = "text") -> Chain:
    return chained(*sample(docs, labels, targets, most, id_col, text_col), folds)


def scored(docs: DataFrame, chain: Chain, names: list[str], text_col: str = "text") -> DataFrame:
    """``docs`` with one probability per category, under ``names``."""
    shared = docs.sparkSession.sparkContext.broadcast([(np.flatnonzero(w).astype(np.int32), w[w != 0], v) for w, v in chain.models])
    made: list = []

    def run(texts: pa.Array) -> list[pa.Array]:
        if not made:
            for used, values, v in shared.value:
                w = np.zeros(SPACE)
                w[used] = values
                made.append((w, v))
        ids, bounds = indicators(texts)
        extra = np.zeros((len(texts), 0))
        for model in made:
            extra = np.column_stack([extra, probability(model, ids, bounds, extra)])
        return [pa.array(c) for c in extra.T]

    return with_columns(docs, text_col, names, T.DoubleType(), run)


def chain_labels(labels: DataFrame) -> DataFrame:
    """The categories of the given labels: low quality first, toxicity after it."""
    return labels.select("doc_id", (1 - F.col("quality")).alias("low_quality"), "toxic")


def reject(docs: DataFrame, labels: DataFrame, threshold: float | None = None, text_col: str = "text") -> DataFrame:
    """The rows that are not toxic, columns as given; ``threshold`` in place of the one that out-of-fold probabilities name."""
    chain = fit(docs, chain_labels(labels), CHAIN, text_col=text_col)
    names = fresh(docs, *(f"p_{c}" for c in CHAIN))
    limit = chain.thresholds[-1] if threshold is None else threshold
    return scored(docs, chain, names, text_col).where(F.col(names[-1]) < limit).drop(*names)
