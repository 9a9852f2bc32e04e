"""Training runs on sufficient statistics: Spark reduces any number of texts to count matrices bounded by the model; runs are tasks of their own.

The gradient of a softmax model on counts depends on the data through ``worker, i, j, n`` only. That table is aggregated once over the whole input,
written, and shared by all runs; each run (a compressor, a rank, a seed) is one group of ``applyInPandas`` and iterates on dense blocks
``(workers, n, m)``. So the grid of an experiment is spread over the cluster, and no run waits for another.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VALUE = 4  # bytes of a value that travels


@dataclass(frozen=True)
class Run:
    """One cell of an experiment's grid; ``lr`` and ``momentum`` stay those of plain descent unless a method needs its own."""

    method: str
    rank: int = 0
    seed: int = 0
    lr: float = 2.0
    momentum: float = 0.9
    steps: int = 60
    feedback: bool = True

    @property
    def name(self) -> str:
        return f"{self.method}:{self.rank}:{self.seed}:{self.lr:g}"


def orthonormal(p: np.ndarray) -> np.ndarray:
    """Gram-Schmidt, twice; dependent columns become zero."""
    p = p.copy()
    for c in range(p.shape[1]):
        before = np.linalg.norm(p[:, c])
        for _ in range(2):
            p[:, c] -= p[:, :c] @ (p[:, :c].T @ p[:, c])
        size = np.linalg.norm(p[:, c])
        p[:, c] = p[:, c] / size if size > 3e-7 * before and size > 0 else 0.0
    return p


def draws(run: Run, step: int, label: str) -> np.random.Generator:
    return np.random.default_rng(int(hashlib.md5(f"{run.seed}:{step}:{label}".encode()).hexdigest()[:15], 16))


Sent = tuple[np.ndarray, np.ndarray, int]  # update, each worker's own part, bytes that a worker sends


def low_rank(run: Run, delta: np.ndarray, state: dict, step: int, warm: bool) -> Sent:
    whole = delta.mean(0)
    n, m = whole.shape
    q = state.get("q") if warm else None
    q = draws(run, 0 if warm else step, "start").normal(size=(m, run.rank)) if q is None else q
    p = orthonormal(whole @ q)
    state["q"] = q = whole.T @ p
    update = p @ q.T
    return update, np.broadcast_to(update, delta.shape), VALUE * run.rank * (n + m)


def best_rank(run: Run, delta: np.ndarray) -> Sent:
    whole = delta.mean(0)
    u, s, w = np.linalg.svd(whole, full_matrices=False)
    update = (u[:, : run.rank] * s[: run.rank]) @ w[: run.rank]
    return update, np.broadcast_to(update, delta.shape), VALUE * run.rank * sum(whole.shape)


def unbiased(run: Run, delta: np.ndarray, step: int) -> Sent:
    n, m = delta.shape[1:]
    u = draws(run, step, "projection").normal(size=(m, run.rank)) / np.sqrt(run.rank)
    update = delta.mean(0) @ u @ u.T
    return update, np.broadcast_to(update, delta.shape), VALUE * run.rank * n


def masked(delta: np.ndarray, mask: np.ndarray, size: int) -> Sent:
    own = delta * mask
    return own.mean(0), own, size


def sparse(run: Run, delta: np.ndarray, step: int) -> Sent:
    w, n, m = delta.shape
    k = min(n * m, run.rank * (n + m))
    if run.method == "top_k":
        flat = np.abs(delta.reshape(w, -1))
        mask = np.zeros_like(flat, bool)
        np.put_along_axis(mask, np.argsort(-flat, axis=1, kind="stable")[:, :k], True, axis=1)
        return masked(delta, mask.reshape(delta.shape), 2 * VALUE * k)
    mask = np.zeros(n * m, bool)
    g = draws(run, step, run.method)
    mask[(g.integers(n * m) + np.arange(k)) % (n * m) if run.method == "random_block" else g.choice(n * m, k, replace=False)] = True
    return masked(delta, mask.reshape(n, m), VALUE * k)


def spectral(run: Run, delta: np.ndarray, step: int) -> Sent:
    """Each worker keeps singular triplets at random, scaled to stay unbiased."""
    from ..operators.spectral import keep_probabilities

    own, sent = np.zeros_like(delta), 0
    for k, d in enumerate(delta):
        u, s, w = np.linalg.svd(d, full_matrices=False)
        p = keep_probabilities(s, run.rank)
        kept = draws(run, step, f"spectral:{k}").random(len(s)) < p
        own[k] = (u[:, kept] * (s[kept] / p[kept])) @ w[kept]
        sent = max(sent, int(kept.sum()))
    return own.mean(0), own, VALUE * sent * (sum(delta.shape[1:]) + 1)


def exchanged(run: Run, delta: np.ndarray, state: dict, step: int) -> Sent:
    n, m = delta.shape[1:]
    if run.method in ("lowrank", "lowrank_cold"):
        return low_rank(run, delta, state, step, run.method == "lowrank")
    if run.method == "best_rank":
        return best_rank(run, delta)
    if run.method == "unbiased_lowrank":
        return unbiased(run, delta, step)
    if run.method in ("random_block", "random_k", "top_k"):
        return sparse(run, delta, step)
    if run.method == "spectral_sampling":
        return spectral(run, delta, step)
    if run.method == "sign_norm":
        own = np.sign(delta) * np.abs(delta).mean((1, 2), keepdims=True)
        return own.mean(0), own, -(-n * m // 8) + VALUE
    if run.method == "sign_vote":
        state["m"] = run.momentum * state.get("m", 0.0) + (1 - run.momentum) * delta
        return np.sign(np.sign(state["m"]).sum(0)), delta, -(-n * m // 8)
    if run.method == "identity":
        return delta.mean(0), delta, VALUE * n * m
    if run.method == "no_update":
        return np.zeros((n, m)), delta, 0
    raise ValueError(run.method)


NO_FEEDBACK = ("unbiased_lowrank", "spectral_sampling", "sign_vote", "identity", "no_update")


def trained(run: Run, gradient: Callable[[np.ndarray], np.ndarray], shape: tuple[int, int], measure: Callable[[np.ndarray], dict]) -> pd.DataFrame:
    """``run, step, metric, value`` of one run; ``gradient`` gives ``(workers, n, m)``."""
    x, momentum, memory, state, rows = np.zeros(shape), np.zeros(shape), 0.0, {}, []
    sent_before = 0
    for step in range(run.steps + 1):
        values = measure(x) | {"bytes": float(sent_before), "memory_norm": float(np.sqrt(np.square(memory).sum()))}
        rows += [(run.name, run.method, run.rank, run.seed, step, k, v) for k, v in values.items()]
        if step == run.steps:
            break
        with np.errstate(all="ignore"):
            feedback = run.feedback and run.method not in NO_FEEDBACK
            delta = gradient(x) + (memory if feedback else 0.0)
            if not np.isfinite(delta).all():
                x = np.full(shape, np.nan)  # diverged: stays so, and its measures say so
                continue
            update, own, sent = exchanged(run, delta, state, step)
            if feedback:
                memory = delta - own
            sent_before += sent
            if run.method == "sign_vote":
                x = x - run.lr * update
            else:
                momentum = run.momentum * momentum + update
                x = x - run.lr * (update + momentum)
    return pd.DataFrame(rows, columns=["run", "method", "rank", "seed", "step", "metric", "value"])


def log_probabilities(x: np.ndarray) -> np.ndarray:
    z = x - x.max(1, keepdims=True)
    return z - np.log(np.exp(z).sum(1, keepdims=True))


def count_model(counts: pd.DataFrame, shape: tuple[int, int], workers: int, scale: float) -> tuple[Callable, Callable]:
    """Gradient and measures of the softmax model on ``part, worker, i, j, n`` (part: train or test)."""
    n = np.zeros((2, workers, *shape))
    test = (counts["part"] == "test").to_numpy().astype(int)
    np.add.at(n, (test, counts["worker"].to_numpy(), counts["i"].to_numpy(), counts["j"].to_numpy()), counts["n"].to_numpy())
    train, held = n[0], n[1].sum(0)
    totals = np.maximum(train.sum((1, 2), keepdims=True), 1)
    rows = train.sum(2, keepdims=True)

    def gradient(x: np.ndarray) -> np.ndarray:
        return (np.exp(log_probabilities(x))[None] * rows - train) * scale / totals

    def measure(x: np.ndarray) -> dict:
        with np.errstate(all="ignore"):
            lp = log_probabilities(x)
            loss = -(held * lp).sum() / max(held.sum(), 1)
            return {"perplexity": float(np.exp(min(loss, 700.0))) if np.isfinite(loss) else float("inf"), "accuracy": float(held[np.arange(len(lp)), lp.argmax(1)].sum() / max(held.sum(), 1))}

    return gradient, measure


def grid(counts: DataFrame, runs: list[Run], shape: tuple[int, int], workers: int, scale: float) -> DataFrame:
    """All ``runs`` on ``part, worker, i, j, n``: ``run, method, rank, seed, step, metric, value``, a task for each run.

    The counts travel once per run; they are bounded by ``2 * workers * n * m`` rows, whatever the corpus was.
    """
    spark = counts.sparkSession
    by_name = {r.name: r for r in runs}
    names = spark.createDataFrame([(n,) for n in by_name], "run string")

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        return trained(by_name[key[0]], *(lambda g, m: (g, shape, m))(*count_model(rows, shape, workers, scale)))

    dealt = counts.withColumn("run", F.explode(F.array(*[F.lit(n) for n in by_name]))) if by_name else counts.crossJoin(names)
    return dealt.groupBy("run").applyInPandas(one, "run string, method string, rank int, seed int, step int, metric string, value double")


def error_bars(metrics: DataFrame, metric: str) -> DataFrame:
    """``method, rank, least, mean, most`` over seeds, of the last step of each run."""
    last = metrics.where(F.col("metric") == metric).groupBy("method", "rank", "seed").agg(F.max_by("value", "step").alias("value"))
    return last.groupBy("method", "rank").agg(F.min("value").alias("least"), F.avg("value").alias("mean"), F.max("value").alias("most"), F.count(F.lit(1)).alias("seeds"))


def time_to_target(metrics: DataFrame, metric: str, target: float, below: bool = True) -> DataFrame:
    """``run, step``: first step that reaches the target; null where none does."""
    reached = F.col("value") <= target if below else F.col("value") >= target
    of_metric = metrics.where(F.col("metric") == metric)
    return of_metric.groupBy("run", "method", "rank", "seed").agg(F.min(F.when(reached, F.col("step"))).alias("step"))


def choose_rank(metrics: DataFrame, metric: str, tolerance: float = 0.02) -> DataFrame:
    """Smallest rank of each method whose last measure is within ``tolerance`` of that of plain descent."""
    last = error_bars(metrics, metric)
    plain = last.where("method = 'identity'").select(F.col("mean").alias("goal"))
    good = last.where("rank > 0").join(F.broadcast(plain)).where(F.col("mean") <= F.col("goal") * (1 + tolerance))
    return good.groupBy("method").agg(F.min("rank").alias("rank"))


def mean_metrics(metrics: DataFrame) -> DataFrame:
    """``method, rank, step, metric, value``: mean over seeds."""
    return metrics.groupBy("method", "rank", "step", "metric").agg(F.avg("value").alias("value"))
