"""Spectral baselines. One matrix with a bounded smaller side is decomposed in one task; each step or worker is a group of its own."""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .lowrank import mean

SIDE = 4096  # largest smaller side that a task decomposes


def dense(cells: pd.DataFrame, rows: int, columns: int) -> np.ndarray:
    if min(rows, columns) > SIDE:
        raise ValueError(f"the smaller side is above {SIDE}; iterate low-rank sweeps instead")
    out = np.zeros((rows, columns))
    np.add.at(out, (cells.i.to_numpy(), cells.j.to_numpy()), cells.v.to_numpy())
    return out


def cells_of(step: int, matrix: np.ndarray) -> pd.DataFrame:
    i, j = np.indices(matrix.shape)
    return pd.DataFrame({"step": step, "i": i.ravel(), "j": j.ravel(), "v": matrix.ravel()})


def singular_values(m: DataFrame, rows: int, columns: int, workers: int) -> DataFrame:
    """``step, t, sigma`` of the mean matrices, descending."""

    def run(cells: pd.DataFrame) -> pd.DataFrame:
        s = np.linalg.svd(dense(cells, rows, columns), compute_uv=False)
        return pd.DataFrame({"step": cells.step.iloc[0], "t": range(len(s)), "sigma": s})

    return mean(m, workers).groupBy("step").applyInPandas(run, "step int, t int, sigma double")


def best_rank(m: DataFrame, rows: int, columns: int, rank: int, workers: int) -> DataFrame:
    """The closest matrices of a rank: what a low-rank sweep is measured against."""

    def run(cells: pd.DataFrame) -> pd.DataFrame:
        u, s, w = np.linalg.svd(dense(cells, rows, columns), full_matrices=False)
        return cells_of(cells.step.iloc[0], (u[:, :rank] * s[:rank]) @ w[:rank])

    return mean(m, workers).groupBy("step").applyInPandas(run, "step int, i int, j int, v double")


def energy_curve(sigma: DataFrame) -> DataFrame:
    """``step, rank, share``: part of the squared norm that the best matrix of each rank holds."""
    square = F.col("sigma") * F.col("sigma")
    whole = Window.partitionBy("step")
    upto = whole.orderBy("t").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return sigma.select("step", (F.col("t") + 1).alias("rank"), (F.sum(square).over(upto) / F.sum(square).over(whole)).alias("share"))


def keep_probabilities(sigma: np.ndarray, budget: float) -> np.ndarray:
    """In proportion to the singular values, capped at one, with ``budget`` as their sum where enough values are positive."""
    p, fixed = np.zeros(len(sigma)), np.zeros(len(sigma), bool)
    while (left := budget - fixed.sum()) > 0 and sigma[~fixed].sum() > 0:
        p[~fixed] = left * sigma[~fixed] / sigma[~fixed].sum()
        over = ~fixed & (p > 1)
        if not over.any():
            break
        fixed |= over
        p[fixed] = 1
    return np.minimum(p, 1)


def spectral_sampling(m: DataFrame, rows: int, columns: int, budget: float, workers: int, seed: int = 0) -> DataFrame:
    """Mean over workers of randomly kept singular triplets, scaled to stay unbiased; draws are each worker's own."""

    def run(cells: pd.DataFrame) -> pd.DataFrame:
        step, worker = int(cells.step.iloc[0]), int(cells.worker.iloc[0])
        u, s, w = np.linalg.svd(dense(cells, rows, columns), full_matrices=False)
        p = keep_probabilities(s, budget)
        draw = np.array([int(hashlib.md5(f"{seed}:{step}:{worker}:{t}".encode()).hexdigest()[:8], 16) / 2**32 for t in range(len(s))])
        kept = draw < p
        return cells_of(step, (u[:, kept] * (s[kept] / p[kept])) @ w[kept])

    return mean(m.groupBy("step", "worker").applyInPandas(run, "step int, i int, j int, v double"), workers)
