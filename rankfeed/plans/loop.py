"""Optimizer loop over steps: error memory, any compressor, momentum behind the compressor.

State is three coordinate tables (memory by worker, momentum, parameters) and what a compressor carries on. The driver only composes plans and
names the steps; no cell comes to it. Gradients are written once, in a folder per step, so a step reads its own alone.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import lowrank as L
from ..operators import sparse as S
from ..operators import spectral as X
from .state import discard, kept

CELLS = "worker int, i int, j int, v double"


@dataclass(frozen=True)
class Step:
    """What a compressor returns: the update all receive, each worker's own decoded part if that differs, and its state."""

    update: DataFrame
    own: DataFrame | None = None
    carried: DataFrame | None = None


Compressor = Callable[[DataFrame, DataFrame | None, int], Step]


def low_rank(columns: int, rank: int, warm: bool = True, seed: int = 0, error_target: str = "shared") -> Compressor:
    """One sweep; a warm one starts from the right factor of the step before.

    ``error_target``: a worker's memory is taken against the update that all share, or (``local``) against its own projection on the shared left factor.
    Both have the same mean over the workers, and the sweep reads workers through their mean only, so the parameters are the same.
    """

    def run(delta: DataFrame, carried: DataFrame | None, workers: int) -> Step:
        if not warm:
            start = L.fresh_factor(delta.select("step").distinct(), columns, rank, seed)
        else:
            start = carried if carried is not None else L.start_factor(delta.sparkSession, columns, rank, seed)
        p, q = L.compress(delta, start, rank, workers)
        p, q = kept(p, "left"), kept(q, "right")
        own = None
        if error_target == "local":
            sums = [F.sum(F.col("v") * F.col("p")[c]).alias(f"s{c}") for c in range(rank)]
            mine = delta.join(p, ["step", "i"]).groupBy("step", "worker", "j").agg(*sums).select("step", "worker", "j", L.each(rank, lambda c: F.col(f"s{c}")).alias("q"))
            own = p.join(mine, "step").select("worker", "i", "j", L.dot("p", "q", rank).alias("v"))
        return Step(L.reconstruct(p, q, rank).select("i", "j", "v"), own, q.select("j", "q"))

    return run


def identity(delta: DataFrame, carried: DataFrame | None, workers: int) -> Step:
    return Step(L.mean(delta, workers).select("i", "j", "v"), delta.select("worker", "i", "j", "v"))


def gathered(select: Callable[[DataFrame], DataFrame]) -> Compressor:
    """Each worker sends what ``select`` leaves of its matrix; all take the mean of what was sent, and a worker decodes its own part."""

    def run(delta: DataFrame, carried: DataFrame | None, workers: int) -> Step:
        sent = kept(select(delta), "sent")
        return Step(L.mean(sent, workers).select("i", "j", "v"), sent.select("worker", "i", "j", "v"))

    return run


def top_k(k: int, columns: int) -> Compressor:
    return gathered(lambda d: S.largest(d, k, columns))


def random_k(k: int, rows: int, columns: int, seed: int = 0) -> Compressor:
    return gathered(lambda d: S.drawn(d, k, rows, columns, seed))


def random_block(k: int, rows: int, columns: int, seed: int = 0) -> Compressor:
    return gathered(lambda d: S.block(d, k, rows, columns, seed))


def sign_norm(rows: int, columns: int) -> Compressor:
    return gathered(lambda d: S.scaled_signs(d, rows, columns))


def best_rank(rows: int, columns: int, rank: int) -> Compressor:
    """The closest matrix of a rank to the mean: the optimum that sweeps are measured against."""

    def run(delta: DataFrame, carried: DataFrame | None, workers: int) -> Step:
        return Step(X.best_rank(delta, rows, columns, rank, workers).select("i", "j", "v"))

    return run


def recompressed(worker_side: Callable[[DataFrame], DataFrame], server_side: Callable[[DataFrame], DataFrame]) -> Compressor:
    """By way of a server that compresses the aggregate once more before sending it on; both take and give cells with a ``worker``."""

    def run(delta: DataFrame, carried: DataFrame | None, workers: int) -> Step:
        sent = kept(worker_side(delta), "sent")
        whole = L.mean(sent, workers).withColumn("worker", F.lit(0))
        return Step(server_side(whole).select("i", "j", "v"), sent.select("worker", "i", "j", "v"))

    return run


@dataclass(frozen=True)
class State:
    memory: DataFrame
    momentum: DataFrame
    parameters: DataFrame
    carried: DataFrame | None = None


def added(*parts: DataFrame, keys: tuple[str, ...] = ("i", "j")) -> DataFrame:
    """Sum of coordinate tables; an absent cell is zero."""
    out = parts[0].select(*keys, "v")
    for p in parts[1:]:
        out = out.unionByName(p.select(*keys, "v"))
    return out.groupBy(*keys).agg(F.sum("v").alias("v"))


def times(df: DataFrame, factor: float) -> DataFrame:
    return df.withColumn("v", F.col("v") * factor)


def begin(gradients: DataFrame) -> State:
    none = gradients.sparkSession.createDataFrame([], CELLS)
    return State(none, none.drop("worker"), none.drop("worker"))


RULES = ("update_plus_momentum", "heavy_ball", "nesterov")


def step(
    gradient: DataFrame,
    state: State,
    t: int,
    compressor: Compressor,
    workers: int,
    lr: float,
    momentum: float = 0.9,
    feedback: bool = True,
    rule: str = "update_plus_momentum",
    momentum_site: str = "post",
    decay: float = 0.0,
) -> State:
    """One iteration on ``worker, i, j, v``: decay, memory in, exchange, error out, momentum, parameters.

    ``rule``: parameters move by update and momentum, by momentum alone, or by update plus the decayed momentum. ``momentum_site``: momentum of what
    was received (``post``), or each worker's own momentum of its gradients before compression (``pre``; then the update alone moves the parameters).
    What to send and what was received are used several times each, so both are written once; every plan is as short as at the first step.
    """
    if rule not in RULES or momentum_site not in ("post", "pre"):
        raise ValueError(f"unknown rule {rule} or momentum site {momentum_site}")
    keys = ("worker", "i", "j")
    if decay:
        every = F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker")
        gradient = added(gradient, times(state.parameters.select(every, "i", "j", "v"), decay), keys=keys)
    moved = state.momentum
    if momentum_site == "pre":
        before = moved if "worker" in moved.columns else state.memory.limit(0)
        moved = kept(added(times(before, momentum), gradient, keys=keys))
        gradient = moved
    delta = kept(added(gradient, state.memory, keys=keys) if feedback else added(gradient, keys=keys), "delta")
    got = compressor(delta.withColumn("step", F.lit(t)), state.carried, workers)
    update = kept(got.update, "update")
    memory = state.memory
    if feedback:
        every = F.explode(F.sequence(F.lit(0), F.lit(workers - 1))).alias("worker")
        own = got.own if got.own is not None else update.select(every, "i", "j", "v")
        memory = kept(added(delta, times(own, -1.0), keys=keys), "memory")
    if momentum_site == "pre":
        change = [times(update, -lr)]
    else:
        moved = kept(added(times(moved, momentum), update), "momentum")
        change = {"update_plus_momentum": [times(update, -lr), times(moved, -lr)], "heavy_ball": [times(moved, -lr)], "nesterov": [times(update, -lr), times(moved, -lr * momentum)]}[rule]
    parameters = kept(added(state.parameters, *change), "parameters")
    for old in (delta, state.parameters, *([state.memory] if feedback else []), state.momentum):
        discard(old)
    return State(memory, moved, parameters, got.carried)


def run(gradients: DataFrame, steps: list[int], compressor: Compressor, workers: int, lr: float, state: State | None = None, **how) -> State:
    """State after ``steps`` of ``step, worker, i, j, v``, from the beginning or from a state."""
    gradients = kept(gradients, "gradients", by="step")
    state = state or begin(gradients)
    for t in steps:
        state = step(gradients.where(F.col("step") == t).drop("step"), state, t, compressor, workers, lr, **how)
    return state


def sign_descent(gradients: DataFrame, steps: list[int], workers: int, lr: float, beta: float = 0.9) -> State:
    """Signs of each worker's momentum, their majority, a fixed step; no error memory. An even split moves nothing."""
    gradients = kept(gradients, "gradients", by="step")
    keys, state = ("worker", "i", "j"), begin(gradients)
    momentum, parameters = state.memory, state.parameters
    for t in steps:
        own = gradients.where(F.col("step") == t).drop("step")
        momentum = kept(added(times(momentum, beta), times(own, 1 - beta), keys=keys), "momentum")
        vote = momentum.groupBy("i", "j").agg(F.signum(F.sum(F.signum(F.round("v", 9)))).alias("v"))
        parameters = kept(added(parameters, times(vote, -lr)), "parameters")
    return State(state.memory, momentum, parameters)


def tracked(gradients: DataFrame, columns: int, ranks: list[int], workers: int, steps: list[int], warm: bool = True, seed: int = 0) -> DataFrame:
    """``step, rank, residual`` of sweeps over a sequence of matrices, each from the right factor of the step before, or each from a fresh start.

    Columns are orthogonalised in their order, so the first columns of a chain are the chain of that smaller rank: one chain of the largest rank gives
    the residuals of all. A sweep reads workers through their mean only, which is taken once.
    """
    rank = max(ranks)
    whole = kept(L.mean(gradients.where(F.col("step").isin(steps)), workers), "means", by="step")
    if warm:
        q, parts = L.start_factor(gradients.sparkSession, columns, rank, seed), []
        for t in steps:
            right = kept(L.compress(whole.where(F.col("step") == t), q, rank, 1)[1], "right")
            parts.append(right)
            q = right.select("j", "q")
        factors = parts[0]
        for p in parts[1:]:
            factors = factors.unionByName(p)
    else:
        factors = L.compress(whole, L.fresh_factor(whole.select("step").distinct(), columns, rank, seed), rank, 1)[1]
    factors = kept(factors, "factors")
    out = None
    for r in ranks:
        one = L.residual(whole, factors, r, 1).select("step", F.lit(r).alias("rank"), "residual")
        out = one if out is None else out.unionByName(one)
    return out


def memory_norm(memory: DataFrame) -> DataFrame:
    """``worker, norm`` of the error memories."""
    return memory.groupBy("worker").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("norm"))


def drift(m: DataFrame, workers: int) -> DataFrame:
    """``step, i, j, v``: change of the mean matrices from one step to the next (of cells that both have)."""
    before = Window.partitionBy("i", "j").orderBy("step")
    return L.mean(m, workers).withColumn("d", F.col("v") - F.lag("v").over(before)).where("d is not null").select("step", "i", "j", F.col("d").alias("v"))
