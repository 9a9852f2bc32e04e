"""Compressors that keep cells or signs, and the ways to aggregate what workers send."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.draws import hex32, uniform
from .lowrank import keys_of, mean


def flat(columns: int):
    return F.col("i") * columns + F.col("j")


def largest(m: DataFrame, k: int, columns: int) -> DataFrame:
    """Each worker's ``k`` largest cells, ties by position."""
    order = Window.partitionBy(*keys_of(m), "worker").orderBy(F.abs("v").desc(), flat(columns))
    return m.withColumn("r", F.row_number().over(order)).where(F.col("r") <= k).drop("r")


def top_k(m: DataFrame, k: int, columns: int, workers: int) -> DataFrame:
    """Each worker's largest cells, gathered and averaged."""
    return mean(largest(m, k, columns), workers)


def drawn(m: DataFrame, k: int, rows: int, columns: int, seed: int = 0) -> DataFrame:
    """Cells drawn without replacement from a shared seed: those with the ``k`` smallest hashes.

    Only positions whose hash is below a bound that about ``k`` of them pass (twelve standard errors above) are ranked, so no task sorts a whole matrix.
    """
    cells = rows * columns
    bound = min(1.0, (k + 12 * math.sqrt(k) + 64) / cells)
    f = F.explode(F.sequence(F.lit(0), F.lit(cells - 1)))
    every = m.select("step").distinct().select("step", f.alias("f"))
    hashed = every.withColumn("h", hex32(F.concat(F.lit(f"{seed}:"), F.col("step").cast("string"), F.lit(":"), F.col("f").cast("string"))))
    low = hashed.where(F.col("h") <= F.lit(int(bound * 2**32)))
    chosen = low.withColumn("r", F.row_number().over(Window.partitionBy("step").orderBy("h", "f"))).where(F.col("r") <= k).select("step", "f")
    return m.withColumn("f", flat(columns)).join(chosen, ["step", "f"], "left_semi").drop("f")


def random_k(m: DataFrame, k: int, rows: int, columns: int, workers: int, seed: int = 0) -> DataFrame:
    """Shared random cells; workers send values only."""
    return mean(drawn(m, k, rows, columns, seed), workers)


def block(m: DataFrame, k: int, rows: int, columns: int, seed: int = 0) -> DataFrame:
    """A contiguous run of cells (wrapping) from a shared seed: a plain filter."""
    start = F.floor(uniform(F.concat(F.lit(f"{seed}:block:"), F.col("step").cast("string"))) * (rows * columns))
    return m.where(F.pmod(flat(columns) - start, F.lit(rows * columns)) < k)


def random_block(m: DataFrame, k: int, rows: int, columns: int, workers: int, seed: int = 0) -> DataFrame:
    return mean(block(m, k, rows, columns, seed), workers)


def scaled_signs(m: DataFrame, rows: int, columns: int) -> DataFrame:
    """Signs times the mean absolute value of each worker's matrix; absent cells are zeros and count."""
    keys = [*keys_of(m), "worker"]
    scale = m.groupBy(*keys).agg((F.sum(F.abs("v")) / (rows * columns)).alias("scale"))
    return m.join(scale, keys).withColumn("v", F.signum("v") * F.col("scale")).drop("scale")


def sign_norm(m: DataFrame, rows: int, columns: int, workers: int) -> DataFrame:
    return mean(scaled_signs(m, rows, columns), workers)


def majority(m: DataFrame) -> DataFrame:
    """Sign of the sum of the workers' signs; an even split gives zero."""
    return m.groupBy(*keys_of(m), "i", "j").agg(F.signum(F.sum(F.signum("v"))).alias("v"))


sign_vote = majority  # of gradients, which at a first step have the signs of the momenta; see plans.loop.sign_descent for later steps


def tree_reduce(m: DataFrame, workers: int, fanout: int = 2) -> DataFrame:
    """Sum over workers in logarithmically many rounds; equal to the flat sum by associativity."""
    while workers > 1:
        m = m.groupBy("step", F.floor(F.col("worker") / fanout).cast("int").alias("worker"), "i", "j").agg(F.sum("v").alias("v"))
        workers = -(-workers // fanout)
    return m.select("step", "i", "j", "v")


def all_gather(messages: DataFrame, workers: int) -> DataFrame:
    """Every message at every receiver: ``receiver`` is added, rows are repeated ``workers`` times."""
    return messages.withColumn("receiver", F.explode(F.sequence(F.lit(0), F.lit(workers - 1))))


def decoded_at_receivers(messages: DataFrame, workers: int) -> DataFrame:
    """The gather way to a mean: each receiver adds up all messages for itself, work that grows with the number of workers."""
    return all_gather(messages, workers).groupBy("step", "receiver", "i", "j").agg((F.sum("v") / workers).alias("v"))


def remember(m: DataFrame, decoded: DataFrame, workers: int) -> DataFrame:
    """Error memory of a step in mean form: what was to be sent minus what was received."""
    sent = mean(m, workers).unionByName(decoded.withColumn("v", -F.col("v")))
    return sent.groupBy(*keys_of(m), "i", "j").agg(F.sum("v").alias("v"))


def double_compression(m: DataFrame, send: Callable[[DataFrame], DataFrame], workers: int) -> DataFrame:
    """``step, once, twice``: relative error of the mean after the workers' compression, and after that of the server on top of it."""
    whole = mean(m, workers)
    once = mean(send(m), workers)
    twice = send(once.withColumn("worker", F.lit(0))).select("step", "i", "j", "v")

    def error(got: DataFrame, name: str) -> DataFrame:
        both = whole.unionByName(got.withColumn("v", -F.col("v"))).groupBy("step", "i", "j").agg(F.sum("v").alias("d"))
        return both.groupBy("step").agg(F.sqrt(F.sum(F.col("d") * F.col("d"))).alias(name))

    size = whole.groupBy("step").agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("size"))
    joined = size.join(error(once, "once"), "step").join(error(twice, "twice"), "step")
    return joined.select("step", (F.col("once") / F.col("size")).alias("once"), (F.col("twice") / F.col("size")).alias("twice"))


def sign_agreement(m: DataFrame) -> DataFrame:
    """``step, cells, agree``: cells that several workers have, and those on which all of these agree in sign."""
    signs = m.groupBy("step", "i", "j").agg(F.abs(F.sum(F.signum("v"))).alias("s"), F.count(F.lit(1)).alias("n")).where("n > 1")
    return signs.groupBy("step").agg(F.count(F.lit(1)).alias("cells"), F.count_if(F.col("s") == F.col("n")).alias("agree"))
