"""Low-rank step on matrices in coordinate form. Every key (``step``, and ``param`` where given) is a matrix of its own, so all go in one pass.

Factors are wide rows: ``p`` and ``q`` hold one array of ``rank`` values per row or column index. Each product is one join with
a factor (small: rows or columns times rank, so the optimizer broadcasts it below its own size limit and shuffles it above)
and one partial and final aggregation; nothing of the size of the matrix is shuffled unaggregated.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.draws import normal

KEYS = ("step", "param")
DEPENDENT = 1e-13  # a column with this share of its squared norm left counts as dependent


def keys_of(df: DataFrame) -> list[str]:
    return [c for c in KEYS if c in df.columns]


def each(rank: int, f) -> Column:
    return F.array(*[f(c) for c in range(rank)])


def dot(a: str, b: str, rank: int) -> Column:
    return sum((F.col(a)[c] * F.col(b)[c] for c in range(1, rank)), F.col(a)[0] * F.col(b)[0])


def start_factor(spark: SparkSession, columns: int, rank: int, seed: int = 0, step: str = "0", scale: float = 1.0) -> DataFrame:
    """``j, q``: independent standard normal values."""
    j = F.col("id").cast("int")
    return spark.range(columns).select(j.alias("j"), each(rank, lambda c: normal(F.concat(F.lit(f"{seed}:{step}:"), j.cast("string"), F.lit(f":{c}"))) * scale).alias("q"))


def fresh_factor(steps: DataFrame, columns: int, rank: int, seed: int = 0, label: str = "", scale: float = 1.0) -> DataFrame:
    """``step, j, q``: a new start for each step."""
    j = F.explode(F.sequence(F.lit(0), F.lit(columns - 1)))
    name = F.concat(F.lit(f"{seed}:{label}"), F.col("step").cast("string"), F.lit(":"), F.col("j").cast("string"))
    return steps.select("step", j.alias("j")).withColumn("q", each(rank, lambda c: normal(F.concat(name, F.lit(f":{c}"))) * scale))


def start_factors(specs: DataFrame, rank: int, seed: int = 0) -> DataFrame:
    """``param, j, q`` for each matrix of ``param, m``."""
    j = F.explode(F.sequence(F.lit(0), F.col("m").cast("int") - 1))
    name = F.concat(F.lit(f"{seed}:0:"), F.col("param"), F.lit(":"), F.col("j").cast("string"))
    return specs.select("param", j.alias("j")).withColumn("q", each(rank, lambda c: normal(F.concat(name, F.lit(f":{c}")))))


def right_product(m: DataFrame, q: DataFrame, rank: int, workers: int, per_worker: bool = False) -> DataFrame:
    """Keys, ``i, p``: mean over workers of matrix times factor (or each worker's own)."""
    on = [*keys_of(q), "j"]
    keys = [*keys_of(m), *(["worker"] if per_worker else []), "i"]
    share = 1 if per_worker else workers
    sums = [F.sum(F.col("v") * F.col("q")[c]).alias(f"s{c}") for c in range(rank)]
    return m.join(q, on).groupBy(*keys).agg(*sums).select(*keys, each(rank, lambda c: F.col(f"s{c}") / share).alias("p"))


def orthogonalize(p: DataFrame, rank: int, passes: int = 2) -> DataFrame:
    """Orthonormal columns in the order of Gram-Schmidt; a dependent column becomes zero.

    A pass is one aggregation (inner products of all columns: a triangle per matrix), its triangular factor by arithmetic on that one row, and one
    join back; so the plan has as many scans and exchanges at rank 7 as at rank 1. The second pass removes what rounding leaves in the first.
    """
    for _ in range(passes):
        p = triangular_pass(p, rank)
    return p


def triangular_pass(p: DataFrame, rank: int) -> DataFrame:
    keys = keys_of(p)
    wide = p.select(*keys, "i", *[F.col("p")[c].alias(f"x{c}") for c in range(rank)])
    pairs = [(a, b) for b in range(rank) for a in range(b + 1)]
    t = wide.groupBy(*keys).agg(*[F.sum(F.col(f"x{a}") * F.col(f"x{b}")).alias(f"g{a}_{b}") for a, b in pairs])
    for a, b in pairs:
        rest = F.col(f"g{a}_{b}")
        for k in range(a):
            rest = rest - F.col(f"t{k}_{a}") * F.col(f"t{k}_{b}")
        if a < b:
            t = t.withColumn(f"t{a}_{b}", F.when(F.col(f"t{a}_{a}") > 0, rest / F.col(f"t{a}_{a}")).otherwise(0.0))
        else:
            t = t.withColumn(f"r{b}", rest).withColumn(f"t{b}_{b}", F.when(F.col(f"r{b}") > DEPENDENT * F.col(f"g{b}_{b}"), F.sqrt(f"r{b}")).otherwise(0.0))
    out = wide.join(t.select(*keys, *[f"t{a}_{b}" for a, b in pairs]), keys)
    for c in range(rank):
        rest = F.col(f"x{c}")
        for b in range(c):
            rest = rest - F.col(f"t{b}_{c}") * F.col(f"u{b}")
        out = out.withColumn(f"u{c}", F.when(F.col(f"t{c}_{c}") > 0, rest / F.col(f"t{c}_{c}")).otherwise(0.0))
    return out.select(*keys, "i", each(rank, lambda c: F.col(f"u{c}")).alias("p"))


def orthonormality(p: DataFrame, rank: int) -> DataFrame:
    """Keys, ``a, b, dot``: inner products of the columns of a factor."""
    pairs = [(a, b) for b in range(rank) for a in range(b + 1)]
    sums = p.groupBy(*keys_of(p)).agg(*[F.sum(F.col("p")[a] * F.col("p")[b]).alias(f"d{a}_{b}") for a, b in pairs])
    each_pair = F.explode(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(f"d{a}_{b}").alias("dot")) for a, b in pairs])).alias("d")
    return sums.select(*keys_of(p), each_pair).select(*keys_of(p), "d.a", "d.b", "d.dot")


def left_product(m: DataFrame, p: DataFrame, rank: int, workers: int) -> DataFrame:
    """Keys, ``j, q``: mean over workers of transposed matrix times orthonormal factor."""
    keys = keys_of(p)
    sums = [F.sum(F.col("v") * F.col("p")[c]).alias(f"s{c}") for c in range(rank)]
    return m.join(p, [*keys, "i"]).groupBy(*keys, "j").agg(*sums).select(*keys, "j", each(rank, lambda c: F.col(f"s{c}") / workers).alias("q"))


def reconstruct(p: DataFrame, q: DataFrame, rank: int) -> DataFrame:
    keys = keys_of(p)
    return p.join(q, keys).select(*keys, "i", "j", dot("p", "q", rank).alias("v"))


def compress(m: DataFrame, start: DataFrame, rank: int, workers: int) -> tuple[DataFrame, DataFrame]:
    """One sweep: orthonormal left factor and right factor."""
    p = orthogonalize(right_product(m, start, rank, workers), rank)
    return p, left_product(m, p, rank, workers)


def sweeps(m: DataFrame, start: DataFrame, rank: int, workers: int, count: int, keep=lambda df: df) -> tuple[DataFrame, DataFrame]:
    """Repeated sweeps on the same matrices, each from the right factor of the one before: they approach the best matrices of the rank."""
    q = start
    for _ in range(count):
        p, q = compress(m, q, rank, workers)
        q = keep(q)
    return p, q


def unbiased(m: DataFrame, columns: int, rank: int, workers: int, seed: int = 0) -> DataFrame:
    """Random projection with identity second moment, drawn anew at each step; no feedback needed."""
    u = fresh_factor(m.select("step").distinct(), columns, rank, seed, "u:", rank**-0.5)
    return right_product(m, u, rank, workers).join(u, "step").select("step", "i", "j", dot("p", "q", rank).alias("v"))


def residual(m: DataFrame, q: DataFrame, rank: int, workers: int) -> DataFrame:
    """Relative error of a sweep from norms alone: the left factor is orthonormal, so no reconstruction is needed."""
    keys = keys_of(m)
    whole = mean(m, workers).groupBy(*keys).agg(F.sum(F.col("v") * F.col("v")).alias("total"))
    kept = q.groupBy(*keys).agg(F.sum(dot("q", "q", rank)).alias("kept"))
    return whole.join(kept, keys).select(*keys, F.sqrt(F.greatest(F.lit(0.0), 1 - F.col("kept") / F.col("total"))).alias("residual"))


def mean(m: DataFrame, workers: int) -> DataFrame:
    return m.groupBy(*keys_of(m), "i", "j").agg((F.sum("v") / workers).alias("v"))


def gap(one: DataFrame, other: DataFrame) -> DataFrame:
    """``step, gap``: largest difference of two sets of matrices; an absent cell is zero."""
    keys = [*keys_of(one), "i", "j"]
    both = one.select(*keys, "v").unionByName(other.select(*keys, (-F.col("v")).alias("v"))).groupBy(*keys).agg(F.sum("v").alias("d"))
    return both.groupBy(*keys_of(one)).agg(F.max(F.abs("d")).alias("gap"))
