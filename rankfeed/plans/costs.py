"""Bytes, rounds and times by formula. Profiles and sizes are settings of a model, no measurements."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

VALUE = 4
FAST, SLOW = (0.05, 1e-7), (0.5, 1e-6)  # milliseconds a message, milliseconds a byte
REDUCED = ("identity", "lowrank", "unbiased_lowrank", "random_block", "random_k")  # messages that can be added on the way


def steps_per_epoch(samples: Column, workers: int, per_worker: int = 128) -> Column:
    return F.ceil(samples.cast("double") / (per_worker * workers))


def message_bytes(rows: int, columns: int, rank: Column) -> dict[str, Column]:
    cells = rows * columns
    return {
        "identity": F.lit(VALUE * cells),
        "lowrank": rank * VALUE * (rows + columns),
        "unbiased_lowrank": rank * VALUE * rows,
        "random_block": rank * VALUE * (rows + columns),
        "random_k": rank * VALUE * (rows + columns),
        "top_k": rank * 2 * VALUE * (rows + columns),
        "sign_norm": F.lit(-(-cells // 8) + VALUE),
        "sign_vote": F.lit(-(-cells // 8)),
        "spectral_sampling": rank * VALUE * (rows + columns + 1),
    }


def bytes_sent(epochs: DataFrame, rows: int, columns: int, workers: int, vectors: int = 0, ranks: tuple[int, ...] = (1, 2, 4, 7)) -> DataFrame:
    """Bytes of a worker per epoch over the samples of each row of ``step, samples``, by method and rank budget, and the ratio to sending everything; ``vectors`` values go uncompressed."""
    size = message_bytes(rows, columns, F.col("rank"))
    steps = steps_per_epoch(F.col("samples"), workers)
    pairs = [y for k, v in size.items() for y in (F.lit(k), ((v + VALUE * vectors) * steps).cast("bigint"))]
    grid = epochs.select("step", "samples", F.explode(F.array(*map(F.lit, ranks))).alias("rank"))
    sent = grid.select("step", "rank", (F.lit(VALUE * (rows * columns + vectors)) * steps).cast("double").alias("plain"), F.explode(F.create_map(*pairs)).alias("method", "bytes"))
    return sent.select("step", "rank", "method", "bytes", F.round(F.col("plain") / F.col("bytes"), 6).alias("ratio"))


def exchange(messages: DataFrame, latency: float, per_byte: float, workers: tuple[int, ...] = (1, 2, 4, 8, 16, 32)) -> DataFrame:
    """Milliseconds of a reduce (logarithmic rounds) and of a gather (linear) of each message of ``step, bytes``."""
    w, size = F.col("workers"), F.col("bytes").cast("double")
    rounds = F.ceil(F.log2(w.cast("double")))
    grid = messages.select("step", "bytes", F.explode(F.array(*map(F.lit, workers))).alias("workers"))
    return grid.select(
        "step", "workers", F.round(rounds * latency + 2 * size * per_byte * (w - 1) / w, 7).alias("reduce_ms"), F.round((w - 1) * (latency + size * per_byte), 7).alias("gather_ms")
    )


def phases(steps: DataFrame, rows: int, columns: int, rank: int = 2, per_flop: float = 1e-8, profile: tuple[float, float] = FAST, workers: tuple[int, ...] = (2, 4, 8, 16)) -> DataFrame:
    """``step, workers, method, phase, ms``: each step of ``step, compute_ms`` in forward, backward, coding and exchange.

    Reduced messages are decoded once; gathered ones once for each worker, so their coding grows with the number of workers.
    """
    cells, r = rows * columns, rank
    latency, per_byte = profile
    w, compute_ms = F.col("workers").cast("double"), F.col("compute_ms")
    flops = {"identity": F.lit(0.0), "lowrank": F.lit(float(6 * cells * r + 2 * rows * r * r)), "sign_vote": cells * (1.0 + w), "top_k": cells * 1.0 + r * (rows + columns) * w}
    size = {k: v for k, v in message_bytes(rows, columns, F.lit(rank)).items() if k in flops}
    grid = steps.select("step", "compute_ms", F.explode(F.array(*map(F.lit, workers))).alias("workers"))
    parts = []
    for method, work in flops.items():
        bytes_ = size[method].cast("double")
        reduced = F.ceil(F.log2(w)) * latency + 2 * bytes_ * per_byte * (w - 1) / w
        gathered = (w - 1) * (latency + bytes_ * per_byte)
        times = {"forward": compute_ms / 3, "backward": compute_ms * 2 / 3, "coding": work * per_flop * 1e3, "exchange": reduced if method in REDUCED else gathered}
        parts += [F.struct(F.lit(method).alias("method"), F.lit(phase).alias("phase"), F.round(ms.cast("double"), 6).alias("ms")) for phase, ms in times.items()]
    return grid.select("step", "workers", F.explode(F.array(*parts)).alias("x")).select("step", "workers", "x.method", "x.phase", "x.ms")


def step_times(breakdown: DataFrame) -> DataFrame:
    """``step, workers, method, total_ms, relative, exchange_cut``: time of a step, against plain exchange of everything, and the share of exchange that is saved."""
    wide = breakdown.groupBy("step", "workers", "method").pivot("phase", ["forward", "backward", "coding", "exchange"]).agg(F.first("ms"))
    wide = wide.withColumn("total_ms", F.col("forward") + F.col("backward") + F.col("coding") + F.col("exchange"))
    plain = wide.where("method = 'identity'").select("step", "workers", F.col("total_ms").alias("plain_ms"), F.col("exchange").alias("plain_exchange"))
    return wide.join(plain, ["step", "workers"]).select("step", "workers", "method", F.round("total_ms", 6).alias("total_ms"), F.round(F.col("total_ms") / F.col("plain_ms") - 1, 6).alias("relative"), F.round(1 - F.col("exchange") / F.col("plain_exchange"), 6).alias("exchange_cut"))


def scaling(epochs: DataFrame, rows: int, columns: int, compute_ms: float = 100.0, rank: int = 2, workers: tuple[int, ...] = (1, 2, 4, 8, 16)) -> DataFrame:
    """``step, profile, method, workers, epoch_ms, speedup``: an epoch over the samples of each row of ``step, samples`` against one worker that exchanges nothing; the batch grows with the workers."""
    out = None
    for name, profile in (("fast", FAST), ("slow", SLOW)):
        each = phases(epochs.withColumn("compute_ms", F.lit(compute_ms)), rows, columns, rank, profile=profile, workers=workers)
        coded = F.when((F.col("workers") == 1) & F.col("phase").isin("coding", "exchange"), 0.0).otherwise(F.col("ms"))
        batch = each.groupBy("step", "workers", "method").agg(F.sum(coded).alias("ms")).join(epochs, "step")
        epoch = batch.withColumn("epoch_ms", F.col("ms") * F.ceil(F.col("samples").cast("double") / (128 * F.col("workers"))))
        one = epoch.where("workers = 1").select("step", "method", F.col("epoch_ms").alias("one_ms"))
        part = epoch.join(one, ["step", "method"]).select("step", F.lit(name).alias("profile"), "method", "workers", F.round("epoch_ms", 6).alias("epoch_ms"), F.round(F.col("one_ms") / F.col("epoch_ms"), 6).alias("speedup"))
        out = part if out is None else out.unionByName(part)
    return out


def rates(epochs: DataFrame, workers: int = 16, base: float = 0.1, warmup: int = 5, milestones: tuple[int, ...] = (150, 250)) -> DataFrame:
    """Learning rate of each ``epoch``: linear warm-up to the scaled rate, a tenth after each milestone."""
    e = F.col("epoch")
    warm = base + (base * workers - base) * e / warmup
    passed = sum((F.when(e >= m, 1).otherwise(0) for m in milestones), F.lit(0))
    return epochs.select("epoch", F.round(F.when(e < warmup, warm).otherwise(base * workers) * F.pow(F.lit(0.1), passed), 9).alias("lr"))


def matrix_view(shapes: DataFrame) -> DataFrame:
    """``param, kind, n, m``: tensors of ``param, shape`` as matrices. The first axis stays, the others are laid flat; vectors travel as they are."""
    rest = F.aggregate(F.slice("shape", F.lit(2), F.greatest(F.size("shape") - 1, F.lit(0))), F.lit(1), lambda a, b: a * b)
    return shapes.select("param", F.when(F.size("shape") > 1, "matrix").otherwise("vector").alias("kind"), F.col("shape")[0].alias("n"), F.when(F.size("shape") > 1, rest).otherwise(1).alias("m"))
