"""Queries of the gradient methods, baselines, measures and workloads over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import lowrank as L
from .operators import relational as R
from .operators import sparse as S
from .operators import spectral as X
from .plans import costs, loop, training
from .plans.state import kept
from .sources import gradients as G

W = 4
N, M = G.QTR
K = 2 * (N + M)
DIGITS = 4


def cells(df: DataFrame, digits: int = DIGITS) -> DataFrame:
    """Cells rounded for comparison; negative zero and zero are one value."""
    return df.select(*[c for c in ("step", "param", "receiver", "worker", "i", "j") if c in df.columns], (F.round("v", digits) + F.lit(0.0)).alias("v"))


def factor(df: DataFrame, name: str) -> DataFrame:
    keys = [c for c in ("step", "param", "worker", "i", "j") if c in df.columns]
    return df.select(*keys, F.posexplode(name).alias("c", "v")).select(*keys, "c", (F.round("v", DIGITS) + F.lit(0.0)).alias("v"))


def step_of(rank: int, cold: bool = False):
    def parts(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame, DataFrame]:
        m = kept(G.quarterly(spark, sf_dir, W), "gradients")
        start = L.fresh_factor(m.select("step").distinct(), M, rank) if cold else L.start_factor(spark, M, rank)
        p = kept(L.orthogonalize(L.right_product(m, start, rank, W), rank), "left")
        return m, p, L.left_product(m, p, rank, W)

    return parts


LR, LAMBDA = 0.01, 0.9


def after(steps: int, part: str = "parameters", compressor=None, digits: int = DIGITS, **how):
    """A part of the optimizer's state after so many quarters, with warm low-rank steps of rank 1 or another compressor."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        state = loop.run(G.quarterly(spark, sf_dir, W), list(range(steps)), compressor or loop.low_rank(M, 1), W, LR, **({"momentum": LAMBDA} | how))
        out = getattr(state, part)
        return out.select("j", (F.round(F.col("q")[0], DIGITS) + F.lit(0.0)).alias("v")) if part == "carried" else out.select("i", "j", (F.round("v", digits) + F.lit(0.0)).alias("v"))

    return run


def votes(steps: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        state = loop.sign_descent(G.quarterly(spark, sf_dir, W), list(range(steps)), W, LR, LAMBDA)
        return state.parameters.select("i", "j", (F.round("v", 7) + F.lit(0.0)).alias("v"))

    return run


def computed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``step, compute_ms``: a hundredth of a millisecond for each sample of a quarter."""
    return kept(G.quarters(spark, sf_dir).select("step", (F.col("samples") * 0.01).alias("compute_ms")), "computed")


def warm_and_cold(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean over the quarters of the residual against that of the best matrix, warm and cold."""
    g = kept(G.quarterly(spark, sf_dir, W), "gradients")
    ranks, steps = [1, 2, 4], list(range(G.QUARTERS))
    sigma = kept(X.singular_values(g, N, M, W), "sigma")
    best = None
    for r in ranks:
        one = least(sigma, r).withColumn("rank", F.lit(r))
        best = one if best is None else best.unionByName(one)
    parts = [loop.tracked(g, M, ranks, W, steps, warm=start == "warm").withColumn("start", F.lit(start)) for start in ("warm", "cold")]
    both = parts[0].unionByName(parts[1]).join(best, ["step", "rank"])
    return both.groupBy("rank", "start").agg(F.round(F.avg(F.col("residual") / F.col("best")), 4).alias("ratio"))


def all_quarters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parameters after every quarter of the table, rank 1, warm, with memory and momentum.

    Low-rank steps read the workers through their mean only, so the mean gradient with one mean memory gives the parameters of all workers.
    """
    g = L.mean(G.quarterly(spark, sf_dir, W), W).withColumn("worker", F.lit(0)).select("step", "worker", "i", "j", "v")
    state = loop.run(g, list(range(G.QUARTERS)), loop.low_rank(M, 1), 1, LR, momentum=LAMBDA)
    return state.parameters.select("i", "j", (F.round("v", DIGITS) + F.lit(0.0)).alias("v"))


def excess(g: DataFrame, rank: int) -> DataFrame:
    """Relative error of the best matrix of a rank."""
    return least(X.singular_values(g, N, M, W), rank)


def least(sigma: DataFrame, rank: int) -> DataFrame:
    """``step, best``: share of the singular values beyond a rank."""
    square = F.col("sigma") * F.col("sigma")
    kept_ = F.sum(F.when(F.col("t") < rank, square).otherwise(0.0))
    return sigma.groupBy("step").agg(F.sqrt(F.greatest(F.lit(0.0), 1 - kept_ / F.sum(square))).alias("best"))


def two_params(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quarters and days as parameters of one model, side by side under ``param``: the first steps of both."""
    a = G.quarterly(spark, sf_dir, W).where("step < 3").withColumn("param", F.lit("quarters"))
    b = G.daily(spark, sf_dir, W).where("step < 3").withColumn("param", F.lit("days"))
    return kept(a.unionByName(b), "params")


def multi(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = two_params(spark, sf_dir)
    specs = spark.createDataFrame([("quarters", M), ("days", G.DAY[1])], "param string, m int")
    p, q = L.compress(m, L.start_factors(specs, 1), 1, W)
    return cells(L.reconstruct(p, q, 1))


def linearity(send: Callable[[DataFrame, int], DataFrame]):
    """Largest difference between one worker with all the data and the mean over all workers."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        m = kept(G.quarterly(spark, sf_dir, W), "gradients")
        one = m.groupBy("step", "i", "j").agg((F.sum("v") / W).alias("v")).withColumn("worker", F.lit(0))
        gap = L.gap(send(m, W).select("step", "i", "j", "v"), send(one, 1).select("step", "i", "j", "v"))
        return gap.agg(F.round(F.max("gap"), 6).alias("gap"))

    return run


def sweep(rank: int):
    def send(m: DataFrame, workers: int) -> DataFrame:
        p, q = L.compress(m, L.start_factor(m.sparkSession, M, rank), rank, workers)
        return L.reconstruct(p, q, rank)

    return send


def telescopes(compressor):
    """Updates so far plus the mean memory against the sum of all mean gradients: the largest difference."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = kept(G.quarterly(spark, sf_dir, W).where("step < 2"), "gradients")
        state = loop.run(g, [0, 1], compressor, W, 0.5, momentum=0.0)
        sent = loop.times(state.parameters, -1.0)
        held = L.mean(state.memory.withColumn("step", F.lit(0)), W)
        given = loop.times(L.mean(g, W), -1.0)
        return loop.added(sent, held, given).agg(F.round(F.max(F.abs("v")), 6).alias("gap"))

    return run


def lm_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = kept(G.trigram_counts(G.table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id", F.col("text"), W), "counts")
    return split_counts(counts)


def split_counts(counts: DataFrame) -> DataFrame:
    part = F.when(F.col("fold") == 0, "test").when(F.col("fold") != 5, "train")
    return counts.withColumn("part", part).where("part is not null").groupBy("part", "worker", "i", "j").agg(F.sum("n").alias("n"))


def class_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    classes = G.table(spark, sf_dir, "documents").where(F.col("lang").isin(G.LANGS)).select("doc_id", G.index_in(G.LANGS, "lang").alias("j"))
    return split_counts(kept(G.bigram_counts(spark, sf_dir, classes, W), "counts"))


def runs(methods: list[tuple[str, int]], seeds: int = 1, **how) -> list[training.Run]:
    return [training.Run(m, r, s, **how) for m, r in methods for s in range(seeds)]


def lm(methods: list[tuple[str, int]], seeds: int = 1, metric: str = "perplexity", **how):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = training.grid(lm_counts(spark, sf_dir), runs(methods, seeds, **how), G.LM3, W, float(G.LETTERS))
        return training.error_bars(kept(found, "metrics"), metric)

    return run


def classes(methods: list[tuple[str, int]], seeds: int = 1, **how):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = training.grid(class_counts(spark, sf_dir), runs(methods, seeds, lr=1.0, **how), G.LANG, W, float(G.LETTERS))
        return training.error_bars(kept(found, "metrics"), "accuracy")

    return run


MEDIUM = [("lowrank", 7), ("random_block", 7), ("random_k", 7), ("top_k", 7), ("sign_norm", 0)]
HIGH = [("lowrank", 2), ("random_block", 2), ("random_k", 2), ("top_k", 2)]
STEPS = 60  # of the main setting; lr 2 is the best of plain descent on the validation fold


def curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = training.grid(lm_counts(spark, sf_dir), runs([("identity", 0), ("lowrank", 4), ("lowrank", 7)], steps=60), G.LM3, W, float(G.LETTERS))
    return training.time_to_target(kept(found, "metrics"), "perplexity", 7.0)


def chosen(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = training.grid(lm_counts(spark, sf_dir), runs([("identity", 0), *[(m, r) for m in ("lowrank", "best_rank") for r in (1, 2, 4, 7)]], steps=STEPS), G.LM3, W, float(G.LETTERS))
    return training.choose_rank(kept(found, "metrics"), "perplexity")


def spectral_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean of sampled matrices over seeds against the matrix itself: relative error, which falls as draws add up."""
    g = kept(G.quarterly(spark, sf_dir, W).where("step = 0"), "gradients")
    total = None
    for seed in range(8):
        one = X.spectral_sampling(g, N, M, 4.0, W, seed)
        total = one if total is None else total.unionByName(one)
    mean = total.groupBy("step", "i", "j").agg((F.sum("v") / 8).alias("v"))
    d = loop.added(mean, loop.times(L.mean(g, W), -1.0)).agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("d"))
    size = L.mean(g, W).agg(F.sqrt(F.sum(F.col("v") * F.col("v"))).alias("size"))
    return d.join(F.broadcast(size)).select(F.round(F.col("d") / F.col("size"), 4).alias("error"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    quarters = lambda s, d: G.quarterly(s, d, W)
    q: dict[str, Callable[[SparkSession, str], DataFrame]] = {
        "grad_qtr": lambda s, d: cells(quarters(s, d)),
        "grad_day": lambda s, d: cells(G.daily(s, d, W)),
        "grad_mean": lambda s, d: cells(L.mean(quarters(s, d), W)),
        "grad_lm3": lambda s, d: cells(G.letters_model(s, d, W), 6),
        "grad_html": lambda s, d: cells(G.pages_model(s, d, W), 6),
        "grad_lang": lambda s, d: cells(G.languages_model(s, d, W), 6),
        "grad_qual": lambda s, d: cells(G.quality_model(s, d, W), 6),
        "grad_emb": lambda s, d: cells(G.embeddings_model(s, d, W), 6),
        "grad_price": lambda s, d: cells(G.prices_model(s, d, W)),
        "grad_wide": lambda s, d: G.hashed_words_counts(s, d, 2048, W),
        "vector_mean": lambda s, d: G.embeddings_bias(s, d, W).groupBy("step", "i").agg((F.round(F.sum("v") / W, 6) + F.lit(0.0)).alias("v")),
        "matrix_view": lambda s, d: costs.matrix_view(G.tensor_shapes(s, d)),
        "multi_param_step": multi,
        "start_factor": lambda s, d: factor(L.fresh_factor(G.quarters(s, d), M, 2), "q"),
        "right_product": lambda s, d: factor(L.right_product(quarters(s, d), L.start_factor(s, M, 2), 2, W, True), "p"),
        "lrc_p_mean": lambda s, d: factor(L.right_product(quarters(s, d), L.start_factor(s, M, 2), 2, W), "p"),
        "unbiased_lowrank_step": lambda s, d: cells(L.unbiased(quarters(s, d), M, 2, W)),
        "tree_reduce": lambda s, d: cells(S.tree_reduce(quarters(s, d), W)),
        "all_gather_fanout": lambda s, d: cells(S.decoded_at_receivers(quarters(s, d), W)),
        "majority_vs_mean": lambda s, d: S.majority(quarters(s, d)).withColumnRenamed("v", "vote").join(L.mean(quarters(s, d), W), ["step", "i", "j"]).select("step", "i", "j", "vote", F.round("v", DIGITS).alias("mean")),
        "sign_agreement": lambda s, d: S.sign_agreement(G.letters_model(s, d, W)),
        "top_k_step": lambda s, d: cells(S.top_k(quarters(s, d), K, M, W)),
        "random_k_step": lambda s, d: cells(S.random_k(quarters(s, d), K, N, M, W)),
        "random_block_step": lambda s, d: cells(S.random_block(quarters(s, d), K, N, M, W)),
        "sign_norm_step": lambda s, d: cells(S.sign_norm(quarters(s, d), N, M, W)),
        "sign_vote_step": lambda s, d: cells(S.sign_vote(quarters(s, d))),
        "double_compression_error": lambda s, d: S.double_compression(quarters(s, d), lambda m: S.largest(m, K, M), W).select("step", F.round("once", 5).alias("once"), F.round("twice", 5).alias("twice")),
        "linearity_gap_lowrank": linearity(sweep(2)),
        "linearity_gap_topk": linearity(lambda m, w: S.top_k(m, K, M, w)),
        "linearity_gap_sign": linearity(lambda m, w: S.sign_norm(m, N, M, w)),
        "gradient_drift": lambda s, d: cells(loop.drift(quarters(s, d), W)),
        "bytes_per_epoch": lambda s, d: costs.bytes_sent(G.quarters(s, d), N, M, 16, vectors=M),
        "cost_model": lambda s, d: costs.exchange(G.quarters(s, d).select("step", (F.col("samples") * 8).alias("bytes")), 0.05, 1e-6),
        "phase_breakdown": lambda s, d: costs.phases(computed(s, d), 2048, 2048),
        "relative_time": lambda s, d: costs.step_times(costs.phases(computed(s, d), 2048, 2048)),
        "scaling_curve": lambda s, d: costs.scaling(kept(G.quarters(s, d), "quarters"), 2048, 2048),
        "lr_schedule": lambda s, d: costs.rates(G.order_weeks(s, d)),
        "warm_track_3": after(3, "carried", feedback=False),
        "warm_vs_cold": warm_and_cold,
        "efm_step_1": after(1),
        "efm_two_steps": after(2),
        "efm_all_quarters": all_quarters,
        "efm_no_momentum": after(2, momentum=0.0),
        "efm_heavy_ball": after(2, rule="heavy_ball"),
        "efm_nesterov": after(2, rule="nesterov"),
        "efm_local_error": after(2, compressor=loop.low_rank(M, 1, error_target="local")),
        "weight_decay": after(2, decay=0.01),
        "efm_identity": after(2, compressor=loop.identity, digits=7),
        "efm_top_k": after(2, compressor=loop.top_k(K, M), digits=7),
        "efm_random_k": after(2, compressor=loop.random_k(K, N, M), digits=7),
        "efm_random_block": after(2, compressor=loop.random_block(K, N, M), digits=7),
        "efm_sign_norm": after(2, compressor=loop.sign_norm(N, M), digits=7),
        "efm_best_rank": after(2, compressor=loop.best_rank(N, M, 2)),
        "efm_momentum_before": after(2, compressor=loop.top_k(K, M), momentum_site="pre", digits=7),
        "sign_vote_descent": votes(2),
        "no_feedback_step": after(2, feedback=False),
        "feedback_telescopes": telescopes(loop.low_rank(M, 2)),
        "svd_energy": lambda s, d: X.singular_values(quarters(s, d), N, M, W).groupBy("step").agg(F.round(F.sum(F.col("sigma") * F.col("sigma")), 4).alias("energy")),
        "energy_curve": lambda s, d: X.energy_curve(X.singular_values(quarters(s, d), N, M, W)).select("step", "rank", F.round("share", 6).alias("share")),
        "best_rank_residual": lambda s, d: excess(quarters(s, d), 2).select("step", F.round("best", 5).alias("residual")),
        "spectral_sampling_step": lambda s, d: cells(X.spectral_sampling(quarters(s, d), N, M, 2.0, W)),
        "spectral_unbiased": spectral_means,
        "wl_ef_vs_unbiased": lm([("identity", 0), *[(m, r) for m in ("lowrank", "unbiased_lowrank") for r in (1, 2, 4)]], 3, steps=STEPS),
        "wl_best_warm_cold": lm([(m, r) for m in ("best_rank", "lowrank", "lowrank_cold") for r in (2, 4)], 3, steps=STEPS),
        "wl_rank_sweep_lm": lm([("identity", 0), *[("lowrank", r) for r in (1, 2, 4, 7)]], 3, steps=STEPS),
        "wl_rank_sweep_class": classes([("identity", 0), *[("lowrank", r) for r in (1, 2, 4)]], 3, steps=40),
        "wl_compressors_medium": lm(MEDIUM, 3, steps=STEPS),
        "wl_compressors_high": lm(HIGH, 3, steps=STEPS),
        "wl_compressors_bytes": lm([("identity", 0), *MEDIUM, *HIGH], metric="bytes", steps=10),
        "wl_other_lm": lm([("identity", 0), ("lowrank", 4)], 3, steps=STEPS),
        "wl_other_lm_vote": lm([("sign_vote", 0)], 3, steps=STEPS, lr=0.05),
        "wl_other_class": classes([("identity", 0), ("lowrank", 2), ("spectral_sampling", 2)], 3, steps=40),
        "time_to_target": curve,
        "choose_rank": chosen,
    }
    for rank in (1, 2, 4, 7):
        parts = step_of(rank)
        q[f"orthogonalize_r{rank}"] = lambda s, d, f=parts: factor(f(s, d)[1], "p")
        q[f"left_product_r{rank}"] = lambda s, d, f=parts: factor(f(s, d)[2], "q")
        q[f"lrc_step_r{rank}"] = lambda s, d, f=parts, r=rank: cells(L.reconstruct(*f(s, d)[1:], r))
        q[f"residual_r{rank}"] = lambda s, d, f=parts, r=rank: (lambda m, p, x: L.residual(m, x, r, W).withColumn("residual", F.round("residual", 5)))(*f(s, d))
        q[f"error_memory_r{rank}"] = lambda s, d, f=parts, r=rank: (lambda m, p, x: cells(S.remember(m, L.reconstruct(p, x, r), W)))(*f(s, d))
        q[f"orthonormality_r{rank}"] = lambda s, d, f=parts, r=rank: L.orthonormality(f(s, d)[1], r).select("step", "a", "b", (F.round("dot", 6) + F.lit(0.0)).alias("dot"))
    q["cold_step"] = lambda s, d: cells(L.reconstruct(*step_of(1, True)(s, d)[1:], 1))
    return q | R.queries()
