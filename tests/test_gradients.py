import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from rankfeed import oracles, queries
from rankfeed.operators import lowrank as L
from rankfeed.operators import sparse as S
from rankfeed.operators import spectral as X
from rankfeed.plans import loop
from tests.conftest import SF, TABLES


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as from '{SF}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(oracles.oracle_sql()))
def test_same_as_sql(spark, duck, name):
    got = queries.queries()[name](spark, SF).toPandas()
    want = duck.execute(oracles.oracle_sql()[name]).df()
    names = sorted(want.columns)
    assert sorted(got.columns) == names
    assert sorted(map(tuple, got[names].values.tolist())) == sorted(map(tuple, want[names].values.tolist()))


def matrix(spark, rows, workers=1):
    return spark.createDataFrame([(0, w, i, j, float(v)) for w in range(workers) for i, r in enumerate(rows) for j, v in enumerate(r)], "step int, worker int, i int, j int, v double")


def test_exact_rank_is_recovered(spark):
    m = matrix(spark, [[1, 2, 3], [2, 4, 6], [0, 1, 0]])
    p, q = L.compress(m, L.start_factor(spark, 3, 2), 2, 1)
    assert L.residual(m, q, 2, 1).first()["residual"] < 1e-6
    dots = p.select(*[F.sum(F.col("p")[a] * F.col("p")[b]) for a, b in ((0, 0), (0, 1), (1, 1))]).first()
    assert [round(x, 9) for x in dots] == [1, 0, 1]


def test_zero_matrix_gives_zero_factors(spark):
    p, q = L.compress(matrix(spark, [[0, 0], [0, 0]]), L.start_factor(spark, 2, 2), 2, 1)
    assert all(v == 0 for r in q.collect() for v in r["q"])


def test_top_k_breaks_ties_by_position(spark):
    out = S.top_k(matrix(spark, [[1, -1], [1, 0]]), 2, 2, 1).collect()
    assert sorted((r.i, r.j) for r in out) == [(0, 0), (0, 1)]


def test_even_vote_is_zero(spark):
    m = spark.createDataFrame([(0, 0, 0, 0, 2.0), (0, 1, 0, 0, -1.0)], "step int, worker int, i int, j int, v double")
    assert S.sign_vote(m).first()["v"] == 0


def test_keep_probabilities_use_the_budget():
    p = X.keep_probabilities(np.array([10.0, 1, 1, 0]), 2)
    assert p.sum() == pytest.approx(2) and p.max() == 1 and p[3] == 0


def test_best_rank_is_not_worse_than_a_sweep(spark):
    rows = [[(3 * i + 5 * j) % 7 for j in range(5)] for i in range(4)]
    m = matrix(spark, rows)
    a = np.array(rows, float)
    best = np.zeros_like(a)
    for r in X.best_rank(m, 4, 5, 2, 1).collect():
        best[r.i, r.j] = r.v
    sweep = L.residual(m, L.compress(m, L.start_factor(spark, 5, 2), 2, 1)[1], 2, 1).first()["residual"]
    assert np.linalg.norm(a - best) / np.linalg.norm(a) <= sweep + 1e-9


@pytest.mark.parametrize("compressor", [loop.identity, loop.low_rank(3, 1), loop.low_rank(3, 1, warm=False), loop.top_k(2, 3)])
def test_feedback_loses_nothing(spark, compressor):
    """Updates so far plus the mean memory are the sum of all gradients."""
    g = matrix(spark, [[1, 2, 3], [4, 0, -2]], workers=2).unionByName(matrix(spark, [[0, 1, 5], [2, 2, 2]], workers=2).withColumn("step", F.lit(1)))
    state = loop.run(g, [0, 1], compressor, 2, 0.5, momentum=0.0)
    sent = {(r.i, r.j): -r.v for r in state.parameters.collect()}  # each update counts twice without momentum, times 0.5
    kept = {(r.i, r.j): r.v for r in L.mean(state.memory.withColumn("step", F.lit(0)), 2).collect()}
    want = {(r.i, r.j): r.v / 2 for r in g.groupBy("i", "j").agg(F.sum("v").alias("v")).collect()}
    assert {k: round(sent.get(k, 0) + kept.get(k, 0), 9) for k in want} == pytest.approx(want)


def test_rank_seven_is_orthonormal_and_dependent_columns_vanish(spark):
    rng = np.random.default_rng(0)
    a = rng.normal(size=(20, 9)) @ rng.normal(size=(9, 12))
    m = matrix(spark, a.tolist())
    p = L.orthogonalize(L.right_product(m, L.start_factor(spark, 12, 7), 7, 1), 7)
    dots = {(r.a, r.b): r.dot for r in L.orthonormality(p, 7).collect()}
    assert all(abs(v - (x == y)) < 1e-9 for (x, y), v in dots.items())


def test_training_recovers_counts():
    from rankfeed.plans import training

    rng = np.random.default_rng(1)
    n = rng.integers(0, 30, (2, 6, 4)).astype(float)
    gradient = lambda x: (np.exp(training.log_probabilities(x))[None] * n.sum(2, keepdims=True) - n) / n.sum((1, 2), keepdims=True)
    loss = lambda x: {"loss": float(-(n.sum(0) * training.log_probabilities(x)).sum() / n.sum())}
    last = {}
    for method, rank in (("identity", 0), ("lowrank", 2), ("best_rank", 2), ("top_k", 1), ("no_update", 0)):
        out = training.trained(training.Run(method, rank, steps=40, lr=0.5), gradient, (6, 4), loss)
        last[method] = out[(out.metric == "loss") & (out.step == 40)].value.iloc[0]
    assert max(last[k] for k in ("identity", "lowrank", "best_rank", "top_k")) < last["no_update"]


def test_one_chain_gives_the_residuals_of_all_ranks(spark):
    """Warm sweeps of each rank on its own, in NumPy, against the first columns of the chain of the largest rank."""
    rng = np.random.default_rng(3)
    mats = [rng.normal(size=(6, 5)) for _ in range(3)]
    g = None
    for t, a in enumerate(mats):
        one = matrix(spark, a.tolist(), workers=2).withColumn("step", F.lit(t))
        g = one if g is None else g.unionByName(one)
    got = {(r.step, r["rank"]): r.residual for r in loop.tracked(g, 5, [1, 3], 2, [0, 1, 2]).collect()}
    for rank in (1, 3):
        q = np.array([r.q for r in L.start_factor(spark, 5, rank).orderBy("j").collect()])
        for t, a in enumerate(mats):
            p, _ = np.linalg.qr(a @ q)
            q = a.T @ p
            assert got[t, rank] == pytest.approx(np.linalg.norm(a - p @ q.T) / np.linalg.norm(a))


def test_mean_gradients_give_the_parameters_of_all_workers(spark):
    """Low-rank steps with memory and momentum see the workers through their mean only."""
    rng = np.random.default_rng(4)
    g = None
    for t in range(3):
        for w in range(3):
            one = matrix(spark, rng.normal(size=(4, 3)).tolist()).withColumn("step", F.lit(t)).withColumn("worker", F.lit(w))
            g = one if g is None else g.unionByName(one)
    mean = L.mean(g, 3).withColumn("worker", F.lit(0)).select("step", "worker", "i", "j", "v")
    whole, short = (loop.run(x, [0, 1, 2], loop.low_rank(3, 1), n, 0.1).parameters for x, n in ((g, 3), (mean, 1)))
    assert {(r.i, r.j): r.v for r in short.collect()} == pytest.approx({(r.i, r.j): r.v for r in whole.collect()})
