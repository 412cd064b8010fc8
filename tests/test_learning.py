import numpy as np
import pytest

from prefpat.operators import pairs
from prefpat.plans import learn


def data(seed=1, n=60, width=8):
    rng = np.random.default_rng(seed)
    x, w = rng.choice([-1.0, 0, 1], (n, width)), rng.normal(0, 1, width)
    return x * np.where(x @ w >= 0, 1, -1)[:, None]


def test_pairs_of_the_worked_rankings(spark):
    rows = [("s", 1, 1, 3.0, "1"), ("s", 1, 2, 2.0, "3"), ("s", 1, 3, 1.0, "2"), ("s", 2, 1, 2.0, "4"), ("s", 2, 2, 1.0, "2"), ("s", 3, 1, 5.0, "x"), ("s", 3, 2, 5.0, "y")]
    df = spark.createDataFrame(rows, "session_id string, iter int, pos int, level double, pattern string")
    assert {(r.winner, r.loser) for r in pairs.from_rankings(df).collect()} == {("1", "3"), ("1", "2"), ("3", "2"), ("4", "2")}


def test_descent_reaches_the_optimum(spark):
    d = data()
    fit = learn.scd_l1(d, 0.01, 20_000, trace=True)
    assert all(b <= a + 1e-12 for a, b in zip(fit.trace, fit.trace[1:]))
    assert learn.kkt_violation(d, fit.weights, 0.01) < 1e-6
    assert fit.weights == pytest.approx(learn.l1_reference(spark, d, 0.01), abs=1e-3)


def test_any_prefix_is_usable_and_strong_penalties_give_nothing():
    d = data()
    assert learn.objective(d, learn.scd_l1(d, updates=5).weights, 1e-3) <= learn.objective(d, np.zeros(d.shape[1]), 1e-3)
    assert not learn.scd_l1(d, 10.0).weights.any()
    assert not learn.scd_l1(np.zeros((0, 4))).weights.any()


def test_rank_svm_orders_separable_pairs():
    d = data()
    w = learn.rank_svm(d, 10.0, 2000)
    assert (d @ w >= 0).mean() > 0.95
    assert (np.abs(learn.rank_svm(d, 1e-6)) < 1e-3).all()
