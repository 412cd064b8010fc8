"""Learners on difference vectors: coordinate descent for an L1 logistic loss, and a
linear rank-SVM. The data are tiny (pairs of a session by features) whatever the size
of the dataset, so both are numpy kernels, run on the driver or inside executors."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np

from prefpat.functions.rng import u32_py


def sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -700, 700)))


def objective(deltas: np.ndarray, weights: np.ndarray, lam: float) -> float:
    """Mean logistic loss of the margins plus the penalty."""
    loss = np.logaddexp(0, -(deltas @ weights)).mean() if len(deltas) else 0.0
    return float(loss + lam * np.abs(weights).sum())


@dataclass
class Fit:
    weights: np.ndarray
    trace: list[float]


def scd_l1(deltas: np.ndarray, lam: float = 1e-3, updates: int = 1000, seed=0, start: np.ndarray | None = None, active_only: bool = False, trace: bool = False, order: Sequence[int] | None = None) -> Fit:
    """Stochastic coordinate descent; any number of updates gives a usable model.

    One update picks a coordinate, steps against its gradient by the curvature bound
    (a quarter of the column's largest square) and shrinks by the penalty. Margins
    are kept, so an update costs one column. Columns of zeros stay at zero. ``order``
    gives the coordinates of the updates where they have been drawn before, over
    more columns than those that are here.
    """
    n, width = deltas.shape
    weights = np.zeros(width) if start is None else start.astype(float).copy()
    history: list[float] = []
    if not n or not width:
        return Fit(weights, history)
    curvature = (deltas**2).max(axis=0) / 4
    pool = np.flatnonzero(curvature) if active_only else np.arange(width)
    if not len(pool):
        return Fit(weights, history)
    margins = deltas @ weights
    columns = np.asfortranarray(deltas)
    for t in range(updates):
        j = int(pool[u32_py(seed, "scd", t) % len(pool)]) if order is None else order[t]
        if curvature[j]:
            column = columns[:, j]
            gradient = -(column @ sigmoid(-margins)) / n
            moved = weights[j] - gradient / curvature[j]
            new = np.sign(moved) * max(abs(moved) - lam / curvature[j], 0.0)
            if new != weights[j]:
                margins += column * (new - weights[j])
                weights[j] = new
        if trace:
            history.append(objective(deltas, weights, lam))
    return Fit(weights, history)


def drawn_coordinates(width: int, updates: int, seed) -> list[int]:
    """The coordinates that ``scd_l1`` picks over so many columns."""
    return [u32_py(seed, "scd", t) % width for t in range(updates)]


def kkt_violation(deltas: np.ndarray, weights: np.ndarray, lam: float) -> float:
    """Distance from optimality: 0 at the optimum."""
    gradient = -(deltas.T @ sigmoid(-(deltas @ weights))) / len(deltas)
    at_zero = np.maximum(np.abs(gradient) - lam, 0)
    return float(np.where(weights == 0, at_zero, np.abs(gradient + lam * np.sign(weights))).max(initial=0.0))


def l1_reference(spark, deltas: np.ndarray, lam: float) -> np.ndarray:
    """The same optimum by Spark ML, on mirrored pairs without intercept."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.linalg import Vectors

    rows = [(float(y), Vectors.dense(s * d)) for d in deltas for s, y in ((1, 1), (-1, 0))]
    model = LogisticRegression(elasticNetParam=1.0, regParam=lam, fitIntercept=False, standardization=False, maxIter=2000, tol=1e-10)
    return model.fit(spark.createDataFrame(rows, ["label", "features"])).coefficients.toArray()


def rank_svm(deltas: np.ndarray, c: float = 0.005, epochs: int = 200, seed=0, tol: float = 1e-8) -> np.ndarray:
    """Linear hinge-loss SVM on difference vectors, by dual coordinate descent."""
    return rank_svm_dual(deltas @ deltas.T, c, epochs, seed, tol) @ deltas


def rank_svm_dual(gram: np.ndarray, c: float = 0.005, epochs: int = 200, seed=0, tol: float = 1e-8) -> np.ndarray:
    """How much each difference vector counts in the weights, from their inner products
    alone: the vectors themselves may be of any width."""
    n = len(gram)
    margins, dual = np.zeros(n), np.zeros(n)
    squares = gram.diagonal()
    rng = np.random.default_rng(u32_py(seed, "svm"))
    for _ in range(epochs):
        change = 0.0
        for r in rng.permutation(n):
            if squares[r] > 0:
                new = min(max(dual[r] - (margins[r] - 1) / squares[r], 0.0), c)
                if new != dual[r]:
                    margins += (new - dual[r]) * gram[r]
                    change, dual[r] = max(change, abs(new - dual[r])), new
        if change < tol:
            break
    return dual
