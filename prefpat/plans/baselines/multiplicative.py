"""Sampler with multiplicative item weights and like/dislike feedback.

A pattern's weight is the product of its items' weights. A liked sample multiplies
its items' weights by b, a disliked one divides them. Draws are perfect ones over all
patterns, one portable number each. Weights are kept as logarithms; ``double`` keeps plain numbers instead and
stops as failed where they overflow.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefpat.functions.rng import u01, u01_py
from prefpat.plans.spaces import MatrixSpace, Shown


@dataclass
class Sampled:
    samples: list[Shown]
    liked: list[bool]
    status: str
    log_weights: np.ndarray


def run(space: MatrixSpace, likes, n: int = 300, b: float = 1.75, seed=0, weights: str = "log", every: int = 1) -> Sampled:
    """``every``: weights change after so many samples, with all their feedback."""
    log_w, plain = np.zeros(space.n_items), np.ones(space.n_items)
    samples: list[Shown] = []
    liked: list[bool] = []
    waiting = []
    for i in range(n):
        if weights == "double":
            with np.errstate(over="ignore", invalid="ignore"):
                product = np.multiply.reduceat(plain[space.flat], space.starts)
                total = product.sum()
            if not np.isfinite(total) or total <= 0:
                return Sampled(samples, liked, "overflow", np.log(np.maximum(plain, 1e-300)))
            score = np.log(np.maximum(product, 1e-300))
        else:
            score = np.add.reduceat(log_w[space.flat], space.starts)
        reached = np.cumsum(np.exp(score - score.max()))
        place = min(int(np.searchsorted(reached, u01_py(seed, "multiplicative", i) * reached[-1])), len(score) - 1)
        shown = space.shown([place], np.ones(len(space.pattern)))[0]
        samples.append(shown)
        liked.append(bool(likes.likes(shown.items)))
        waiting.append((shown, liked[-1]))
        if len(waiting) == every:
            for s, like in waiting:
                change = np.log(b) if like else -np.log(b)
                log_w[list(s.items)] += change
                with np.errstate(over="ignore"):
                    plain[list(s.items)] *= b if like else 1 / b
            waiting = []
    return Sampled(samples, liked, "ok", log_w)


def windows(samples: list[Shown], group: int = 10, tail: int = 5) -> list[list[Shown]]:
    """The last ``tail`` of each group of samples stand for a query."""
    return [samples[i + group - tail : i + group] for i in range(0, len(samples) - group + 1, group)]


def first_draw(patterns: DataFrame, log_weights: DataFrame, seed) -> DataFrame:
    """One perfect draw as a plan: the largest of log weight plus Gumbel noise.

    ``log_weights`` is ``(item_id, lw)``, one row an item.
    """
    sent = log_weights.agg(F.transform(F.array_sort(F.collect_list(F.struct("item_id", "lw"))), lambda s: s["lw"]).alias("_lw")).withColumn("_one", F.lit(1))
    joined = patterns.withColumn("_one", F.lit(1)).join(F.broadcast(sent), "_one")
    key = F.aggregate("items", F.lit(0.0), lambda a, i: a + F.get("_lw", i)) - F.ln(-F.ln(u01(F.lit(seed), F.lit("gumbel"), F.col("pattern")) - 1e-12))
    return joined.withColumn("key", key).agg(F.max_by(F.col("pattern"), F.col("key")).alias("pattern"))
