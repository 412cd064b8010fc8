"""The interest model: a linear score, squashed by a logistic with a floor."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.functions import bits
from prefpat.operators.encode import EncodedDataset

#: Scores are clamped so that the exponential stays finite.
CLAMP = 700.0


@dataclass
class Weights:
    """Weights by feature; ``transactions`` are (mask words, weight), non-zero ones only."""

    items: np.ndarray
    length: float = 0.0
    frequency: float = 0.0
    transactions: list[tuple[tuple[int, ...], float]] = field(default_factory=list)

    @classmethod
    def zero(cls, n_items: int) -> Weights:
        return cls(np.zeros(n_items))


def logistic(score, floor: float):
    """Floor plus the rest of the range times the sigmoid; columns or numpy arrays."""
    if isinstance(score, Column):
        held = F.greatest(F.least(score, F.lit(CLAMP)), F.lit(-CLAMP))
        return F.lit(floor) + F.lit(1 - floor) / (1 + F.exp(-held))
    return floor + (1 - floor) / (1 + np.exp(-np.clip(score, -CLAMP, CLAMP)))


def zero_weight(floor: float) -> float:
    """Every pattern's weight before anything is learned."""
    return floor + (1 - floor) / 2


def tilt(floor: float) -> float:
    """Bound of the largest weight over the smallest; the floor must not be 0."""
    if not 0 < floor <= 1:
        raise ValueError("the floor lies in (0, 1]: without it weights have no bound")
    return 1 / floor


def weights_frame(spark, w: Weights, words: int) -> DataFrame:
    """One row of data. As literals they would compile new code every round."""
    known = [tuple(map(int, masks)) + (float(x),) for masks, x in w.transactions]
    inner = ", ".join([f"{m}: bigint" for m in bits.mask_names(words)] + ["w: double"])
    schema = f"w_items array<double>, w_len double, w_freq double, w_trans array<struct<{inner}>>, one int"
    return spark.createDataFrame([([float(x) for x in w.items], float(w.length), float(w.frequency), known, 1)], schema)


def score_patterns(patterns: DataFrame, w: Weights, ds: EncodedDataset) -> DataFrame:
    """Adds ``score`` to every pattern, in one narrow step after a one-row broadcast."""
    sent = F.broadcast(weights_frame(patterns.sparkSession, w, ds.words))
    joined = patterns.withColumn("one", F.lit(1)).join(sent, "one").drop("one")
    score = F.aggregate("items", F.lit(0.0), lambda a, i: a + F.get("w_items", i)) + F.col("w_len") * F.col("len") / float(max(ds.n_items, 1)) + F.col("w_freq") * F.col("sup") / float(max(ds.n, 1))
    if w.transactions:
        inside = lambda t: bits.contains([t[m] for m in ds.masks], [F.col(m) for m in ds.masks])
        score = score + F.aggregate("w_trans", F.lit(0.0), lambda a, t: a + F.when(inside(t), t["w"]).otherwise(0.0))
    return joined.withColumn("score", score).drop("w_items", "w_len", "w_freq", "w_trans")


def with_weight(patterns: DataFrame, w: Weights, ds: EncodedDataset, floor: float) -> DataFrame:
    """Adds ``score`` and the sampling weight ``w`` in (0, 1]."""
    tilt(floor)
    return score_patterns(patterns, w, ds).withColumn("w", logistic(F.col("score"), floor))


def rank_keys(patterns: DataFrame, by: str = "score") -> DataFrame:
    """Adds ``rank_key``, whose order is the predicted one: best first, equal scores (of
    nine digits) by the pattern itself."""
    return patterns.withColumn("rank_key", F.struct((-F.round(by, 9)).alias("worse"), "pattern"))
