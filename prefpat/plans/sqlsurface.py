"""The methods from SQL: table functions, aggregates and a vectorised function."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from prefpat.functions.model import logistic
from prefpat.operators.xorcells import draw_py
from prefpat.plans.learn import scd_l1


@F.udtf(returnType="draw_id int, x int, words array<bigint>, parity int")
class XorDraws:
    """``xor_draws(seed, m, n_items, n_draws)``: random parity constraints."""

    def eval(self, seed: str, m: int, n_items: int, n_draws: int):
        for d, constraints in enumerate(draw_py(m, n_items, range(n_draws), seed)):
            for x, (words, parity) in enumerate(constraints):
                yield d, x, words, parity


@F.udtf(returnType="feature_id int, w double")
class ScdFit:
    """``scd_fit(TABLE(rows) PARTITION BY session_id, lam, updates, seed)`` over rows with
    ``(pair_id, feature_id, delta)``. There is one fit for each partition, so the rows
    of a single session need ``WITH SINGLE PARTITION``."""

    def __init__(self):
        self.rows, self.settings = [], (1e-3, 1000, "0")

    def eval(self, row, lam: float, updates: int, seed: str):
        self.rows.append((row["pair_id"], row["feature_id"], row["delta"]))
        self.settings = (float(lam), int(updates), seed)

    def terminate(self):
        if not self.rows:
            return
        frame = pd.DataFrame(self.rows, columns=["pair", "feature", "delta"]).pivot_table(index="pair", columns="feature", values="delta", fill_value=0.0)
        lam, updates, seed = self.settings
        fitted = scd_l1(frame.to_numpy(), lam, updates, seed).weights
        for feature, w in zip(frame.columns, fitted):
            if w:
                yield int(feature), float(w)


def entropy_udaf():
    """Entropy in bits of the grouped values, as a grouped-aggregate function."""

    @F.pandas_udf("double")
    def entropy_bits(values: pd.Series) -> float:
        share = values.value_counts(normalize=True).to_numpy()
        return float(-(share * np.log2(share)).sum())

    return entropy_bits


def weighted_draw_udaf():
    """One weighted draw from a group: least of -ln(u) / w over given uniforms."""

    @F.pandas_udf("string")
    def weighted_draw(pattern: pd.Series, w: pd.Series, u: pd.Series) -> str:
        return pattern.iloc[int((-np.log(u) / w).to_numpy().argmin())]

    return weighted_draw


def quality_udf():
    """Floored logistic of a score; plans use the column form instead."""

    @F.pandas_udf("double")
    def floored_logistic(score: pd.Series, floor: pd.Series) -> pd.Series:
        return pd.Series(logistic(score.to_numpy(), floor.to_numpy()))

    return floored_logistic


def register(spark: SparkSession) -> None:
    spark.udtf.register("xor_draws", XorDraws)
    spark.udtf.register("scd_fit", ScdFit)
    spark.udf.register("entropy_bits", entropy_udaf())
    spark.udf.register("weighted_draw", weighted_draw_udaf())
    spark.udf.register("floored_logistic", quality_udf())
