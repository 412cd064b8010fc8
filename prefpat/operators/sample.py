"""Weighted draws of patterns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from prefpat.functions.rng import u01


def race_key(weight: Column, *parts) -> Column:
    """The least key belongs to a row with probability weight / sum of weights, and
    the n least are n draws without replacement; no total is needed."""
    return F.when(weight > 0, -F.ln(u01(*parts)) / weight)


def exact(patterns: DataFrame, weight: Column, n: int, seed, replace: bool = False) -> DataFrame:
    """Perfect samples over materialised patterns: one mergeable aggregate or top-n."""
    if not replace:
        keyed = patterns.withColumn("_key", race_key(weight, F.lit(seed), F.lit("race"), F.col("pattern")))
        return keyed.where("_key is not null").orderBy("_key", "pattern").limit(n).drop("_key")
    drawn = patterns.withColumn("_w", weight).where("_w > 0").withColumn("draw_id", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    keyed = drawn.withColumn("_key", race_key(F.col("_w"), F.lit(seed), F.col("draw_id"), F.col("pattern")))
    best = keyed.groupBy("draw_id").agg(F.min_by(F.struct(*[c for c in patterns.columns]), F.struct("_key", "pattern")).alias("p"))
    return best.select("draw_id", "p.*")


def uniform(patterns: DataFrame, n: int, seed) -> DataFrame:
    return exact(patterns, F.lit(1.0), n, seed)


def ideal(patterns: DataFrame, phi: str, n: int, seed) -> DataFrame:
    """In proportion to the hidden quality: what the loop tries to learn."""
    return exact(patterns, F.col(phi), n, seed)


def sessions(patterns: DataFrame, weight: Column, grid: DataFrame) -> DataFrame:
    """``(session_id, iter, pos, pattern)``: for every row ``(session_id, seed, rounds, k)``
    of a grid, ``rounds`` queries of ``k`` patterns drawn by weight, without learning.

    The grid is broadcast; the ``k`` least race keys of a query are found in
    sixteen parts first, so no query's candidates meet in one task.
    """
    rounds = grid.select("session_id", "seed", "k", F.explode(F.sequence(F.lit(1), F.col("rounds"))).alias("iter"))
    drawn = patterns.withColumn("_w", weight).where("_w > 0").withColumn("_one", F.lit(1)).join(F.broadcast(rounds.withColumn("_one", F.lit(1))), "_one")
    drawn = drawn.withColumn("_key", race_key(F.col("_w"), F.col("seed"), F.col("iter"), F.col("pattern")))
    near = Window.partitionBy("session_id", "iter", "_part").orderBy("_key", "pattern")
    order = Window.partitionBy("session_id", "iter").orderBy("_key", "pattern")
    few = drawn.withColumn("_part", F.pmod(F.xxhash64("pattern"), F.lit(16))).withColumn("_at", F.row_number().over(near)).where("_at <= k")
    return few.withColumn("pos", F.row_number().over(order)).where("pos <= k").select("session_id", "iter", "pos", "pattern")


def from_cell(cells: DataFrame, strategy, seed=0) -> DataFrame:
    """One weighted draw of each cell (``"random"``) or its m best (``("top", m)``)."""
    if strategy == "random":
        key = F.struct(race_key(F.col("w"), F.lit(seed), F.col("draw_id"), F.col("pattern")).alias("k"), "pattern")
        rows = cells.groupBy("draw_id").agg(F.min_by(F.struct(*cells.columns), key).alias("p"))
        return rows.select("p.*")
    kind, m = strategy
    if kind != "top":
        raise ValueError(strategy)
    order = Window.partitionBy("draw_id").orderBy(F.desc("w"), "pattern")
    return cells.withColumn("place", F.row_number().over(order)).where(F.col("place") <= m)


def batch(picks: DataFrame, need: int) -> DataFrame:
    """The first ``need`` distinct patterns over draws in order (best of a cell first)."""
    kept = ["draw_id", "w"]
    first = picks.groupBy("pattern").agg(F.min_by(F.struct(*kept), F.struct("draw_id", (-F.col("w")).alias("better"))).alias("p"))
    return first.select("pattern", "p.*").orderBy("draw_id", F.desc("w"), "pattern").limit(need)


def within_cell_prob(cells: DataFrame) -> DataFrame:
    """Each pattern's chance under a weighted draw from its cell."""
    return cells.withColumn("prob", F.col("w") / F.sum("w").over(Window.partitionBy("draw_id")))
