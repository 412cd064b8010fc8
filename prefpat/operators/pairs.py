"""Rankings to ordered pairs to difference vectors, as plans.

Feedback rows are ``(session_id, iter, pos, level, pattern)``: equal levels are ties
and give no pair. Pairs come from inside one ranking only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def from_rankings(feedback: DataFrame) -> DataFrame:
    """``(session_id, iter, winner, loser)``: a ranking's better against its worse."""
    better = feedback.select("session_id", "iter", F.col("pos").alias("p1"), F.col("level").alias("v1"), F.col("pattern").alias("winner"))
    worse = feedback.select("session_id", "iter", F.col("pos").alias("p2"), F.col("level").alias("v2"), F.col("pattern").alias("loser"))
    return better.join(worse, ["session_id", "iter"]).where("p1 < p2 and v1 <> v2").select("session_id", "iter", "winner", "loser")


def deltas(pairs: DataFrame, features: DataFrame) -> DataFrame:
    """``(session_id, iter, winner, loser, feature_id, delta)`` without zeros."""
    key = ["session_id", "iter", "winner", "loser"]
    plus = pairs.join(features, pairs.winner == features.pattern).select(*key, "feature_id", "value")
    minus = pairs.join(features, pairs.loser == features.pattern).select(*key, "feature_id", (-F.col("value")).alias("value"))
    return plus.unionByName(minus).groupBy(*key, "feature_id").agg(F.sum("value").alias("delta")).where(F.abs("delta") > 1e-15)


def discordant(pairs: DataFrame, scores: DataFrame) -> DataFrame:
    """``(session_id, pairs, discordant)``: pairs that a score does not order as asked."""
    s = scores.select("pattern", "score")
    joined = pairs.join(s.toDF("winner", "s_winner"), "winner").join(s.toDF("loser", "s_loser"), "loser")
    return joined.groupBy("session_id").agg(F.count(F.lit(1)).alias("pairs"), F.count_if(F.col("s_winner") <= F.col("s_loser")).alias("discordant"))
