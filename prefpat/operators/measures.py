"""Accuracy, diversity and cost measures.

``queries`` rows are ``(session_id, iter, pos, pattern)``; ``pct`` rows map a pattern
to its percentile.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from prefpat.functions import bits
from prefpat.functions.rng import u01
from prefpat.operators.encode import EncodedDataset
from prefpat.operators.relational import running_counts


def query_quality(queries: DataFrame, pct: DataFrame) -> DataFrame:
    """``(session_id, iter, avg_quality, max_quality)`` of what was shown."""
    joined = queries.join(pct.select("pattern", "pct"), "pattern")
    return joined.groupBy("session_id", "iter").agg(F.avg("pct").alias("avg_quality"), F.max("pct").alias("max_quality"))


def avg_quality(queries: DataFrame, pct: DataFrame) -> DataFrame:
    return query_quality(queries, pct).select("session_id", "iter", F.col("avg_quality").alias("value"))


def max_quality(queries: DataFrame, pct: DataFrame) -> DataFrame:
    return query_quality(queries, pct).select("session_id", "iter", F.col("max_quality").alias("value"))


def signature(shown: Column, masks: list[str]) -> Column:
    """Which of the shown patterns a transaction contains, as a text of 0 and 1."""
    inside = lambda p: bits.contains([F.col(m) for m in masks], [p[m] for m in masks])
    return F.array_join(F.transform(shown, lambda p: F.when(inside(p), F.lit("1")).otherwise(F.lit("0"))), "")


def shown_row(patterns: DataFrame, masks: list[str]) -> DataFrame:
    """The few shown patterns as one row with an array, ordered by pattern."""
    return patterns.agg(F.array_sort(F.collect_list(F.struct("pattern", *masks))).alias("shown")).withColumn("_one", F.lit(1))


def joint_entropy(patterns: DataFrame, ds: EncodedDataset, normalise: bool = False) -> DataFrame:
    """One row ``(k, entropy)`` in bits: spread of the transactions' signatures.

    Signatures are counted before the shuffle, so it moves at most 2^k rows a task.
    """
    few = F.broadcast(shown_row(patterns, ds.masks))
    signed = ds.transactions.withColumn("_one", F.lit(1)).join(few, "_one").select(F.size("shown").alias("k"), signature(F.col("shown"), ds.masks).alias("s"))
    counts = signed.groupBy("k", "s").agg(F.count(F.lit(1)).alias("n"))
    share = F.col("n") / F.lit(float(ds.n))
    bits_ = F.sum(-share * F.log2(share))
    return counts.groupBy("k").agg((bits_ / F.first("k") if normalise else bits_).alias("entropy"))


def query_entropy(queries: DataFrame, patterns: DataFrame, ds: EncodedDataset) -> DataFrame:
    """``(session_id, iter, entropy, entropy_share)`` of many queries in one pass over the
    transactions; the queries, a few patterns each, are broadcast."""
    shown = queries.join(patterns.select("pattern", *ds.masks), "pattern").groupBy("session_id", "iter").agg(F.array_sort(F.collect_list(F.struct("pattern", *ds.masks))).alias("shown"))
    signed = ds.transactions.withColumn("_one", F.lit(1)).join(F.broadcast(shown.withColumn("_one", F.lit(1))), "_one")
    counts = signed.groupBy("session_id", "iter", F.size("shown").alias("k"), signature(F.col("shown"), ds.masks).alias("s")).agg(F.count(F.lit(1)).alias("n"))
    share = F.col("n") / F.lit(float(ds.n))
    per = counts.groupBy("session_id", "iter", "k").agg(F.sum(-share * F.log2(share)).alias("entropy"))
    return per.select("session_id", "iter", "entropy", (F.col("entropy") / F.col("k")).alias("entropy_share"))


def regret(series: DataFrame) -> DataFrame:
    """Adds ``regret`` and its running sum to ``(session_id, measure, iter, value)``."""
    up_to = Window.partitionBy("session_id", "measure").orderBy("iter").rowsBetween(Window.unboundedPreceding, 0)
    return series.withColumn("regret", 1 - F.col("value")).withColumn("cumulative", F.sum(1 - F.col("value")).over(up_to))


def agreement(patterns: DataFrame, learned: str, hidden: str) -> DataFrame:
    """One row: Pearson correlation of the values and of their average ranks."""

    def ranked(column: str) -> DataFrame:
        ranked = running_counts(patterns.groupBy(column).agg(F.count(F.lit(1)).alias("n")).persist(), column, "n")
        return ranked.select(column, (F.col("_before") + (F.col("n") + 1) / 2).alias(f"{column}_rank"))

    both = patterns.select(learned, hidden).join(ranked(learned), learned).join(ranked(hidden), hidden)
    return both.agg(F.corr(learned, hidden).alias("pearson"), F.corr(f"{learned}_rank", f"{hidden}_rank").alias("spearman"))


def five_numbers(patterns: DataFrame, column: str, exact: bool = True) -> DataFrame:
    points = [0.0, 0.25, 0.5, 0.75, 1.0]
    q = F.percentile(column, F.array(*map(F.lit, points))) if exact else F.percentile_approx(column, points, 10_000)
    names = ["least", "lower", "median", "upper", "most"]
    return patterns.agg(q.alias("q")).select(*[F.get("q", F.lit(i)).alias(n) for i, n in enumerate(names)])


def dataset_stats(ds: EncodedDataset, patterns: DataFrame, min_sup: int) -> DataFrame:
    return patterns.agg(F.count(F.lit(1)).alias("patterns"), F.max("len").alias("longest")).select(F.lit(ds.name).alias("dataset"), F.lit(ds.n_items_all).alias("items"), F.lit(ds.n_items).alias("frequent_items"), F.lit(ds.n).alias("transactions"), F.lit(min_sup).alias("min_sup"), "patterns", "longest")


def effort(feedback: DataFrame) -> DataFrame:
    """``(session_id, shown, distinct_shown, pairs)``: what the user was asked."""
    per = feedback.groupBy("session_id", "iter").agg(F.count(F.lit(1)).alias("k"))
    asked = per.groupBy("session_id").agg(F.sum("k").alias("shown"), F.sum(F.col("k") * (F.col("k") - 1) / 2).cast("long").alias("pairs"))
    return asked.join(feedback.groupBy("session_id").agg(F.count_distinct("pattern").alias("distinct_shown")), "session_id")


def failures(sessions: DataFrame) -> DataFrame:
    return sessions.groupBy("method", "phi").agg(F.count(F.lit(1)).alias("sessions"), F.count_if(F.col("status") == "overflow").alias("failed"))


def jaccard_spread(patterns: DataFrame, masks: list[str]) -> DataFrame:
    """One row: mean, least and greatest Jaccard similarity of pairs of shown sets."""
    a = patterns.select(F.col("pattern").alias("p1"), *[F.col(m).alias(f"a{m}") for m in masks])
    b = patterns.select(F.col("pattern").alias("p2"), *[F.col(m).alias(f"b{m}") for m in masks])
    pairs = a.join(F.broadcast(b), F.col("p1") < F.col("p2"))
    j = bits.jaccard([F.col(f"a{m}") for m in masks], [F.col(f"b{m}") for m in masks])
    return pairs.select(j.alias("j")).agg(F.avg("j").alias("mean"), F.min("j").alias("least"), F.max("j").alias("most"))


def total_variation(draws: DataFrame, patterns: DataFrame, weight: str = "w") -> DataFrame:
    """Half the summed distance of drawn shares from weight shares; one row."""
    n = draws.agg(F.count(F.lit(1)).alias("n"))
    total = patterns.agg(F.sum(weight).alias("total"))
    shares = draws.groupBy("pattern").agg(F.count(F.lit(1)).alias("c"))
    both = patterns.select("pattern", weight).join(shares, "pattern", "full").withColumn("_one", F.lit(1))
    both = both.join(F.broadcast(n.withColumn("_one", F.lit(1))), "_one").join(F.broadcast(total.withColumn("_one", F.lit(1))), "_one")
    gap = F.abs(F.coalesce(F.col("c"), F.lit(0)) / F.col("n") - F.coalesce(F.col(weight), F.lit(0.0)) / F.col("total"))
    return both.agg((F.sum(gap) / 2).alias("total_variation"))


def item_gram(patterns: DataFrame) -> DataFrame:
    """``(i, j, n)``: patterns with both items; its size is the items squared."""
    one = patterns.select(F.explode("items").alias("i"), "items").select("i", F.explode("items").alias("j"))
    return one.where("i <= j").groupBy("i", "j").agg(F.count(F.lit(1)).alias("n"))


def principal_axes(patterns: DataFrame, n_items: int, k: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """Mean and first axes of the patterns' item vectors, from the item counts alone."""
    total = patterns.count()
    gram = np.zeros((n_items, n_items))
    for r in item_gram(patterns).collect():  # items squared at most
        gram[r.i, r.j] = gram[r.j, r.i] = r.n
    mean = np.diag(gram) / total
    values, vectors = np.linalg.eigh(gram / total - np.outer(mean, mean))
    axes = vectors[:, np.argsort(values)[::-1][:k]].T
    flip = np.sign(axes[np.arange(len(axes)), np.abs(axes).argmax(axis=1)])
    return mean, axes * flip[:, None]


def item_pca(patterns: DataFrame, n_items: int, k: int = 2, keep: float = 0.01, seed=0) -> DataFrame:
    """A kept share of the patterns with their coordinates ``pc1 ..``."""
    mean, axes = principal_axes(patterns, n_items, k)
    kept = patterns.where(u01(F.lit(seed), F.lit("keep"), F.col("pattern")) <= keep)
    for a in range(k):
        kept = kept.withColumn(f"pc{a + 1}", along(axes[a]) - float(mean @ axes[a]))
    return kept


def along(axis: np.ndarray) -> Column:
    """A pattern's coordinate on an axis of the item space."""
    known = F.array(*[F.lit(float(x)) for x in axis])
    return F.aggregate("items", F.lit(0.0), lambda s, i: s + F.get(known, i))
