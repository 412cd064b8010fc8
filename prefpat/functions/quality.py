"""Pattern qualities: the hidden measures of emulated users, and percentiles.

All take the columns of ``patterns`` (``sup``, ``sup_pos``, ``items``).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.operators.encode import EncodedDataset
from prefpat.operators.relational import running_counts


def frequency(n: int) -> Column:
    return F.col("sup") / F.lit(float(n))


def log_item_frequency(ds: EncodedDataset) -> DataFrame:
    """``(item_id, log_f)``: logarithms of the items' frequencies."""
    return ds.items.select("item_id", F.ln(F.col("support") / F.lit(float(ds.n))).alias("log_f"))


def with_surprisingness(patterns: DataFrame, ds: EncodedDataset) -> DataFrame:
    """Frequency less what independent items would give, not below 0.

    The items' log frequencies are one small array, sent along as a row of data.
    """
    logs = F.broadcast(log_item_frequency(ds).agg(F.transform(F.array_sort(F.collect_list(F.struct("item_id", "log_f"))), lambda s: s["log_f"]).alias("_logs")).withColumn("_one", F.lit(1)))
    expected = F.exp(F.aggregate("items", F.lit(0.0), lambda a, i: a + F.get("_logs", i)))
    joined = patterns.withColumn("_one", F.lit(1)).join(logs, "_one")
    return joined.withColumn("surprisingness", F.greatest(frequency(ds.n) - expected, F.lit(0.0))).drop("_logs", "_one")


def chi2(n: int, n_pos: int, reading: str = "pearson") -> Column:
    """Discrimination of the classes by occurrence.

    ``pearson`` is the 2x2 statistic: the support times the squared difference of
    each class's share inside the cover and in the data, by the latter, and the
    same for the transactions outside. ``literal`` puts plain counts where a formula
    in counts and class sizes would have them, for comparison.
    """
    sup, pos = F.col("sup").cast("double"), F.col("sup_pos").cast("double")
    if reading == "literal":
        terms = [(pos - n_pos) ** 2 / float(max(n_pos, 1)), (sup - pos - (n - n_pos)) ** 2 / float(max(n - n_pos, 1))]
        return terms[0] + terms[1]
    n_neg, neg = n - n_pos, sup - pos
    a, b, c, d = pos, neg, n_pos - pos, n_neg - neg
    bottom = (a + b) * (c + d) * float(n_pos) * float(n_neg)
    return F.when(bottom == 0, F.lit(0.0)).otherwise(float(n) * (a * d - b * c) ** 2 / bottom)


def with_quality(patterns: DataFrame, ds: EncodedDataset, name: str, column: str = "phi") -> DataFrame:
    if name == "frequency":
        return patterns.withColumn(column, frequency(ds.n))
    if name == "chi2":
        return patterns.withColumn(column, chi2(ds.n_labelled, ds.n_pos))
    if name == "surprisingness":
        return with_surprisingness(patterns, ds).withColumnRenamed("surprisingness", column)
    raise ValueError(name)


def with_percentile(patterns: DataFrame, column: str = "phi", kind: str = "cume_dist") -> DataFrame:
    """Share of patterns that are not better; the best one has 1.

    Patterns are counted by distinct value first, and the counts are summed in ranges
    of values, so neither patterns nor values meet in one place.
    """
    ranked = running_counts(patterns.groupBy(column).agg(F.count(F.lit(1)).alias("_n")).persist(), column, "_n")
    if kind == "percent_rank":
        share = F.when(F.col("_all") > 1, F.col("_before") / (F.col("_all") - 1)).otherwise(0.0)
    else:
        share = (F.col("_before") + F.col("_n")) / F.col("_all")
    return patterns.join(ranked.select(column, share.alias("pct")), column)
