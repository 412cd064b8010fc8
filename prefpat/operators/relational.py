"""Joins and windows around the methods: as-of, range, semi and anti, session logs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_of(events: DataFrame, states: DataFrame, on: list[str], event_time: str, state_time: str) -> DataFrame:
    """Each event with the last state of its key at or before it (null if there is none).

    Both sides are united and sorted once within the key; no pair of an event with
    an earlier state other than the last is ever made.
    """
    carried = [c for c in states.columns if c not in (*on, state_time)]
    left = events.select(F.struct(*events.columns).alias("_event"), *on, F.col(event_time).alias("_t"), F.lit(1).alias("_kind"), F.lit(None).cast(states.select(F.struct(*carried, state_time).alias("s")).schema["s"].dataType).alias("_state"))
    right = states.select(F.lit(None).cast(left.schema["_event"].dataType).alias("_event"), *on, F.col(state_time).alias("_t"), F.lit(0).alias("_kind"), F.struct(*carried, state_time).alias("_state"))
    before = Window.partitionBy(*on).orderBy("_t", "_kind").rowsBetween(Window.unboundedPreceding, 0)
    both = left.unionByName(right).withColumn("_last", F.last("_state", ignorenulls=True).over(before))
    return both.where("_kind = 1").select("_event.*", *[F.col("_last")[c].alias(c) for c in (*carried, state_time)])


def numbered_rows(df: DataFrame, order: str, name: str = "row") -> DataFrame:
    """Rows numbered from 0 without gaps in the order of a column of distinct values.

    Ranges of the order are sorted side by side and counted; a range's first number
    comes from the counts of those before it, one row for each range. The ranges are
    kept, so that the counts are those of the rows that are numbered.
    """
    ranged = df.repartitionByRange(order).sortWithinPartitions(order).select("*", F.spark_partition_id().alias("_range"), F.monotonically_increasing_id().alias("_id")).persist()
    before = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    firsts = ranged.groupBy("_range").agg(F.count(F.lit(1)).alias("_n"), F.min("_id").alias("_least")).select("_range", "_least", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    return ranged.join(F.broadcast(firsts), "_range").select(*df.columns, (F.col("_before") + F.col("_id") - F.col("_least")).alias(name))


def running_counts(counts: DataFrame, column: str, n: str) -> DataFrame:
    """Adds ``_before``, the sum of ``n`` over all lesser values, and ``_all``, over all.

    ``column`` holds distinct numbers. Quantiles cut them into ranges, one for each
    shuffle partition; sums run inside a range and start from the ranges before it, so
    no task sees all values, however many there are.
    """
    parts = int(counts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    cuts = sorted(set(counts.approxQuantile(column, [i / parts for i in range(1, parts)], 0.25 / parts))) if parts > 1 else []
    known = F.array(*[F.lit(float(c)) for c in cuts]) if cuts else F.array().cast("array<double>")
    ranged = counts.withColumn("_range", F.size(F.filter(known, lambda c: c < F.col(column))))
    earlier = Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    sums = ranged.groupBy("_range").agg(F.sum(n).alias("_sum"))
    sums = sums.select("_range", F.coalesce(F.sum("_sum").over(earlier), F.lit(0)).alias("_first"), F.sum("_sum").over(Window.partitionBy()).alias("_all"))
    inside = Window.partitionBy("_range").orderBy(column).rowsBetween(Window.unboundedPreceding, -1)
    joined = ranged.withColumn("_inside", F.coalesce(F.sum(n).over(inside), F.lit(0))).join(F.broadcast(sums), "_range")
    return joined.select(*counts.columns, (F.col("_first") + F.col("_inside")).alias("_before"), "_all")


def range_bins(df: DataFrame, value: Column, edges: DataFrame, width: float) -> DataFrame:
    """Rows with the bin ``(bin, lo, hi)`` that holds their value: lo <= v < hi.

    Edges are cut into cells of ``width`` and joined by cell, so it is an equi-join
    however many edges there are.
    """
    cells = edges.withColumn("_cell", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor((F.col("hi") - 1e-12) / width))))
    keyed = df.withColumn("_v", value).withColumn("_cell", F.floor(F.col("_v") / width))
    return keyed.join(cells, "_cell").where((F.col("_v") >= F.col("lo")) & (F.col("_v") < F.col("hi"))).drop("_cell", "_v")


def unseen(patterns: DataFrame, shown: DataFrame) -> DataFrame:
    """Patterns that have not been shown."""
    return patterns.join(shown.select("pattern").distinct(), "pattern", "left_anti")


def seen(patterns: DataFrame, shown: DataFrame) -> DataFrame:
    return patterns.join(shown.select("pattern").distinct(), "pattern", "left_semi")


def retained(ordered: DataFrame, keep: int) -> DataFrame:
    """The best of every session's last ordered query."""
    last = Window.partitionBy("session_id")
    return ordered.withColumn("_last", F.max("iter").over(last)).where((F.col("iter") == F.col("_last")) & (F.col("pos") <= keep)).drop("_last")
