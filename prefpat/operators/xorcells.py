"""Random parity cells of the pattern space.

A parity constraint asks for an even or odd number of some random items. ``m`` of
them cut the patterns into 2^m cells; random coefficients pick one. All draws are
listed in one pass over the patterns: a pattern is labelled with how many of a
draw's constraints, from the first on, it meets, which gives the nested cells of
every m at once.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from prefpat.functions import bits
from prefpat.functions.rng import u32, u32_py


@dataclass(frozen=True)
class CellBounds:
    """Accepted cell weights, in units of the largest weight, for a tolerance."""

    kappa: float = 0.9

    def __post_init__(self):
        if not 0 < self.kappa < 1:
            raise ValueError("the tolerance lies between 0 and 1")

    @property
    def pivot(self) -> int:
        return math.ceil(4.03 * (1 + 1 / self.kappa) ** 2)

    @property
    def low(self) -> float:
        return self.pivot / (1 + self.kappa)

    @property
    def high(self) -> float:
        return 1 + (1 + self.kappa) * self.pivot


def estimate_m(total: float, w_max: float, bounds: CellBounds) -> tuple[int, int]:
    """First and last number of constraints to try, from the total and largest weight."""
    if total <= 0 or w_max <= 0 or total / w_max <= bounds.high:
        return 0, 0
    guess = math.log2(total / w_max / bounds.pivot) + math.log2(1.8)
    return max(0, math.floor(guess) - 3), max(1, math.ceil(guess) + 4)


def draw_py(m: int, n_items: int, draws: range, seed) -> list[list[tuple[list[int], int]]]:
    """For each draw its constraints: coefficient words and parity bit."""
    out = []
    for d in draws:
        constraints = []
        for x in range(m):
            words = [0] * bits.words_for(n_items)
            for i in range(n_items):
                if u32_py(seed, d, x, i) % 2:
                    words[i // bits.WORD] |= 1 << (i % bits.WORD)
            constraints.append(([bits.signed(w) for w in words], u32_py(seed, d, x, "parity") % 2))
        out.append(constraints)
    return out


def draw(spark: SparkSession, m: int, n_items: int, n_draws: int, seed) -> DataFrame:
    """``(draw_id, xors)``: the same constraints as ``draw_py``, made by Spark."""
    words = bits.words_for(n_items)
    cells = spark.range(n_draws * m * n_items).select((F.col("id") / (m * n_items)).cast("int").alias("draw_id"), (F.col("id") / n_items).cast("int").alias("x"), (F.col("id") % n_items).cast("int").alias("item_id"))
    cells = cells.withColumn("x", F.col("x") % m)
    used = cells.withColumn("item", F.when(u32(F.lit(seed), F.col("draw_id"), F.col("x"), F.col("item_id")) % 2 == 1, F.col("item_id")))
    rows = used.groupBy("draw_id", "x").agg(*[c.alias(f"c{w}") for w, c in enumerate(bits.pack_item(F.col("item"), words))])
    parity = (u32(F.lit(seed), F.col("draw_id"), F.col("x"), F.lit("parity")) % 2).cast("int")
    one = F.struct("x", *[f"c{w}" for w in range(words)], parity.alias("parity"))
    return rows.groupBy("draw_id").agg(F.array_sort(F.collect_list(one)).alias("xors"))


def draws_frame(spark: SparkSession, drawn: list[list[tuple[list[int], int]]], words: int, first: int = 0) -> DataFrame:
    inner = "x: int, " + ", ".join(f"c{w}: bigint" for w in range(words)) + ", parity: int"
    rows = [(first + d, [(x, *c, p) for x, (c, p) in enumerate(constraints)]) for d, constraints in enumerate(drawn)]
    return spark.createDataFrame(rows, f"draw_id int, xors array<struct<{inner}>>")


def meets(masks: list[str], xor: Column) -> Column:
    return bits.parity([F.col(m) for m in masks], [xor[f"c{w}"] for w in range(len(masks))]) == xor["parity"]


def in_cell(masks: list[str], xors: Column) -> Column:
    return F.forall(xors, lambda x: meets(masks, x))


def cell_id(masks: list[str], xors: Column) -> Column:
    """The parities of all constraints as one number: which of the 2^m cells."""
    parity = lambda x: bits.parity([F.col(m) for m in masks], [x[f"c{w}"] for w in range(len(masks))])
    return F.aggregate(xors, F.lit(0).cast("long"), lambda a, x: a * 2 + parity(x))


def matched(masks: list[str], xors: Column) -> Column:
    """How many constraints, from the first on, are met before one is not."""
    start = F.struct(F.lit(0).alias("n"), F.lit(True).alias("on"))
    step = lambda s, x: F.struct((s["n"] + (s["on"] & meets(masks, x)).cast("int")).alias("n"), (s["on"] & meets(masks, x)).alias("on"))
    return F.aggregate(xors, start, step, lambda s: s["n"])


def enumerate_cells(patterns: DataFrame, draws: DataFrame, masks: list[str], at_least: int | None = None) -> DataFrame:
    """Every pattern in every draw's cell: ``draw_id``, ``matched`` and the pattern's
    columns. Draws are few (their number is a parameter) and broadcast.

    ``at_least`` keeps the nested cells from that many constraints on; otherwise all
    constraints hold.
    """
    sent = F.broadcast(draws.withColumn("_one", F.lit(1)))
    joined = patterns.withColumn("_one", F.lit(1)).join(sent, "_one").drop("_one")
    if at_least is None:
        return joined.where(in_cell(masks, F.col("xors"))).withColumn("matched", F.size("xors")).drop("xors")
    need = F.forall(F.slice("xors", 1, at_least), lambda x: meets(masks, x)) if at_least else F.lit(True)
    return joined.where(need).withColumn("matched", matched(masks, F.col("xors"))).drop("xors")


def cell_weights(cells: DataFrame) -> DataFrame:
    """``(draw_id, m, weight, size)`` of nested cells: a row of matched n is in all m <= n."""
    per = cells.groupBy("draw_id", "matched").agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n"))
    each = per.select("draw_id", F.explode(F.sequence(F.lit(0), F.col("matched"))).alias("m"), "w", "n")
    return each.groupBy("draw_id", "m").agg(F.sum("w").alias("weight"), F.sum("n").alias("size"))


def accept(weights: DataFrame, w_max: float, bounds: CellBounds) -> DataFrame:
    """``(draw_id, m)``: the first number of constraints whose cell weight is accepted."""
    unit = F.col("weight") / F.lit(w_max)
    return weights.where((unit >= bounds.low) & (unit <= bounds.high)).groupBy("draw_id").agg(F.min("m").alias("m"))


def approx_total(cells: DataFrame, n_draws: int) -> DataFrame:
    """Median over draws of cell weight times the number of cells; one row."""
    per = cells.groupBy("draw_id").agg((F.sum("w") * F.pow(F.lit(2.0), F.max("matched"))).alias("total"))
    spark = cells.sparkSession
    return spark.range(n_draws).select(F.col("id").cast("int").alias("draw_id")).join(per, "draw_id", "left").agg(F.percentile(F.coalesce("total", F.lit(0.0)), 0.5).alias("total"))
