"""Cells without a pattern table: frequent patterns of one cell, found by search.

Constraints are eliminated so that each has a last item of its own, as early as can
be. A depth-first search over frequent prefixes drops a prefix as soon as a decided
constraint (no item left that could change it) fails. First items are dealt out to
tasks; the vertical bitmaps are broadcast, their size is checked.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefpat.functions import bits
from prefpat.operators.encode import EncodedDataset
from prefpat.operators.mine import as_patterns

#: Bytes of vertical bitmaps that may be sent to every executor.
BITMAP_BYTES = 1 << 30


def eliminated(constraints: list[tuple[int, int]]) -> list[tuple[int, int]] | None:
    """Constraints (item mask, parity) with distinct highest items; None if they contradict."""
    done: list[tuple[int, int]] = []
    for mask, parity in constraints:
        for m, p in done:
            if mask.bit_length() == m.bit_length():
                mask, parity = mask ^ m, parity ^ p
        while mask and any(mask.bit_length() == m.bit_length() for m, _ in done):
            m, p = next((m, p) for m, p in done if m.bit_length() == mask.bit_length())
            mask, parity = mask ^ m, parity ^ p
        if mask:
            done.append((mask, parity))
        elif parity:
            return None
    return done


def search(columns: list[int], min_sup: int, constraints: list[tuple[int, int]], first: int, n_rows: int) -> Iterator[tuple[list[int], int]]:
    """Frequent sets whose least item is ``first`` and that meet all constraints."""
    by_last: dict[int, list[tuple[int, int]]] = {}
    for mask, parity in constraints:
        by_last.setdefault(mask.bit_length() - 1, []).append((mask, parity))
    lasts = sorted(by_last)

    def decided(own: int, low: int, high: int) -> bool:
        """Do the constraints hold whose last item lies in [low, high)?"""
        return all((own & mask).bit_count() % 2 == parity for i in lasts if low <= i < high for mask, parity in by_last[i])

    n_items = len(columns)
    if columns[first].bit_count() < min_sup or not decided(1 << first, 0, first):
        return
    stack = [([first], 1 << first, columns[first])]
    while stack:
        items, own, cover = stack.pop()
        at = items[-1]
        if decided(own, at, n_items):
            yield items, cover.bit_count()
        for nxt in range(at + 1, n_items):
            below = cover & columns[nxt]
            if below.bit_count() >= min_sup:
                grown = own | 1 << nxt
                if decided(grown, at, nxt):
                    stack.append(([*items, nxt], grown, below))


def enumerate_lazy(ds: EncodedDataset, min_sup: int, constraints: list[tuple[list[int], int]]) -> DataFrame:
    """Patterns of one cell with their supports, never listing the others."""
    if ds.n * ds.n_items // 8 > BITMAP_BYTES:
        raise ValueError("the bitmaps are too large to be broadcast: mine in partitions instead")
    spark = ds.items.sparkSession
    rows = ds.transactions.select(*ds.masks).collect()  # within the checked size
    columns = [0] * ds.n_items
    for r, row in enumerate(rows):
        mask = sum((w & (1 << 64) - 1) << (64 * i) for i, w in enumerate(row))
        while mask:
            low = mask & -mask
            columns[low.bit_length() - 1] |= 1 << r
            mask ^= low
    plain = [(sum((w & (1 << 64) - 1) << (bits.WORD * i) for i, w in enumerate(words)), parity) for words, parity in constraints]
    ready = eliminated(plain)
    sent = spark.sparkContext.broadcast((columns, ready, len(rows)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        columns, ready, n_rows = sent.value
        for batch in batches:
            for first in batch.column(0).to_pylist():
                found = list(search(columns, min_sup, ready, first, n_rows)) if ready is not None else []
                yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in found], pa.list_(pa.int32())), pa.array([s for _, s in found], pa.int64())], names=["items", "sup"])

    found = spark.range(0, ds.n_items, 1, ds.n_items).mapInArrow(run, "items array<int>, sup long")
    return as_patterns(found, ds, ["sup"])


def approx_count(ds: EncodedDataset, min_sup: int, m: int, n_draws: int, seed) -> DataFrame:
    """Median over draws of a cell's size times the number of cells."""
    from prefpat.operators.xorcells import approx_total, draw_py

    cells = None
    for d, constraints in enumerate(draw_py(m, ds.n_items, range(n_draws), seed)):
        one = enumerate_lazy(ds, min_sup, constraints).select(F.lit(d).alias("draw_id"), F.lit(1.0).alias("w"), F.lit(m).alias("matched"))
        cells = one if cells is None else cells.unionByName(one)
    return approx_total(cells, n_draws)
