"""Transactions as vertical bitmaps: for each item the rows that hold it.

A row's place in a bitmap means nothing beyond being the same for all items, so every
partition turns its own rows over and the pieces are joined by item. Rows are cut to
whole bytes at a partition's end. Bitmaps are whole numbers of Python: an intersection
is one ``&`` and a support one ``bit_count``.
"""

from __future__ import annotations

import itertools
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefpat.operators.encode import EncodedDataset

#: Bytes of vertical bitmaps that may be sent to every executor.
BITMAP_BYTES = 1 << 30
#: Mask words turned over at a time; they take 64 times their number in bytes.
CHUNK_WORDS = 1 << 20
#: Bitmaps of so many rows are cut to a cover's rows if it holds less than this part of them.
NARROW_BITS, NARROW_PART = 1 << 14, 4
#: Numbers of pseudo items: rows of class 1, rows of class 0.
POSITIVE, NEGATIVE = -1, -2


def turned(words: np.ndarray) -> np.ndarray:
    """Mask words (rows x W) to packed bits (items x bytes of rows)."""
    flags = np.unpackbits(np.ascontiguousarray(words).view(np.uint8).reshape(len(words), -1), axis=1, bitorder="little")
    return np.packbits(flags.T, axis=1, bitorder="little")


def rows_of(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Mask words and labels (-1 for null) of a batch ``(m0.., label)``."""
    *masks, label = batch.columns
    words = np.stack([m.to_numpy() for m in masks], axis=1).view(np.uint64)
    return words, label.fill_null(-1).to_numpy(zero_copy_only=False)


def bit_columns(words: np.ndarray, labels: np.ndarray) -> dict[int, bytes]:
    """Packed rows by item, present ones only, with the two classes as pseudo items."""
    packed = turned(words)
    own = np.flatnonzero(packed.any(axis=1))
    out = {int(i): packed[i].tobytes() for i in own}
    for name, value in ((POSITIVE, 1), (NEGATIVE, 0)):
        out[name] = np.packbits(labels == value, bitorder="little").tobytes()
    return out


@dataclass(frozen=True)
class Bitmaps:
    """Bitmaps by item, and the rows of the two classes."""

    columns: list[int]
    positive: int
    negative: int


def fits(ds: EncodedDataset) -> bool:
    return ds.n * (ds.n_items + 2) // 8 <= BITMAP_BYTES


def collect_bitmaps(ds: EncodedDataset) -> Bitmaps:
    """All bitmaps on the driver, as bytes and never as rows; their size is checked."""
    if not fits(ds):
        raise ValueError("the bitmaps are too large to be broadcast: mine in partitions instead")

    def turn(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                own = bit_columns(*rows_of(batch))
                yield pa.RecordBatch.from_arrays([pa.array(list(own), pa.int32()), pa.array([batch.num_rows] * len(own), pa.int64()), pa.array(list(own.values()), pa.binary())], names=["item", "rows", "bits"])

    pieces = ds.transactions.select(*ds.masks, "label").mapInArrow(turn, "item int, rows long, bits binary")
    numbered = pieces.withColumn("piece", F.monotonically_increasing_id())
    found = numbered.toArrow().sort_by("piece")
    columns: dict[int, list[bytes]] = {i: [] for i in range(NEGATIVE, ds.n_items)}
    before, at = 0, {i: 0 for i in columns}
    for item, rows, own in zip(found["item"].to_pylist(), found["rows"].to_pylist(), found["bits"]):
        data = own.as_py()
        columns[item].append(bytes(before - at[item]) + data)
        at[item] = before + len(data)
        if item == NEGATIVE:  # the last of a batch
            before += len(data)
    number = lambda i: int.from_bytes(b"".join(columns[i]), "little")
    return Bitmaps([number(i) for i in range(ds.n_items)], number(POSITIVE), number(NEGATIVE))


def sent_bitmaps(ds: EncodedDataset):
    """The broadcast bitmaps of a dataset, collected once for its transactions."""
    held = ds.__dict__.get("_sent")
    if held is None or held[0] is not ds.transactions:
        held = ds.__dict__["_sent"] = (ds.transactions, ds.items.sparkSession.sparkContext.broadcast(collect_bitmaps(ds)))
    return held[1]


def narrowed(cover: int, bitmaps: list[int]) -> list[int]:
    """Bitmaps cut to the rows of a cover that holds them all, in the rows' order."""
    size = -(-cover.bit_length() // 8)
    as_bytes = lambda b: np.frombuffer(b.to_bytes(size, "little"), np.uint8)
    rows = np.flatnonzero(np.unpackbits(as_bytes(cover), bitorder="little"))
    at, bit = rows >> 3, (rows & 7).astype(np.uint8)
    return [int.from_bytes(np.packbits(as_bytes(b)[at] >> bit & 1, bitorder="little").tobytes(), "little") for b in bitmaps]


def below(bitmaps: Bitmaps, head: tuple[int, ...], cover: int, least: int, max_len: int | None) -> Iterator[tuple[tuple[int, ...], int, int]]:
    """Frequent sets that go on from ``head`` with larger items, depth first, with their
    supports and those in class 1. Below a set that few of the rows hold, the search goes
    on with bitmaps of these rows alone, so its steps cost what the support does."""
    columns = bitmaps.columns
    children = [(i, b) for i in range(head[-1] + 1, len(columns)) if (b := cover & columns[i]).bit_count() >= least] if not max_len or len(head) < max_len else []
    stack = [(head, cover, children, cover & bitmaps.positive, cover.bit_length())]
    while stack:
        head, cover, children, positive, width = stack.pop()
        if len(children) > 1 and width >= NARROW_BITS and (sup := cover.bit_count()) * NARROW_PART < width:
            *cut, positive = narrowed(cover, [*(b for _, b in children), positive])
            children, width = [(i, b) for (i, _), b in zip(children, cut)], sup
        for at, (item, cover) in enumerate(children):
            own = (*head, item)
            yield own, cover.bit_count(), (cover & positive).bit_count()
            if not max_len or len(own) < max_len:
                further = [(i, b) for i, c in children[at + 1 :] if (b := cover & c).bit_count() >= least]
                if further:
                    stack.append((own, cover, further, cover & positive, width))


def pair_tasks(ds: EncodedDataset) -> tuple[DataFrame, int]:
    """Numbers of the tasks, a row and partition each, and how many they are."""
    spark = ds.items.sparkSession
    parts = max(1, min(ds.n_items, 4 * spark.sparkContext.defaultParallelism))
    return spark.range(0, parts, 1, parts), parts


def own_pairs(task: int, parts: int, n_items: int) -> Iterator[tuple[int, int]]:
    """A task's two-item prefixes; ``(i, i)`` stands for the single item. Neighbours go to
    different tasks, and another one begins with each item."""
    for i in range(n_items):
        for j in range(i + (task - 7 * i) % parts, n_items, parts):
            yield i, j


def search_all(ds: EncodedDataset, least: int, max_len: int | None = None) -> DataFrame:
    """``(items, sup, sup_pos)`` of all frequent sets: tasks search below two-item
    prefixes on broadcast bitmaps. The length bounds the search itself."""
    sent, n_items = sent_bitmaps(ds), ds.n_items
    tasks, parts = pair_tasks(ds)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bitmaps = sent.value
        columns, positive = bitmaps.columns, bitmaps.positive

        def sets() -> Iterator[tuple[tuple[int, ...], int, int]]:
            for batch in batches:
                for i, j in itertools.chain.from_iterable(own_pairs(t, parts, n_items) for t in batch.column(0).to_pylist()):
                    cover = columns[i] & columns[j]
                    sup = cover.bit_count()
                    if sup < least:
                        continue
                    if i == j:
                        yield (i,), sup, (cover & positive).bit_count()
                    elif not max_len or max_len > 1:
                        yield (i, j), sup, (cover & positive).bit_count()
                        yield from below(bitmaps, (i, j), cover, least, max_len)

        held: list[tuple] = []
        for found in sets():
            held.append(found)
            if len(held) == 10_000:
                yield set_batch(held)
                held = []
        if held:
            yield set_batch(held)

    return tasks.mapInArrow(run, "items array<int>, sup long, sup_pos long")


def set_batch(rows: list[tuple]) -> pa.RecordBatch:
    items, sup, pos = zip(*rows)
    return pa.RecordBatch.from_arrays([pa.array([list(i) for i in items], pa.list_(pa.int32())), pa.array(sup, pa.int64()), pa.array(pos, pa.int64())], names=["items", "sup", "sup_pos"])


class Tally:
    """How many sets have which support, from a floor on that rises as they get too many.

    Over twice ``most`` sets the floor goes up to where ``most`` are left at most, so the
    work is bounded however low the search begins. Whatever has a support of the last
    floor or more is counted: all its subsets have, so none was ever left out.
    """

    def __init__(self, least: int, most: int):
        self.floor, self.most, self.seen, self.counts = least, most, 0, {}

    def add(self, sup: int) -> None:
        self.counts[sup] = self.counts.get(sup, 0) + 1
        self.seen += 1
        if self.seen > 2 * self.most:
            kept, self.seen = {}, 0
            for s in sorted(self.counts, reverse=True):
                if self.seen + self.counts[s] > self.most:
                    self.floor = s + 1
                    break
                kept[s] = self.counts[s]
                self.seen += kept[s]
            self.counts = kept

    def search(self, columns: list[int], pairs: Iterable[tuple[int, int]]) -> None:
        """Counts the pairs and all that goes on from them with larger items."""
        for i, j in pairs:
            cover = columns[i] & columns[j]
            if (sup := cover.bit_count()) >= self.floor:
                self.add(sup)
                if i != j:
                    self.below(cover, sup, columns, j + 1)

    def below(self, cover: int, sup: int, columns: list[int], first: int) -> None:
        stack = [(cover, sup, columns, first, cover.bit_length())]
        while stack:
            cover, sup, columns, first, width = stack.pop()
            if sup < self.floor:
                continue
            children = []
            for c in columns[first:]:
                if (s := (b := cover & c).bit_count()) >= self.floor:
                    children.append((b, s))
                    self.add(s)
            bitmaps = [b for b, _ in children]
            if len(children) > 1 and width >= NARROW_BITS and sup * NARROW_PART < width:
                bitmaps, width = narrowed(cover, bitmaps), sup
            for at, (_, s) in enumerate(children[:-1]):
                stack.append((bitmaps[at], s, bitmaps, at + 1, width))


def count_by_support(ds: EncodedDataset, sent, least: int, most: int) -> tuple[int, dict[int, int]]:
    """How many sets have which support, and the least support from which on all are
    counted: ``least``, or more if a task alone has over ``most`` sets above it.

    ``sent`` are broadcast bitmaps.
    """
    n_items = ds.n_items
    tasks, parts = pair_tasks(ds)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for task in batch.column(0).to_pylist():
                tally = Tally(least, most)
                tally.search(sent.value.columns, own_pairs(task, parts, n_items))
                counts = tally.counts | {-1: tally.floor}
                yield pa.RecordBatch.from_arrays([pa.array(list(counts), pa.int64()), pa.array(list(counts.values()), pa.int64())], names=["sup", "n"])

    rows = tasks.mapInArrow(run, "sup long, n long").groupBy("sup").agg(F.sum("n").alias("n"), F.max("n").alias("most")).collect()  # at most one for each support
    floor = max([least, *(r["most"] for r in rows if r["sup"] < 0)])
    return floor, {r["sup"]: r["n"] for r in rows if r["sup"] >= floor}


def count_given(sets: list[tuple[int, ...]], columns: dict[int, int], positive: int, negative: int) -> tuple[list[int], list[int], list[int]]:
    """Supports of given sets, in lexicographic order: a set starts from the cover of
    what it shares with the one before, so most cost one intersection."""
    sup, pos, neg = [], [], []
    covers: list[int] = []
    last: tuple[int, ...] = ()
    for items in sets:
        same = 0
        while same < len(last) and same < len(items) and last[same] == items[same]:
            same += 1
        del covers[same:]
        for i in items[same:]:
            own = columns.get(i, 0)
            covers.append(covers[-1] & own if covers else own)
        cover, last = covers[-1], items
        sup.append(cover.bit_count())
        pos.append((cover & positive).bit_count())
        neg.append((cover & negative).bit_count())
    return sup, pos, neg


def count_partitions(ds: EncodedDataset, patterns: list[str], sets: list[tuple[int, ...]]) -> DataFrame:
    """``(pattern, sup, sup_pos, sup_neg)`` of broadcast sets: every task counts them in
    its own rows, chunk by chunk, and gives its sums once. No pair of a pattern with a
    transaction is ever made. Sets come sorted; none may be empty."""
    rows_per_chunk = max(1 << 12, CHUNK_WORDS // ds.words)
    sent = ds.items.sparkSession.sparkContext.broadcast((patterns, sets))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, own_sets = sent.value
        totals = np.zeros((3, len(own_sets)), np.int64)

        def add(held: list[tuple[np.ndarray, np.ndarray]]) -> None:
            words, labels = (np.concatenate(x) for x in zip(*held))
            packed = {i: int.from_bytes(b, "little") for i, b in bit_columns(words, labels).items()}
            totals[:] += np.array(count_given(own_sets, packed, packed[POSITIVE], packed[NEGATIVE]), np.int64)

        held, rows = [], 0
        for batch in batches:
            held.append(rows_of(batch))
            rows += batch.num_rows
            if rows >= rows_per_chunk:
                add(held)
                held, rows = [], 0
        if rows:
            add(held)
        hit = np.flatnonzero(totals[0])
        for a in range(0, len(hit), 10_000):
            part = hit[a : a + 10_000]
            yield pa.RecordBatch.from_arrays([pa.array([names[i] for i in part.tolist()], pa.string()), *(pa.array(t[part]) for t in totals)], names=["pattern", "sup", "sup_pos", "sup_neg"])

    partial = ds.transactions.select(*ds.masks, "label").mapInArrow(run, "pattern string, sup long, sup_pos long, sup_neg long")
    return partial.groupBy("pattern").agg(*[F.sum(c).alias(c) for c in ("sup", "sup_pos", "sup_neg")])


def masks_of_rows(words: np.ndarray) -> list[int]:
    """Whole masks of rows of mask words."""
    return [int.from_bytes(r.tobytes(), "little") for r in np.ascontiguousarray(words)]


