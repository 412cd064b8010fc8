"""Hierarchical best-fit packing of token sequences.

A text's ids and a closing separator make an item; only items over the capacity
are cut, into pieces that fill a sequence and a rest. A hash deals the items of all
tasks to pools, so that long and short ones mix whatever their order, and every
pool packs its items by best fit, largest first: an item goes where it leaves least
room. Bins that are nearly full are emitted. All others go up as items of their
own: a hash of the bin deals them to pools again. Rounds go on until one pool takes
all that is left or the number of underfull bins no longer falls. A pool holds about
``POOL_ITEMS`` pieces, ``FIRST_ITEMS`` in the first round, however large the input.
Every round is cut by a checkpoint.

Defined cases: a null or empty text is one separator; a null key is carried
along; repeated rows are items of their own; an empty table gives no rows. Only
key and text are read, so other columns, whatever their names, play no part.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from itertools import count

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefpat.llm.bpe import DEFAULT_VOCABULARY, library_vocabulary, little_endian
from prefpat.llm.common import cut, read_table, shuffle_parts

CAPACITY = 2048
SEPARATOR = 0
POOL_ITEMS = 1 << 16
FIRST_ITEMS = 1 << 13
#: Levels that a sequence number has room for.
LEVELS = 32
#: A bin with at most this share of its capacity left is nearly full.
SLACK = 1 / 256
#: A bin that is fuller than this stays whole on its way up.
WHOLE = 7 / 8
FIELDS = ["piece", "start", "length", "ids_crc32", "level", "pool", "bin", "place", "done"]
FIELD_TYPES = "piece int, start long, length long, ids_crc32 long, level int, pool long, bin long, place long, done boolean"
ARROW_TYPES = [pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.bool_()]


def best_fit(lengths: list[int], capacity: int) -> list[list[int]]:
    """Bins as lists of item numbers: largest item first, least room that fits.

    Open bins are stacked by the room that they have; bit r of an integer tells
    whether there is a bin with room r, so the best one is the lowest bit from the
    item's length on.
    """
    bins: list[list[int]] = []
    stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
    rooms = 0
    for item in sorted(range(len(lengths)), key=lengths.__getitem__, reverse=True):
        length = lengths[item]
        fitting = rooms >> length
        if fitting:
            room = length + (fitting & -fitting).bit_length() - 1
            chosen = stacks[room].pop()
            if not stacks[room]:
                rooms ^= 1 << room
            bins[chosen].append(item)
        else:
            room, chosen = capacity, len(bins)
            bins.append([item])
        if left := room - length:
            stacks[left].append(chosen)
            rooms |= 1 << left
    return bins


def packed(items: list[list[tuple]], level: int, pool: int, capacity: int, last: bool) -> Iterator[tuple]:
    """Rows of a pool's bins. An item is a list of pieces (key, piece, start, length,
    crc) that stay together."""
    lengths = [sum(p[3] for p in item) for item in items]
    bins = best_fit(lengths, capacity)
    room = [capacity - sum(lengths[i] for i in b) for b in bins]
    for n, own in enumerate(bins):
        place = 0
        for item in own:
            for piece in items[item]:
                yield (*piece, level, pool, n, place, last or room[n] <= capacity * SLACK)
                place += piece[3]


def opened(bins: list[list[tuple]], capacity: int) -> list[list[tuple]]:
    """Underfull bins as items; the emptier ones as the pieces in them."""
    items: list[list[tuple]] = []
    for own in bins:
        items += [own] if sum(p[3] for p in own) > capacity * WHOLE else [[p] for p in own]
    return items


def to_batches(rows: Iterator[tuple], key_type: pa.DataType) -> Iterator[pa.RecordBatch]:
    held = []
    for row in rows:
        held.append(row)
        if len(held) >= 10_000:
            yield batch_of(held, key_type)
            held = []
    if held:
        yield batch_of(held, key_type)


def batch_of(rows: list[tuple], key_type: pa.DataType) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(zip(*rows), [key_type, *ARROW_TYPES])], names=["key", *FIELDS])


def pieces_of(text: str | None, path: str, capacity: int) -> Iterator[tuple]:
    """(piece, start, length, crc) of a text's ids and the separator."""
    ids = little_endian(library_vocabulary(path).encode(text)) + SEPARATOR.to_bytes(4, "little")
    for number, at in enumerate(range(0, len(ids), 4 * capacity)):
        part = ids[at : at + 4 * capacity]
        yield number, at // 4, len(part) // 4, zlib.crc32(part)


def pack_texts(path: str, capacity: int):
    """First level: arrow batches of (key, text) to pieces, each a bin of its own."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, key_type = TaskContext.get().partitionId(), pa.int64()
        bins = count()

        def rows() -> Iterator[tuple]:
            nonlocal key_type
            for batch in batches:
                key_type = batch.column(0).type
                for key, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                    for piece in pieces_of(text.as_py(), path, capacity):
                        n = next(bins)  # pools are numbers of this task's own
                        yield (key, *piece, 0, (task << 16) + (n >> 16), n % (1 << 16), 0, piece[2] == capacity)

        # rows() learns the key's type from the first batch, before its first row
        held = rows()
        first = next(held, None)
        if first is not None:
            yield batch_of([first], key_type)
            yield from to_batches(held, key_type)

    return run


def pack_bins(level: int, capacity: int, last: bool):
    """Later levels: rows of underfull bins, sorted by (pool, bin, place)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key_type = pa.int64()

        def rows() -> Iterator[tuple]:
            nonlocal key_type
            at, items, bin_ = None, [], None
            for batch in batches:
                key_type = batch.column(0).type
                columns = [c.to_pylist() for c in batch.columns]
                for key, piece, start, length, crc, _, pool, number, _, _, up in zip(*columns):
                    if up != at:
                        if items:
                            yield from packed(opened(items, capacity), level, at, capacity, last)
                        at, items, bin_ = up, [], None
                    if bin_ != (pool, number):
                        items.append([])
                        bin_ = (pool, number)
                    items[-1].append((key, piece, start, length, crc))
            if items:
                yield from packed(opened(items, capacity), level, at, capacity, last)

        held = rows()
        first = next(held, None)
        if first is not None:
            yield batch_of([first], key_type)
            yield from to_batches(held, key_type)

    return run


def left(rows: DataFrame) -> tuple[int, int]:
    """How many pieces and how many bins there are; one piece of a bin has place 0."""
    found = rows.agg(F.count(F.lit(1)), F.count(F.when(F.col("place") == 0, 1))).first()
    return found[0], found[1]


def pack(df: DataFrame, key: str, text: str, capacity: int = CAPACITY, path: str = DEFAULT_VOCABULARY) -> DataFrame:
    """``(key, piece, start, length, ids_crc32, sequence_id, offset)`` of every piece."""
    source = df.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").alias("text"))
    schema = f"key {source.schema['key'].dataType.simpleString()}, {FIELD_TYPES}"
    rows = cut(source.mapInArrow(pack_texts(path, capacity), schema))
    finished, rows, level = rows.where("done"), rows.where("not done"), 0
    pieces, bins = left(rows)
    while pieces and level + 1 < LEVELS:
        level, pools = level + 1, -(-pieces // (POOL_ITEMS if level else FIRST_ITEMS))
        up = F.pmod(F.xxhash64("pool", "bin", F.lit(level)), F.lit(pools))
        dealt = rows.withColumn("up", up).repartition(min(pools, shuffle_parts(df.sparkSession)), "up").sortWithinPartitions("up", "pool", "bin", "place")
        rows = cut(dealt.mapInArrow(pack_bins(level, capacity, pools == 1), schema))
        finished, rows, before = finished.unionByName(rows.where("done")), rows.where("not done"), bins
        pieces, bins = left(rows)
        if bins >= before:
            break
    finished = finished.unionByName(rows)
    number = F.shiftleft(F.col("level").cast("long"), 58).bitwiseOR(F.shiftleft("pool", 17)).bitwiseOR(F.col("bin"))
    return finished.select("key", "piece", "start", "length", "ids_crc32", number.alias("sequence_id"), F.col("place").alias("offset"))


def op9_packing(spark, sf_dir):
    """All documents in sequences of at most 2048 tokens."""
    return pack(read_table(spark, sf_dir, "documents"), "doc_id", "text").withColumnRenamed("key", "doc_id")
