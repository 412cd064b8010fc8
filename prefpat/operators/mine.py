"""Frequent itemsets: four miners, supports, covers, and what derives from them.

A pattern row is ``(pattern, pattern_id, items, m0.., len, sup, sup_pos)``.
``pattern`` is the canonical text of the sorted item ids; it is the key and breaks
ties. ``pattern_id`` is its hash, for joins by a long.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pyarrow as pa
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.functions import bits
from prefpat.functions.lineage import cut
from prefpat.operators import vertical
from prefpat.operators.encode import EncodedDataset

#: Patterns that are broadcast against transactions at a time.
BROADCAST_PATTERNS = 200_000
#: A task of a search for supports holds at first such a part of the sets that all may find.
SHARES = 12


def canonical(items: Column) -> Column:
    return F.array_join(F.transform(F.array_sort(items), lambda i: i.cast("string")), ",")


def as_patterns(sets: DataFrame, ds: EncodedDataset, extra: list[str]) -> DataFrame:
    """Pattern rows from ``(items, ..extra)``."""
    named = sets.select(F.array_sort("items").alias("items"), *extra)
    return named.select(canonical(F.col("items")).alias("pattern"), F.xxhash64(canonical(F.col("items"))).alias("pattern_id"), "items", *bits.pack_array(F.col("items"), ds.words), F.size("items").alias("len"), *extra)


def support(patterns: DataFrame, ds: EncodedDataset) -> DataFrame:
    """``(pattern, sup, sup_pos, sup_neg)`` of given patterns that occur at all.

    Slices of at most ``BROADCAST_PATTERNS`` patterns, by hash, are sent to the
    transactions; tasks count them on bitmaps of their own rows (see ``vertical``), and
    only sums are shuffled: a row for each pattern and task.
    """
    total = patterns.count()
    slices = -(-total // BROADCAST_PATTERNS) or 1
    out = None
    for s in range(slices):
        own = patterns if slices == 1 else patterns.where(F.pmod(F.xxhash64("pattern"), F.lit(slices)) == s)
        slice_ = own.select("items", "pattern").toArrow()
        rows = sorted(zip(map(tuple, slice_["items"].to_pylist()), slice_["pattern"].to_pylist()))
        empty = [name for items, name in rows if not items]
        rows = [r for r in rows if r[0]]
        part = vertical.count_partitions(ds, [name for _, name in rows], [items for items, _ in rows])
        if empty:
            every = ds.transactions.agg(F.lit(empty[0]).alias("pattern"), F.count(F.lit(1)).alias("sup"), F.count_if(F.col("label") == 1).alias("sup_pos"), F.count_if(F.col("label") == 0).alias("sup_neg"))
            part = part.unionByName(every)
        out = part if out is None else out.unionByName(part)
    return out


def frequent_vertical(ds: EncodedDataset, min_sup: int, max_len: int | None = None) -> DataFrame:
    """Search on broadcast bitmaps, tasks by two-item prefixes; class supports come with it."""
    return as_patterns(vertical.search_all(ds, max(min_sup, 1), max_len), ds, ["sup", "sup_pos"])


def frequent_fpgrowth(ds: EncodedDataset, min_sup: int, max_len: int | None = None) -> DataFrame:
    """Spark's own miner. It knows no bound of length, so a bounded search goes to the
    two-pass miner, which does."""
    if max_len:
        return frequent_partitioned(ds, min_sup, max_len)
    model = FPGrowth(itemsCol="items", minSupport=max(min_sup - 0.5, 0.5) / max(ds.n, 1)).fit(ds.transactions.select("items"))
    return as_patterns(model.freqItemsets.where(F.col("freq") >= min_sup), ds, ["freq"]).withColumnRenamed("freq", "sup")


def subsets_frequent(candidates: DataFrame, level: DataFrame, length: int) -> DataFrame:
    """Candidates of which every subset one item smaller is in ``level``."""
    subsets = candidates.select(F.col("pattern").alias("whole"), F.explode(F.transform("items", lambda i: canonical(F.array_remove("items", i)))).alias("pattern"))
    full = subsets.join(level.select("pattern"), "pattern").groupBy("whole").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") == length + 1)
    return candidates.join(full.select(F.col("whole").alias("pattern")), "pattern", "left_semi")


def frequent_levelwise(ds: EncodedDataset, min_sup: int, max_len: int | None = None) -> DataFrame:
    """Sets of length L+1 from pairs of length L that share all but the last item, if
    all their subsets are frequent. Pairs of single items come from a join with the
    dictionary, whose size is checked (``MAX_ITEMS``)."""
    rows = ds.items.where(F.col("support") >= min_sup)
    level = cut(as_patterns(rows.select(F.array("item_id").alias("items"), F.col("support").alias("sup")), ds, ["sup"]))
    found, length = level, 1
    while not max_len or length < max_len:
        if length == 1:
            one = level.select(F.element_at("items", 1).alias("last"))
            pairs = one.join(F.broadcast(one.select(F.col("last").alias("next"))), F.col("next") > F.col("last")).select(F.array("last", "next").alias("items"))
            candidates = as_patterns(pairs, ds, [])
        else:
            keyed = level.select(canonical(F.slice("items", 1, length - 1)).alias("head"), "items", F.element_at("items", -1).alias("last"))
            right = keyed.select("head", F.col("last").alias("next"))
            pairs = keyed.join(right, "head").where("next > last").select(F.concat("items", F.array("next")).alias("items"))
            candidates = subsets_frequent(as_patterns(pairs, ds, []), level, length)
        candidates = cut(candidates)  # a level's plan names the one before four times
        counted = support(candidates, ds).where(F.col("sup") >= min_sup).select("pattern", "sup")
        level = cut(candidates.join(counted, "pattern").select(*level.columns))
        if level.isEmpty():
            return found
        found, length = found.unionByName(level), length + 1
    return found


def local_frequent(masks: list[int], min_sup: int, max_len: int | None = None) -> Iterator[tuple[tuple[int, ...], int]]:
    """Depth-first search on vertical bitmaps (one big integer for each item)."""
    columns: dict[int, int] = {}
    for row, mask in enumerate(masks):
        while mask:
            low = mask & -mask
            item = low.bit_length() - 1
            columns[item] = columns.get(item, 0) | 1 << row
            mask ^= low
    top = sorted((i, c) for i, c in columns.items() if c.bit_count() >= min_sup)
    stack = [((), top)]
    while stack:
        head, children = stack.pop()
        for at, (item, cover) in enumerate(children):
            own = (*head, item)
            yield own, cover.bit_count()
            if not max_len or len(own) < max_len:
                below = [(i, b) for i, c in children[at + 1 :] if (b := cover & c).bit_count() >= min_sup]
                if below:
                    stack.append((own, below))


def chunks_for(ds: EncodedDataset, min_sup: int, rows_per_task: int, local_least: int) -> int:
    """So many chunks that none holds much more than ``rows_per_task`` rows, and fewer
    if a chunk's share of the threshold would fall under ``local_least``: with a
    threshold of one or two a chunk would list every subset of its rows."""
    return max(1, min(-(-ds.n // rows_per_task), min_sup // local_least))


def frequent_partitioned(ds: EncodedDataset, min_sup: int, max_len: int | None = None, rows_per_task: int = 200_000, local_least: int = 32) -> DataFrame:
    """Two passes. Each chunk mines at its share of the threshold; a set that is
    frequent in all is so in some chunk, so the union misses none; then an exact
    recount drops what is not.

    Chunks are dealt by a hash of the transactions' ids, so they are alike in size
    however the input is partitioned, and there is no small remainder.
    """
    share, words = min_sup / max(ds.n, 1), ds.words
    chunks = chunks_for(ds, min_sup, rows_per_task, local_least)
    source = ds.transactions.repartition(chunks, F.xxhash64("tid")).select(*ds.masks)

    def mine(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[int] = []
        for batch in batches:
            rows += [unsigned_mask(r) for r in zip(*(c.to_pylist() for c in batch.columns))]
        # the least whole count that is no less than the chunk's share
        least, held = max(1, -int(-(share * len(rows)) // 1)), []
        for items, _ in local_frequent(rows, least, max_len):
            held.append(list(items))
            if len(held) == 10_000:
                yield pa.RecordBatch.from_arrays([pa.array(held, pa.list_(pa.int32()))], names=["items"])
                held = []
        yield pa.RecordBatch.from_arrays([pa.array(held, pa.list_(pa.int32()))], names=["items"])

    candidates = as_patterns(source.mapInArrow(mine, "items array<int>").distinct(), ds, []).persist()
    counted = support(candidates, ds).where(F.col("sup") >= min_sup)
    return candidates.join(counted, "pattern").select("pattern", "pattern_id", "items", *bits.mask_names(words), "len", "sup", "sup_pos")


def unsigned_mask(words: tuple[int, ...]) -> int:
    return sum((w & (1 << 64) - 1) << (64 * i) for i, w in enumerate(words))


ENGINES = {"vertical": frequent_vertical, "fpgrowth": frequent_fpgrowth, "levelwise": frequent_levelwise, "partitioned": frequent_partitioned}


def frequent(ds: EncodedDataset, min_sup: int, engine: str = "auto", max_len: int | None = None, include_empty: bool = False, by_class: bool = True) -> DataFrame:
    """All frequent patterns, with class supports if asked for. ``max_len`` bounds the
    search. ``auto`` searches on broadcast bitmaps if they fit, else in two passes."""
    if engine == "auto":
        engine = "vertical" if vertical.fits(ds) else "partitioned"
    found = ENGINES[engine](ds, min_sup, max_len)
    if by_class and "sup_pos" not in found.columns:
        found = found.persist()  # counted and joined: it would be mined again
        found = found.join(support(found, ds).select("pattern", "sup_pos"), "pattern") if ds.n_pos else found.withColumn("sup_pos", F.lit(0).cast("long"))
    if not by_class:
        found = found.drop("sup_pos")
    if include_empty:
        spark = ds.items.sparkSession
        empty = as_patterns(spark.createDataFrame([([], ds.n, ds.n_pos)], "items array<int>, sup long, sup_pos long"), ds, ["sup", "sup_pos"])
        found = found.unionByName(empty.select(*found.columns))
    return found


def count_frequent(ds: EncodedDataset, min_sup: int, cap: int) -> int:
    """Number of frequent patterns by FP-growth, counted no further than just over ``cap``."""
    model = FPGrowth(itemsCol="items", minSupport=max(min_sup - 0.5, 0.5) / ds.n).fit(ds.transactions.select("items"))
    return model.freqItemsets.where(F.col("freq") >= min_sup).limit(cap + 1).count()


def calibrate_min_sup(ds: EncodedDataset, target: int = 140_000, tol: float = 0.15) -> tuple[int, int]:
    """A support for about ``target`` patterns, and the number it gives.

    The bitmaps are sent once. A search tells the numbers for its own and every larger
    support, and one that begins too low for all larger supports that its tasks bear,
    so few searches are run. Where bitmaps do not fit, FP-growth counts, by bisection.
    """
    cap = int(target * (1 + tol))
    if vertical.fits(ds) and ds.n:
        return calibrate_on_bitmaps(ds, target, int(target * (1 - tol)), cap)
    low, high, best = 1, max(ds.n, 1), (max(ds.n, 1), 0)
    while low <= high:
        middle = (low + high) // 2 if low > 1 or high < ds.n else max(1, int(ds.n * 0.6))
        count = count_frequent(ds, middle, cap)
        if count <= cap and abs(count - target) < abs(best[1] - target):
            best = (middle, count)
        if count > cap:
            low = middle + 1
        elif count < target * (1 - tol):
            high = middle - 1
        else:
            return middle, count
    return best


class SupportCounts:
    """How many sets have which support, searched for as far down as is asked for.

    A search begins where somewhat over ``cap`` sets are to be expected, as further
    questions lie above. A task may hold a share of the cap, and more of it where that
    was not enough."""

    def __init__(self, ds: EncodedDataset, cap: int):
        self.ds, self.cap, self.sent = ds, cap, vertical.sent_bitmaps(ds)
        self.floor, self.counts, self.total, self.most = ds.n + 1, {}, 0, max(1, cap // SHARES)

    def below(self, sup: int) -> int:
        """Where the next search begins."""
        earlier = sum(n for s, n in self.counts.items() if s >= 1.15 * self.floor)
        if self.total * 500 < self.cap or not earlier or earlier == self.total:
            return max(1, min(self.floor - 1, sup // 4))
        growth = math.log(self.total / earlier) / math.log(1.15)
        at = int(self.floor * (self.total / (1.4 * self.cap)) ** (1 / growth))
        return max(1, min(self.floor - 1, max(at, self.floor // 4)))

    def at_least(self, sup: int) -> dict[int, int] | None:
        """The counts from a support on; None if there are over ``cap`` sets."""
        while sup < self.floor and self.total <= self.cap:
            begun = self.below(sup)
            floor, counts = vertical.count_by_support(self.ds, self.sent, begun, self.most)
            if floor < self.floor:
                self.floor, self.counts, self.total = floor, counts, sum(counts.values())
            if floor > max(begun, sup):
                if self.most >= self.cap:  # a task alone has more just below its floor
                    return None
                self.most = min(self.cap, 4 * self.most)
        found = {s: n for s, n in self.counts.items() if s >= sup}
        return found if sup >= self.floor and sum(found.values()) <= self.cap else None


def calibrate_on_bitmaps(ds: EncodedDataset, target: int, enough: int, cap: int) -> tuple[int, int]:
    """From large supports down. How fast the numbers grow at the low end of a search
    tells where the next one should end, so that hardly any passes the cap."""
    searched = SupportCounts(ds, cap)
    low, high, at, best = 1, ds.n, max(1, int(ds.n * 0.6)), (ds.n, 0)
    while low <= high:
        at = min(max(at, low), high)
        counts = searched.at_least(at)
        if counts is None:
            low = at + 1
            at = int((low * (high + 1)) ** 0.5)
            continue
        total, known = 0, []
        for sup in sorted(counts, reverse=True):
            total += counts[sup]
            known.append((sup, total))
        best = min([best, *known], key=lambda k: (abs(k[1] - target), k[0]))
        if best[1] >= enough:
            break
        high, earlier = at - 1, sum(n for sup, n in counts.items() if sup >= 1.15 * at)
        growth = math.log(total / earlier) / math.log(1.15) if earlier and total > earlier else 1.0
        at = max(at // 2, int(at * (total / target) ** (1 / growth))) if total else at // 2
    return best


def cover(patterns: DataFrame, ds: EncodedDataset) -> DataFrame:
    """``(pattern, tid)``: the transactions of given patterns."""
    from prefpat.functions.features import transaction_rows

    return transaction_rows(patterns, ds)


def top_k(patterns: DataFrame, quality: str, k: int) -> DataFrame:
    return patterns.orderBy(F.desc(quality), "pattern").limit(k)


def closed(patterns: DataFrame) -> DataFrame:
    """Patterns without a superset of equal support.

    In a full set of frequent patterns it is enough to look one item further: each
    pattern tells its subsets of one item less about its support.
    """
    smaller = patterns.where("len > 1").select("sup", F.explode("items").alias("gone"), "items")
    told = smaller.select(canonical(F.array_remove("items", F.col("gone"))).alias("pattern"), F.col("sup").alias("sup_above")).groupBy("pattern").agg(F.max("sup_above").alias("sup_above"))
    return patterns.join(told, "pattern", "left").where("sup_above is null or sup_above < sup").drop("sup_above")


def where(patterns: DataFrame, *predicates: Column) -> DataFrame:
    for p in predicates:
        patterns = patterns.where(p)
    return patterns


def has_item(item_id: int) -> Column:
    return F.array_contains("items", F.lit(item_id))


def subset_of(masks: dict[str, int]) -> Column:
    return bits.contains([F.lit(v) for v in masks.values()], [F.col(m) for m in masks])


def rules(patterns: DataFrame, min_conf: float, n: int) -> DataFrame:
    """Association rules with one item on the right: ``(left, right, sup, confidence, lift)``."""
    split = patterns.where("len > 1").select("sup", F.explode("items").alias("right"), "items").select("sup", "right", canonical(F.array_remove("items", F.col("right"))).alias("left"))
    left = patterns.select(F.col("pattern").alias("left"), F.col("sup").alias("sup_left"))
    right = patterns.where("len = 1").select(F.element_at("items", 1).alias("right"), F.col("sup").alias("sup_right"))
    confidence = F.col("sup") / F.col("sup_left")
    joined = split.join(left, "left").join(F.broadcast(right), "right")
    return joined.select("left", "right", "sup", confidence.alias("confidence"), (confidence * n / F.col("sup_right")).alias("lift")).where(F.col("confidence") >= min_conf)
