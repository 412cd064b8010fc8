"""SimHash near-duplicate detection by a binary trie self-join.

Fingerprints. A text's words (ASCII white space separates, A-Z lower-cased) give
shingles; each shingle is hashed with XXH64, seed 42; bit b of the fingerprint is
1 if it is set in over half of the hashes. Texts without words get fingerprint 0.

Candidates. Only distinct fingerprints are compared, so exact copies, however
many, cost one entry. Bits are cut into ``budget + agree`` blocks: two fingerprints
that differ in at most ``budget`` bits agree on ``agree`` whole blocks at least. Each
fingerprint is therefore sent once for each block (``agree`` 1) or pair of blocks (2),
to the bucket of these blocks' bits; a bucket is the subtree of a trie in which those
bits come first. Inside a bucket the trie is joined with itself: node pairs go down
together, a differing bit adds one, and a pair is pruned as soon as its sum
exceeds the budget. A pair of nodes with at most ``leaf`` pairs of leaves below is
compared at once; with ``leaf`` 1 only what the descent leaves is compared. Every pair
within the budget meets in a bucket, so no link is lost; a bucket returns a spanning
forest of its links and not all pairs of a group.

Components. Large-star and small-star rounds over the forests, each cut by a
checkpoint, give connected components in a number of rounds that grows with the
logarithm of a component's size.

Near copies by sets. Representatives are kept over a second kind of link as well:
a Jaccard similarity of the shingle sets, decided exactly. See ``exact_links``.

Defined cases: a null text has no words; a null key is carried along and gets
the smallest non-null key of its component (null if there is none); repeated
rows are rows of the same component; an empty table gives no rows. Only key and
text are read, so other columns, whatever their names, play no part.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import accumulate, combinations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.llm.common import cut, read_table, shuffle_parts

SEED = 42
BITS = 64
#: Shingles hashed at a time, and pairs compared at a time: they bound memory.
HASH_CHUNK = 1 << 16
PAIR_CHUNK = 1 << 20
#: Leaf pairs up to which a node pair is compared without going on, where the budget is
#: too wide for the upper levels of a bucket's trie to prune.
LEAF_PAIRS = 64
#: Parts into which the fingerprints of one component, or the texts of one group, are
#: dealt when they get its name or its number of blocks.
SALT = 16
#: Rows of whole buckets gathered before a join starts.
BUCKET_ROWS = 1 << 18
#: Near copies meet where all least hashes of one band agree: at a similarity of 0.8
#: all bands miss in 7 pairs of a million.
BANDS, BAND_ROWS = 30, 5
#: Differing bits of 128 up to which texts of a bucket are compared further. Pairs of
#: similarity 0.8 differ in about 19 (24 for the shortest texts), others in 64.
LOOSE = 44
#: Odd factors that order hashes anew for every least hash.
FACTORS = np.random.Generator(np.random.PCG64(SEED)).integers(0, 1 << 63, BANDS * BAND_ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
#: Hashes sketched at a time, and rows gathered before whole groups are compared.
SKETCH_CHUNK = 1 << 12
GROUP_ROWS, GROUP_BYTES = 1 << 14, 1 << 24
#: Edges that one task solves at once, in about 16 MB.
SMALL_EDGES = 1 << 20
#: Texts, and their bytes, that a block of a group holds: one task compares two blocks.
BLOCK_TEXTS, BLOCK_BYTES = 1 << 13, 1 << 24


def remix(hashes: np.ndarray) -> np.ndarray:
    """A second, independent hash of every hash: the SplitMix64 finaliser."""
    x = hashes + np.uint64(0x9E3779B97F4A7C15)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = (x ^ (x >> np.uint64(shift))) * np.uint64(factor)
    return x ^ (x >> np.uint64(31))


def text_fingerprints(text: bytes | None, shingle: int, guard: bool = False) -> tuple[int, int]:
    """The fingerprint and, if asked for, a second one over remixed hashes."""
    words = (text or b"").lower().split()
    if not words:
        return 0, 0
    starts = [0, *accumulate(len(w) + 1 for w in words)]
    joined = b" ".join(words)
    spans = list(zip(starts, starts[shingle:])) or [(0, len(joined) + 1)]
    digest, ones = xxhash.xxh64_intdigest, np.zeros((2, BITS), dtype=np.int64)
    for i in range(0, len(spans), HASH_CHUNK):
        part = spans[i : i + HASH_CHUNK]
        hashes = np.fromiter((digest(joined[a : b - 1], SEED) for a, b in part), dtype=np.uint64, count=len(part))
        for row, own in enumerate((hashes, remix(hashes)) if guard else (hashes,)):
            ones[row] += np.unpackbits(own.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    bits = (2 * ones > len(spans)).astype(np.uint8)
    first, second = np.packbits(bits, axis=1, bitorder="little").view(np.uint64)[:, 0].tolist()
    return first, second


def text_fingerprint(text: bytes | None, shingle: int) -> int:
    return text_fingerprints(text, shingle)[0]


def fingerprint_column(text: Column, shingle: int, guard: bool) -> Column:
    @F.pandas_udf("print long, guard long")
    def fingerprint(texts: pd.Series) -> pd.DataFrame:
        prints = np.array([text_fingerprints(t, shingle, guard) for t in texts], dtype=np.uint64).reshape(-1, 2)
        return pd.DataFrame(prints.view(np.int64), columns=["print", "guard"])

    return fingerprint(text.cast("binary"))


# --- the trie self-join, on one task's buckets ---------------------------------


class Forest:
    """Union-find over positions; edges inside a tree are dropped in bulk."""

    def __init__(self, n: int):
        self.root = np.arange(n)

    def find(self, x: int) -> int:
        root = self.root
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return int(x)

    def add(self, left: np.ndarray, right: np.ndarray) -> None:
        new = self.root[left] != self.root[right]
        for a, b in zip(left[new].tolist(), right[new].tolist()):
            a, b = self.find(a), self.find(b)
            if a != b:
                self.root[max(a, b)] = min(a, b)
        self.settle()

    def settle(self) -> None:
        while True:
            up = self.root[self.root]
            if np.array_equal(up, self.root):
                return
            self.root = up


def expand(sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For sizes (2, 3): owners 0 0 1 1 1 and places 0 1 0 1 2."""
    owner = np.repeat(np.arange(len(sizes)), sizes)
    return owner, np.arange(len(owner)) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def compare_leaves(prints: np.ndarray, guards: np.ndarray, pairs: np.ndarray, budget: int, both: int | None, forest: Forest) -> None:
    """Compare all leaves below node pairs (rows: first, end, first, end)."""
    sizes = (pairs[1] - pairs[0]) * (pairs[3] - pairs[2])
    groups = np.cumsum(sizes) // PAIR_CHUNK
    for g in np.unique(groups):
        own = pairs[:, groups == g]
        owner, at = expand(sizes[groups == g])
        width = (own[3] - own[2])[owner]
        left, right = own[0][owner] + at // width, own[2][owner] + at % width
        wrong = np.bitwise_count(prints[left] ^ prints[right]).astype(np.int64)
        near = (left < right) & (wrong <= budget)
        left, right = left[near], right[near]
        if both is not None:
            near = wrong[near] + np.bitwise_count(guards[left] ^ guards[right]) <= both
            left, right = left[near], right[near]
        forest.add(left, right)


def trie_self_join(buckets: np.ndarray, prints: np.ndarray, guards: np.ndarray, budget: int, both: int | None = None, leaf: int = LEAF_PAIRS, counts: dict | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Links of a spanning forest of all pairs within the budget and one bucket.

    ``both``, if given, also bounds the differing bits of print and guard
    together. Returned as two arrays of fingerprints. Positions of a sorted array stand for
    leaves and ranges of it for nodes; a node's children are found by counting
    the ones of the next bit in its range. ``counts``, if given, gets how many leaf pairs
    were pruned above the leaves, compared, and known to be near without comparing.
    """
    counts = {} if counts is None else counts
    counts |= {"pruned": 0, "compared": 0, "sure": 0}
    below_ = lambda n: int(((n[1] - n[0]) * (n[3] - n[2])).sum())
    order = np.lexsort((prints, buckets))
    prints, guards, buckets = prints[order], guards[order], buckets[order]
    first = np.flatnonzero(np.r_[True, buckets[1:] != buckets[:-1]]) if len(buckets) else np.zeros(0, int)
    end = np.r_[first[1:], len(buckets)] if len(first) else first
    several = end - first > 1
    first, end = first[several], end[several]
    forest = Forest(len(prints))
    work = [(0, np.stack([first, end, first, end]), np.zeros(len(first), dtype=np.int64))]
    while work:
        depth, nodes, wrong = work.pop()
        if nodes.shape[1] > PAIR_CHUNK:  # depth first in parts, so that memory stays bounded
            half = nodes.shape[1] // 2
            work += [(depth, nodes[:, :half], wrong[:half]), (depth, nodes[:, half:], wrong[half:])]
            continue
        sure = (wrong + (BITS - depth) <= budget) & (both is None)  # whatever follows, all leaves below are near
        for own in nodes[:, sure].T:
            leaves = np.r_[own[0] : own[1], own[2] : own[3]]
            forest.add(np.repeat(leaves[0], len(leaves) - 1), leaves[1:])
        few = ((nodes[1] - nodes[0]) * (nodes[3] - nodes[2]) <= leaf) & ~sure
        if few.any():
            compare_leaves(prints, guards, nodes[:, few], budget, both, forest)
        counts["compared"] += below_(nodes[:, few])
        counts["sure"] += below_(nodes[:, sure])
        go = ~few & ~sure
        nodes, wrong = nodes[:, go], wrong[go]
        if not nodes.shape[1]:
            continue
        ones = np.r_[0, np.cumsum((prints >> np.uint64(BITS - 1 - depth)) & np.uint64(1)).astype(np.int64)]
        a0, a1, b0, b1 = nodes
        a_mid, b_mid = a1 - (ones[a1] - ones[a0]), b1 - (ones[b1] - ones[b0])
        itself = a0 == b0
        below = [
            (np.stack([a0, a_mid, b0, b_mid]), wrong),
            (np.stack([a_mid, a1, b_mid, b1]), wrong),
            (np.stack([a0, a_mid, b_mid, b1]), wrong + 1),
            (np.stack([a_mid, a1, b0, b_mid])[:, ~itself], wrong[~itself] + 1),
        ]
        nodes, wrong = np.concatenate([x for x, _ in below], axis=1), np.concatenate([w for _, w in below])
        live = (nodes[0] < nodes[1]) & (nodes[2] < nodes[3]) & (wrong <= budget)
        counts["pruned"] += below_(nodes[:, wrong > budget])
        work.append((depth + 1, nodes[:, live], wrong[live]))
    forest.settle()
    child = np.flatnonzero(forest.root != np.arange(len(prints)))
    return prints[forest.root[child]], prints[child]


def join_buckets(budget: int, both: int | None, leaf: int = LEAF_PAIRS):
    """Arrow batches of (bucket, print, guard), sorted by bucket, to batches of links."""

    def links(bucket: np.ndarray, prints: np.ndarray, guards: np.ndarray) -> pa.RecordBatch:
        u, v = trie_self_join(bucket, prints.view(np.uint64), guards.view(np.uint64), budget, both, leaf)
        return pa.RecordBatch.from_arrays([pa.array(u.view(np.int64)), pa.array(v.view(np.int64))], names=["u", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        rows = 0
        for batch in batches:
            held.append(tuple(batch.column(i).to_numpy() for i in range(3)))
            rows += batch.num_rows
            if rows >= BUCKET_ROWS:
                columns = [np.concatenate(x) for x in zip(*held)]
                whole = int(np.searchsorted(columns[0], columns[0][-1]))  # the last bucket may go on
                if whole:
                    yield links(*(x[:whole] for x in columns))
                held, rows = [tuple(x[whole:] for x in columns)], len(columns[0]) - whole
        if rows:
            yield links(*(np.concatenate(x) for x in zip(*held)))

    return run


def block_buckets(print_: Column, budget: int, agree: int) -> Column:
    """An array of bucket numbers, one for each choice of ``agree`` blocks (1 or 2)."""
    count = budget + agree
    edges = [BITS * i // count for i in range(count + 1)]
    blocks = list(zip(edges, edges[1:]))
    bits = lambda lo, hi: F.shiftrightunsigned(print_, lo).bitwiseAND(F.lit((1 << (hi - lo)) - 1))
    buckets = []
    for number, chosen in enumerate(combinations(blocks, agree)):
        high = bits(*chosen[0])
        for block in chosen[1:]:
            high = F.shiftleft(high, block[1] - block[0]).bitwiseOR(bits(*block))
        buckets.append(high.bitwiseOR(F.lit(number << 48)))
    return F.array(*buckets)


def near_links(prints: DataFrame, budget: int, both: int | None = None, agree: int = 2, leaf: int = LEAF_PAIRS) -> DataFrame:
    """Links ``(u, v)`` between distinct fingerprints (columns ``print``, ``guard``)."""
    spread = prints.select(F.explode(block_buckets(F.col("print"), budget, agree)).alias("bucket"), "print", "guard")
    dealt = spread.repartition(shuffle_parts(prints.sparkSession), "bucket").sortWithinPartitions("bucket")
    return dealt.mapInArrow(join_buckets(budget, both, leaf), "u long, v long")


def forest_roots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All edges (a, b) to (node, root), in one task."""
    held = [[c.to_numpy() for c in batch.columns] for batch in batches]
    if not held:
        return
    a, b = (np.concatenate(x) for x in zip(*held))
    nodes, place = np.unique(np.concatenate([a, b]), return_inverse=True)
    forest = Forest(len(nodes))
    forest.add(place[: len(a)], place[len(a) :])
    child = np.flatnonzero(forest.root != np.arange(len(nodes)))
    yield pa.RecordBatch.from_arrays([pa.array(nodes[child]), pa.array(nodes[forest.root[child]])], names=["node", "root"])


def connected(links: DataFrame, small: int = 0) -> DataFrame:
    """``(node, root)`` for every node of a link, root the smallest node that it reaches.
    Up to ``small`` edges are solved by one task, more by rounds of joins."""
    edges = cut(links.where("u <> v").select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).distinct())
    seen = None
    while True:
        state = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first()
        if state == seen or not state[0]:
            return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
        if seen is None and state[0] <= small:
            return edges.coalesce(1).mapInArrow(forest_roots, "node long, root long")
        seen = state
        both = edges.union(edges.select(F.col("b"), F.col("a"))).toDF("a", "b")
        least = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select("a", F.col("m").alias("b")))
        edges = cut(small.where("a <> b").distinct())


def simhash_components(df: DataFrame, key: str, text: str, shingle: int = 5, budget: int = 10, both: int | None = 20, agree: int = 2, leaf: int = LEAF_PAIRS) -> DataFrame:
    """``(key, print, component)`` of every row: its fingerprint and the smallest
    key that links reach.

    A link joins fingerprints that differ in at most ``budget`` bits. With
    ``both``, a second fingerprint guards it: the two may differ in at most
    ``both`` bits of 128 together. By default that is a similarity of 0.84, near
    a Jaccard similarity of 0.8 of the shingles; unrelated texts then never link.
    Rows of one print are one link group whatever their guards.
    """
    source = df.select(F.col(key).alias("key"), fingerprint_column(F.col(text), shingle, both is not None).alias("f"))
    prints = cut(source.select("key", "f.print", "f.guard"))
    groups = cut(prints.groupBy("print", "guard").agg(F.min("key").alias("least")))
    roots = connected(near_links(groups, budget, both, agree, leaf))
    least = groups.groupBy("print").agg(F.min("least").alias("least"))
    rooted = cut(least.join(roots, F.col("print") == F.col("node"), "left").select("print", "least", F.coalesce("root", "print").alias("root")))
    # only components of several prints need a common name; a large one is dealt in parts
    smallest = rooted.groupBy("root").agg(F.min("least").alias("component"), F.count(F.lit(1)).alias("n")).where("n > 1").drop("n")
    salted = smallest.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    named = rooted.withColumn("part", F.pmod(F.xxhash64("print"), F.lit(SALT)).cast("int")).join(salted, ["root", "part"], "left")
    return prints.join(named.select("print", F.coalesce("component", "least").alias("component")), "print").select("key", "print", "component")


def op3_simhash(spark, sf_dir):
    """Components of all documents: 4-word shingles, at most 4 differing bits, and the
    trie's descent alone to find them."""
    found = simhash_components(read_table(spark, sf_dir, "documents"), "doc_id", "text", shingle=4, budget=4, both=None, agree=1, leaf=1)
    return found.select(F.col("key").alias("doc_id"), F.lpad(F.lower(F.hex("print")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


# --- near copies by exact similarity of shingle sets ----------------------------


def shingle_hashes(text: bytes | None, shingle: int) -> np.ndarray:
    """The hash of every shingle of a text, in order."""
    words = (text or b"").lower().split()
    starts = [0, *accumulate(len(w) + 1 for w in words)]
    joined = b" ".join(words)
    spans = list(zip(starts, starts[shingle:])) or [(0, len(joined) + 1)] * bool(words)
    digest = xxhash.xxh64_intdigest
    return np.fromiter((digest(joined[a : b - 1], SEED) for a, b in spans), dtype=np.uint64, count=len(spans))


def shingle_set(text: bytes | None, shingle: int) -> np.ndarray:
    """The sorted distinct shingle hashes of a text."""
    return np.unique(shingle_hashes(text, shingle))


def majority(hashes: np.ndarray) -> np.ndarray:
    """Print and guard over given hashes, as in ``text_fingerprints``."""
    ones = np.zeros((2, BITS), dtype=np.int64)
    for i in range(0, len(hashes), HASH_CHUNK):
        part = hashes[i : i + HASH_CHUNK]
        for row, own in enumerate((part, remix(part))):
            ones[row] += np.unpackbits(own.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int32)
    return np.packbits((2 * ones > len(hashes)).astype(np.uint8), axis=1, bitorder="little").view(np.uint64)[:, 0]


def least_hashes(hashes: np.ndarray) -> np.ndarray:
    """The least value of all hashes under every factor."""
    least = np.full(len(FACTORS), np.iinfo(np.uint64).max, dtype=np.uint64)
    for i in range(0, len(hashes), SKETCH_CHUNK):
        np.minimum(least, (FACTORS[:, None] * hashes[i : i + SKETCH_CHUNK]).min(axis=1), out=least)
    return least


def sketch_column(text: Column, shingle: int) -> Column:
    """Of a text: a number of its own, print and guard, the same two over the set of
    its shingles (each counted once), and the bands of least hashes."""

    @F.pandas_udf("id long, print long, guard long, set_print long, set_guard long, bands array<long>")
    def sketches(texts: pd.Series) -> pd.DataFrame:
        ids, prints, least = [], [], []
        for t in texts:
            hashes = shingle_hashes(t, shingle)
            own = np.unique(hashes)
            both = majority(hashes)
            ids.append(xxhash.xxh64_intdigest(hashes.tobytes(), SEED))
            prints.append([*both, *(both if len(own) == len(hashes) else majority(own))])
            least.append(least_hashes(own))
        mins = np.array(least, dtype=np.uint64).reshape(-1, BANDS, BAND_ROWS)
        bands = np.broadcast_to(np.arange(BANDS, dtype=np.uint64), mins.shape[:2])
        for i in range(BAND_ROWS):
            bands = remix(bands ^ mins[:, :, i])
        values = np.array(prints, dtype=np.uint64).reshape(-1, 4).view(np.int64)
        out = pd.DataFrame(values, columns=["print", "guard", "set_print", "set_guard"])
        out.insert(0, "id", np.array(ids, dtype=np.uint64).view(np.int64))
        return out.assign(bands=list(bands.view(np.int64)))

    return sketches(text.cast("binary"))


def reached(n: int, near) -> np.ndarray:
    """For each of ``n`` positions the least one that links reach; ``near(one, rest)``
    tells which of the positions ``rest`` link to ``one``. Each step asks only for
    those not reached yet, so a close group costs little more than its size."""
    root, rest = np.arange(n), np.arange(n)
    while len(rest):
        seed, rest = int(rest[0]), rest[1:]
        ahead = [seed]
        while ahead and len(rest):
            linked = near(ahead.pop(), rest)
            new, rest = rest[linked], rest[~linked]
            root[new] = seed
            ahead += new.tolist()
    return root


def by_group(batches: Iterator[pa.RecordBatch], names: list[str], groups_to_columns) -> Iterator[pa.RecordBatch]:
    """Rows sorted by their first column, given on as whole groups (a list of column
    slices each); every group's result columns make a batch, small ones joined."""
    held: list[list] = []

    def results(columns: list[list]) -> pa.RecordBatch:
        first = np.asarray(columns[0])
        cuts = np.r_[0, np.flatnonzero(first[1:] != first[:-1]) + 1, len(first)]
        found = [groups_to_columns([c[a:b] for c in columns]) for a, b in zip(cuts[:-1], cuts[1:]) if b - a > 1]
        arrays = [np.concatenate(x) if found else np.zeros(0, np.int64) for x in (zip(*found) if found else names)]
        return pa.RecordBatch.from_arrays([pa.array(a.astype(np.int64)) for a in arrays], names=names)

    rows = size = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
        rows, size = rows + batch.num_rows, size + batch.nbytes
        if (rows >= GROUP_ROWS or size >= GROUP_BYTES) and held[0][0][0] != held[-1][0][-1]:
            columns = [np.concatenate(x) for x in zip(*held)]
            whole = int(np.searchsorted(columns[0], columns[0][-1]))  # the last group may go on
            yield results([c[:whole] for c in columns])
            held, rows, size = [[c[whole:] for c in columns]], len(columns[0]) - whole, 0
    if rows:
        yield results([np.concatenate(x) for x in zip(*held)])


def loose_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (bucket, id, set_print, set_guard), sorted by bucket, to links of a forest."""

    def links(group: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        _, ids, prints, guards = group
        near = lambda one, rest: np.bitwise_count(prints[rest] ^ prints[one]).astype(np.int64) + np.bitwise_count(guards[rest] ^ guards[one]) <= LOOSE
        prints, guards = prints.view(np.uint64), guards.view(np.uint64)
        root = reached(len(ids), near)
        child = np.flatnonzero(root != np.arange(len(ids)))
        return ids[root[child]], ids[child]

    yield from by_group(batches, ["u", "v"], links)


def shared_counts(elements: np.ndarray, begins: np.ndarray):
    """A function ``(one, rest)``: how many elements set ``one`` shares with each of the
    sets ``rest``. Set i is ``elements[begins[i] : begins[i + 1]]``, without repeats.

    Elements of one set alone are shared with none. The others are bits of a matrix with
    a row for each set, where it has no more words than there are elements; sets
    that share little with most others are told by marks instead.
    """
    n = len(begins) - 1
    _, place, times = np.unique(elements, return_inverse=True, return_counts=True)
    width = -(-int(np.count_nonzero(times > 1)) // 64)
    if n * width <= len(elements):
        several = times[place] > 1
        bit = (np.cumsum(times > 1) - 1)[place[several]]
        owner = np.repeat(np.arange(n), np.diff(begins))[several]
        matrix = np.zeros((n, width), dtype=np.uint64)
        np.bitwise_or.at(matrix, (owner, bit >> 6), np.uint64(1) << (bit & 63).astype(np.uint64))
        return lambda one, rest: np.bitwise_count(matrix[rest] & matrix[one]).sum(axis=1, dtype=np.int64)

    mark = np.zeros(len(times), dtype=bool)

    def by_marks(one: int, rest: np.ndarray) -> np.ndarray:
        own = place[begins[one] : begins[one + 1]]
        mark[own] = True
        shared = np.array([np.count_nonzero(mark[place[begins[i] : begins[i + 1]]]) for i in rest.tolist()], dtype=np.int64)
        mark[own] = False
        return shared

    return by_marks


def exact_components(shingle: int, similarity: float):
    """Rows (meeting, id, text), sorted by meeting, to (id, component)."""

    def components(group: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        _, ids, texts = group
        sets = [shingle_set(t, shingle) for t in texts]
        sizes = np.array([len(s) for s in sets])
        begins = np.r_[0, np.cumsum(sizes)]
        shared_with = shared_counts(np.concatenate(sets), begins)

        def near(one: int, rest: np.ndarray) -> np.ndarray:
            fits = (np.minimum(sizes[rest], sizes[one]) >= similarity * np.maximum(sizes[rest], sizes[one]) - 1e-9)
            linked = np.zeros(len(rest), dtype=bool)
            shared = shared_with(one, rest[fits])
            linked[fits] = shared >= similarity * (sizes[rest[fits]] + sizes[one] - shared) - 1e-9
            return linked

        return ids, ids[reached(len(ids), near)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from by_group(batches, ["id", "component"], components)

    return run


def meetings(group: Column, id_: Column, blocks: Column) -> Column:
    """The numbers under which a text meets others of its group: the group's own where it
    is one block, else one for each pair of blocks that holds the text's block."""
    own = F.pmod(F.xxhash64(id_), blocks).cast("int")
    others = F.array_remove(F.sequence(F.lit(0), blocks - 1), own)
    pairs = F.transform(others, lambda j: F.xxhash64(group, F.least(own, j), F.greatest(own, j)))
    return F.when(blocks > 1, pairs).otherwise(F.array(group))


def exact_links(rows: DataFrame, texts: DataFrame, shingle: int, similarity: float, block_texts: int = BLOCK_TEXTS, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Links ``(u, v)`` that join all texts whose shingle sets have the similarity.

    Texts meet where one band of least hashes agrees and the prints of their sets
    differ in at most ``LOOSE`` bits; what these loose links reach is compared by
    the shingle sets themselves. A group of more than ``block_texts`` texts or
    ``block_bytes`` is dealt into blocks by a hash of the texts, and every two blocks
    meet in a task of their own: no task holds more, and no pair is lost.
    """
    parts = shuffle_parts(rows.sparkSession)
    spread = texts.select(F.explode("bands").alias("bucket"), "id", "set_print", "set_guard")
    loose = connected(spread.repartition(parts, "bucket").sortWithinPartitions("bucket").mapInArrow(loose_links, "u long, v long"), SMALL_EDGES)
    members = loose.select(F.col("root").alias("group"), F.col("node").alias("id")).union(loose.select("root", "root").distinct())
    wanted = members.join(texts.select("id", "least", "size"), "id")
    wanted = cut(wanted.select("group", F.col("id").alias("number"), "least", "size", row_hash("least").alias("wanted_hash")))
    blocks = F.ceil(F.greatest(F.count(F.lit(1)) / block_texts, F.sum("size") / block_bytes)).cast("int")
    large = wanted.groupBy("group").agg(blocks.alias("blocks")).where("blocks > 1").withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(SALT - 1))))
    wanted = wanted.withColumn("part", F.pmod(F.xxhash64("number"), F.lit(SALT)).cast("int")).join(large, ["group", "part"], "left")
    same = (rows["row_hash"] == wanted["wanted_hash"]) & same_row(rows["id"], wanted["least"])
    # hashed rows are dealt once, for the join and for the repeated rows after it
    fetched = rows.join(wanted, same).dropDuplicates(["row_hash", "number"])
    met = fetched.select(F.explode(meetings(F.col("group"), F.col("number"), F.coalesce("blocks", F.lit(1)))).alias("meeting"), F.col("number").alias("id"), "text")
    exact = met.repartition(parts, "meeting").sortWithinPartitions("meeting").mapInArrow(exact_components(shingle, similarity), "v long, u long")
    return exact.where("u <> v").select("u", "v")


def row_hash(id_: str) -> Column:
    return F.xxhash64(f"{id_}.no_key", f"{id_}.key", f"{id_}.text_hash")


def same_row(left: Column, right: Column) -> Column:
    """Beside an equal ``row_hash``; no join key, so that the join deals rows by that hash alone."""
    return left["text_hash"].bitwiseXOR(right["text_hash"]) == 0


def keep_representatives(df: DataFrame, key: str, text: str, shingle: int = 5, budget: int = 10, both: int | None = 20, similarity: float = 0.8) -> DataFrame:
    """One row of every group of near copies, all columns as they were: of the rows
    with its smallest key the one with the least text hash. Rows without a key come last.

    Two texts link if their fingerprints do (see ``simhash_components``) or if their
    sets of shingles have a Jaccard similarity of at least ``similarity``.
    """
    own = F.col(f"`{key}`")
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), F.struct(own.isNull().alias("no_key"), own.alias("key"), F.xxhash64(F.col(f"`{text}`")).alias("text_hash")).alias("id"))
    rows = rows.withColumn("row_hash", row_hash("id"))
    body = F.col(f"row.`{text}`")
    found = rows.select(F.col("id").alias("key"), F.coalesce(F.octet_length(body), F.lit(0)).alias("size"), sketch_column(body, shingle).alias("s")).select("key", "size", "s.*")
    firsts = [F.first(c).alias(c) for c in ("print", "guard", "set_print", "set_guard", "bands")]
    texts = cut(found.groupBy("id").agg(F.min("key").alias("least"), F.max("size").alias("size"), *firsts))
    prints = cut(texts.groupBy("print").agg(F.min("id").alias("of")))
    near = near_links(cut(texts.select("print", "guard").distinct()), budget, both)
    number = lambda name: prints.select(F.col("print").alias(name), F.col("of").alias(f"{name}_of"))
    links = near.where("u <> v").join(number("u"), "u").join(number("v"), "v").select(F.col("u_of").alias("u"), F.col("v_of").alias("v"))
    links = links.union(texts.join(prints.select("print", "of"), "print").where("id <> of").select("of", "id"))
    links = links.union(exact_links(rows.select("row_hash", "id", body.cast("binary").alias("text")), texts, shingle, similarity))
    rooted = texts.join(connected(links, SMALL_EDGES), F.col("id") == F.col("node"), "left").select("least", F.coalesce("root", "id").alias("root"))
    stays = rooted.groupBy("root").agg(F.min("least").alias("least")).select("least", row_hash("least").alias("stays_hash")).distinct()
    same = (rows["row_hash"] == stays["stays_hash"]) & same_row(rows["id"], stays["least"])
    return rows.join(stays, same, "left_semi").dropDuplicates(["row_hash", "id"]).select("row.*")
