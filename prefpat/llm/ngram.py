"""Stupid-backoff scores of all texts, against the counts of all other texts.

The n-gram tables are relations of (n-gram hash, count) partitioned by hash. An
n-gram of a text joins them by its hash; what a text says itself is subtracted,
so a text is scored by the rest of the corpus and backing off means something.

An exploded row per n-gram would cost many times the text. So texts are gathered
in blocks of about ``BLOCK_BYTES``; a block sends each distinct n-gram hash
once, with its count, in one sorted array per hash partition; a partition adds up
the counts of all blocks, and returns to every block what others counted, in the
block's order. With that the block, which travels compressed, scores its texts
one by one, and the sums of the positions' logarithms are the result. What is
sent grows with the distinct n-grams of the blocks, a partition holds a fixed
share of the hashes, and an n-gram that is everywhere costs one entry a block.

Score of a word after two others: the relative frequency of the trigram if it
occurs elsewhere, else ``ALPHA`` times that of the bigram, else ``ALPHA`` squared
times that of the word, else ``ALPHA`` cubed by the number of words; shorter
contexts at a text's start have fewer steps. N-grams are told apart by their
order and 54 bits of hash: of ten trillion n-grams one in two thousand would
share its hash with another.

Blocks are cut twice from the same rows, once to count and once to score, so the
input must give its partitions the same rows each time, as a scan of files does;
otherwise the number of counts that come back differs and the job fails.

Defined cases: a null or blank text has no words and score 0; a null key is
carried along; repeated rows are texts of their own, and count for each other;
an empty table gives no rows; a corpus of one text has no other words and scores
0. Only key and text are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefpat.llm.common import read_table, shuffle_parts

ALPHA = 0.4
ORDERS = 3
BLOCK_BYTES = 6 << 20
BLOCK_TEXTS = 1 << 16
#: Bits of an n-gram's number: hash, then order.
HASH_BITS = 56
KEPT_WORDS = 1 << 18
#: Fixed odd factors that mix word hashes into n-gram hashes.
FACTORS = tuple(np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9))


class WordHashes(dict):
    def __missing__(self, word: str) -> int:
        if len(self) >= KEPT_WORDS:
            self.clear()
        found = self[word] = xxhash.xxh64_intdigest(word)
        return found


WORD_HASHES = WordHashes()


def mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(29))) * FACTORS[1]
    return x ^ (x >> np.uint64(32))


def numbered(hashes: np.ndarray, order: int) -> np.ndarray:
    return (hashes >> np.uint64(64 - HASH_BITS)) & ~np.uint64(3) | np.uint64(order)


def words_of_text(text: bytes | None) -> list[bytes]:
    return (text or b"").lower().split()


def hashed_texts(texts: list[bytes | None]) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """For each order the n-gram numbers at every position (0 where there is none),
    the text of every position and its place in the text."""
    parts, lengths = [], []
    for text in texts:
        words = words_of_text(text)
        lengths.append(len(words))
        parts.append(np.fromiter(map(WORD_HASHES.__getitem__, words), dtype=np.uint64, count=len(words)))
    words = np.concatenate(parts) * FACTORS[0] if parts else np.zeros(0, np.uint64)
    owner = np.repeat(np.arange(len(texts)), lengths)
    at = np.arange(len(words)) - np.repeat(np.cumsum(lengths) - lengths, lengths)
    gram = mixed(words)
    grams = [numbered(gram, 1)]
    for n in range(1, ORDERS):
        # the hash of w1..wn from that of w1..wn-1, one position earlier, and the last word
        gram = mixed(np.roll(gram, 1) * FACTORS[2] + words + np.uint64(n))
        grams.append(np.where(at < n, np.uint64(0), numbered(gram, n + 1)))
    return grams, owner, at


def squeeze(values: np.ndarray) -> bytes:
    """Byte planes, compressed: high bytes of small numbers cost next to nothing."""
    planes = np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def unsqueeze(data: bytes) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(8, -1)
    return np.ascontiguousarray(planes.T).view("<u8").reshape(-1)


def squeeze_sorted(values: np.ndarray) -> bytes:
    return squeeze(np.diff(values, prepend=np.uint64(0)))


def unsqueeze_sorted(data: bytes) -> np.ndarray:
    return np.cumsum(unsqueeze(data), dtype=np.uint64)


def runs(ordered: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First places and lengths of runs of equal values."""
    first = np.flatnonzero(np.r_[True, ordered[1:] != ordered[:-1]]) if len(ordered) else np.zeros(0, int)
    return first, np.diff(np.r_[first, len(ordered)])


def counted(grams: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Distinct numbers of all orders, sorted, and their counts; 0 is left out."""
    every = np.sort(np.concatenate(grams))
    every = every[np.searchsorted(every, np.uint64(1)) :]
    first, lengths = runs(every)
    return every[first], lengths.astype(np.uint64)


def cut_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, list, list, pa.DataType]]:
    """Block number, keys, texts and the keys' type."""
    task, made = TaskContext.get().partitionId(), 0
    keys, texts, size, key_type = [], [], 0, pa.null()
    for batch in batches:
        key_type = batch.column(0).type
        for key, text in zip(batch.column(0).to_pylist(), batch.column(1)):
            keys.append(key)
            texts.append(text.as_py())
            size += len(texts[-1] or b"")
            if size >= BLOCK_BYTES or len(texts) >= BLOCK_TEXTS:
                yield (task << 24) | made, keys, texts, key_type
                keys, texts, size, made = [], [], 0, made + 1
    if texts:
        yield (task << 24) | made, keys, texts, key_type


def keep_texts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Batches of (key, text) to (block, part -1, no total, compressed texts)."""
    for block, keys, texts, key_type in cut_blocks(batches):
        inner = pa.RecordBatch.from_arrays([pa.array(keys, key_type), pa.array(texts, pa.large_binary())], names=["key", "text"])
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, inner.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", 3))) as writer:
            writer.write_batch(inner)
        yield pa.RecordBatch.from_arrays([pa.array([block], pa.int64()), pa.array([-1], pa.int32()), pa.array([0], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["block", "part", "words", "data"])


def opened(texts: bytes) -> pa.RecordBatch:
    return pa.ipc.open_stream(texts).read_next_batch()


def send_counts(partitions: int):
    """Batches of (key, text) to (part, block, numbers, counts): a row for every
    block and hash partition, empty ones included."""
    edges = np.array([(i << HASH_BITS) // partitions for i in range(1, partitions)], dtype=np.uint64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block, _, texts, _ in cut_blocks(batches):
            numbers, counts = counted(hashed_texts(texts)[0])
            cuts = np.r_[0, np.searchsorted(numbers, edges), len(numbers)].tolist()
            spans = list(zip(cuts[:-1], cuts[1:]))
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(range(partitions), pa.int32()),
                    pa.array([block] * partitions, pa.int64()),
                    pa.array([squeeze_sorted(numbers[a:b]) for a, b in spans], pa.binary()),
                    pa.array([squeeze(counts[a:b]) for a, b in spans], pa.binary()),
                ],
                names=["part", "block", "numbers", "counts"],
            )

    return run


def add_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by part to (block, part, words, data): the part's words in all,
    and what other blocks count."""

    def finish(part: int, rows: list[tuple]) -> pa.RecordBatch:
        numbers, counts = [unsqueeze_sorted(r[1]) for r in rows], [unsqueeze(r[2]) for r in rows]
        every, own = np.concatenate(numbers), np.concatenate(counts)
        words = int(own[every & np.uint64(3) == 1].sum())
        order = np.argsort(every)
        first, lengths = runs(every[order])
        totals = np.empty(len(every), dtype=np.uint64)
        totals[order] = np.repeat(np.add.reduceat(own[order], first), lengths) if len(first) else 0
        ends = np.cumsum([len(h) for h in numbers])
        others = [squeeze(totals[e - len(h) : e] - c) for e, h, c in zip(ends, numbers, counts)]
        return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([part] * len(rows), pa.int32()), pa.array([words] * len(rows), pa.int64()), pa.array(others, pa.binary())], names=["block", "part", "words", "data"])

    at, held = None, []
    for batch in batches:
        for part, block, numbers, counts in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), batch.column(3)):
            if part != at and held:
                yield finish(at, held)
                held = []
            at = part
            held.append((block, numbers.as_py(), counts.as_py()))
    if held:
        yield finish(at, held)


def scored(texts: list[bytes | None], others: np.ndarray, total_words: int) -> tuple[np.ndarray, ...]:
    """Words, log score and positions by order used, of every text of a block."""
    grams, owner, at = hashed_texts(texts)
    every = np.concatenate(grams)
    order = np.argsort(every)
    first, lengths = runs(every[order])
    if len(first) and every[order[0]] == 0:  # positions without an n-gram of an order
        others = np.r_[np.uint64(0), others]
    if len(others) != len(first):
        raise RuntimeError("a block was cut differently to count and to score: its input is not the same each time")
    overall = np.empty(len(every), dtype=np.int64)
    overall[order] = np.repeat(lengths + others.astype(np.int64), lengths)
    sizes = np.bincount(owner, minlength=len(texts)).astype(np.float64)
    left = []  # counts in other texts, by order and position
    for n, g in enumerate(grams):
        key = mixed(g ^ (owner.astype(np.uint64) * FACTORS[2]))
        order = np.argsort(key)
        _, lengths = runs(key[order])
        own = np.empty(len(g), dtype=np.int64)
        own[order] = np.repeat(lengths, lengths)
        left.append(np.where(g > 0, overall[n * len(g) : (n + 1) * len(g)] - own, 0).astype(np.float64))
    earlier = lambda x: np.concatenate([np.zeros(1), x[:-1]]) if len(x) else x
    rest = (total_words - sizes)[owner]
    score = np.where(rest > 0, np.log(np.maximum(left[0], 1)) - np.log(np.maximum(rest, 1)) + np.where(left[0] > 0, 0.0, np.log(ALPHA)), 0.0)
    used = np.where(left[0] > 0, 1, 0)
    for n in range(1, ORDERS):
        hit = left[n] > 0
        better = np.log(np.where(hit, left[n], 1)) - np.log(np.where(hit, np.maximum(earlier(left[n - 1]), 1), 1))
        backed = score + np.where((at >= n) & (rest > 0), np.log(ALPHA), 0.0)
        score, used = np.where(hit, better, backed), np.where(hit, n + 1, used)
    sums = np.bincount(owner, weights=score, minlength=len(texts))
    return sizes.astype(np.int64), sums, *(np.bincount(owner[used == n], minlength=len(texts)) for n in range(ORDERS + 1))


def score_blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (block, part), texts first, to scores of texts."""

    def finish(texts: bytes, others: list[np.ndarray], total_words: int) -> pa.RecordBatch:
        inner = opened(texts)
        found = scored(inner.column(1).to_pylist(), np.concatenate(others), total_words)
        return pa.RecordBatch.from_arrays([inner.column(0), *map(pa.array, found)], names=["key", "n_words", "log_score", *[f"used_{n}" for n in range(ORDERS + 1)]])

    texts, others, total = None, [], 0
    for batch in batches:
        for part, words, data in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3)):
            if part < 0:
                if texts is not None:
                    yield finish(texts, others, total)
                texts, others, total = data.as_py(), [], 0
            else:
                others.append(unsqueeze(data.as_py()))
                total += words
    if texts is not None:
        yield finish(texts, others, total)


def backoff_scores(df: DataFrame, key: str, text: str) -> DataFrame:
    """``(key, n_words, log_score, used_0 .. used_3)``: the natural logarithm of a
    text's score, and how many of its words were scored by which order."""
    source = df.select(F.col(f"`{key}`").alias("key"), F.col(f"`{text}`").cast("binary").alias("text"))
    parts = shuffle_parts(df.sparkSession)
    sent = source.mapInArrow(send_counts(4 * parts), "part int, block long, numbers binary, counts binary")
    row = "block long, part int, words long, data binary"
    added = sent.repartition(parts, "part").sortWithinPartitions("part").mapInArrow(add_counts, row)
    joined = source.mapInArrow(keep_texts, row).unionByName(added)
    key_type = source.schema["key"].dataType.simpleString()
    used = ", ".join(f"used_{n} long" for n in range(ORDERS + 1))
    return joined.repartition(parts, "block").sortWithinPartitions("block", "part").mapInArrow(score_blocks, f"key {key_type}, n_words long, log_score double, {used}")


def op4_ngram(spark, sf_dir):
    """Scores of all documents by trigrams, bigrams and words of all the others."""
    found = backoff_scores(read_table(spark, sf_dir, "documents"), "doc_id", "text")
    return found.select(F.col("key").alias("doc_id"), "n_words", F.round("log_score", 4).alias("log_score"), *[f"used_{n}" for n in range(ORDERS + 1)])


OP4_SQL = r"""
WITH docs AS (
  SELECT row_number() OVER () AS r, doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \t\n\x0B\f\r]+'), lambda w: w <> '') AS w FROM documents
), places AS (
  SELECT r, len(w) AS n, u.i, w[u.i] AS c, CASE WHEN u.i > 1 THEN w[u.i - 1] || ' ' || w[u.i] END AS b, CASE WHEN u.i > 2 THEN w[u.i - 2] || ' ' || w[u.i - 1] || ' ' || w[u.i] END AS a
  FROM docs, unnest(range(1, len(w) + 1)) AS u(i)
), others AS (
  SELECT r, n, i,
         count(*) OVER (PARTITION BY c) - count(*) OVER (PARTITION BY r, c) AS c1,
         CASE WHEN b IS NULL THEN 0 ELSE count(*) OVER (PARTITION BY b) - count(*) OVER (PARTITION BY r, b) END AS c2,
         CASE WHEN a IS NULL THEN 0 ELSE count(*) OVER (PARTITION BY a) - count(*) OVER (PARTITION BY r, a) END AS c3,
         count(*) OVER () - n AS rest
  FROM places
), context AS (
  SELECT *, lag(c1) OVER o AS p1, lag(c2) OVER o AS p2 FROM others WINDOW o AS (PARTITION BY r ORDER BY i)
), used AS (
  SELECT *, CASE WHEN c3 > 0 THEN 3 WHEN c2 > 0 THEN 2 WHEN c1 > 0 THEN 1 ELSE 0 END AS u, least(i, 3) AS top FROM context
), scores AS (
  SELECT *, CASE WHEN rest = 0 THEN 0.0 WHEN u = 3 THEN ln(c3) - ln(p2)
                 WHEN u = 2 THEN ln(c2) - ln(p1) + (top - 2) * ln(0.4)
                 WHEN u = 1 THEN ln(c1) - ln(rest) + (top - 1) * ln(0.4)
                 ELSE top * ln(0.4) - ln(rest) END AS s
  FROM used
), sums AS (
  SELECT r, sum(s) AS s, count(*) FILTER (u = 0) AS used_0, count(*) FILTER (u = 1) AS used_1, count(*) FILTER (u = 2) AS used_2, count(*) FILTER (u = 3) AS used_3
  FROM scores GROUP BY r
)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, round(coalesce(s, 0.0), 4) AS log_score, coalesce(used_0, 0) AS used_0, coalesce(used_1, 0) AS used_1, coalesce(used_2, 0) AS used_2, coalesce(used_3, 0) AS used_3
FROM docs d LEFT JOIN sums s ON s.r = d.r
"""
