"""Sharding by jump consistent hashing.

A stable key and the number of shards decide a row's shard; there is no ring
table to store or to broadcast. When a shard is appended, a row stays or moves
into the new one, and 1/(n+1) of the rows move, the least that evens them out.

Slots number a shard's rows without gaps. Numbering a whole shard in one task
would not scale (there are few shards), so each shard is numbered in buckets:
rows are counted by (shard, bucket), the counts give every bucket its first
slot, and a row number inside the bucket is added. The bucket table has
``shards * buckets`` rows, a bound that does not depend on the data, and so is
broadcast.

Defined cases: a null key hashes as the empty string; a null text has no bytes
and the CRC of no bytes; rows that repeat a key share its shard and get slots of
their own; an empty table gives no rows. Only key and text are read, so other
columns, whatever their names, play no part.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType

from prefpat.llm.common import read_table

#: Fixed values of jump consistent hashing: the multiplier of its linear
#: congruential generator and the shift that leaves 31 high bits.
LCG_MULTIPLIER = 2862933555777941757
HIGH_BITS_SHIFT = 33


def jump_shards(keys: np.ndarray, shards: int) -> np.ndarray:
    """Shards of unsigned 64-bit keys, all rows stepping at once.

    Every step moves a row to a later candidate or ends it, so there are at most
    ``shards`` steps and about ln(shards) on average.
    """
    if shards < 1:
        raise ValueError("at least one shard is needed")
    state = keys.astype(np.uint64, copy=True)
    shard = np.zeros(len(keys), dtype=np.int64)
    live = np.arange(len(keys))
    while len(live):
        with np.errstate(over="ignore"):
            state[live] = state[live] * np.uint64(LCG_MULTIPLIER) + np.uint64(1)
        draw = (state[live] >> np.uint64(HIGH_BITS_SHIFT)).astype(np.float64) + 1.0
        jump = ((shard[live] + 1) * (float(1 << 31) / draw)).astype(np.int64)
        inside = jump < shards
        live = live[inside]
        shard[live] = jump[inside]
    return shard


def key_hex(key: Column) -> Column:
    """A portable digest of a key: stable over engines, sessions and releases."""
    return F.md5(F.coalesce(key.cast("string"), F.lit("")).cast("binary"))


def jump_column(hexdigest: Column, shards: int) -> Column:
    """Shard of a row from the first 64 bits of its key digest."""

    @F.pandas_udf(IntegerType())
    def jump(digests: pd.Series) -> pd.Series:
        keys = np.fromiter((int(d[:16], 16) for d in digests), dtype=np.uint64, count=len(digests))
        return pd.Series(jump_shards(keys, shards).astype(np.int32))

    return jump(hexdigest)


def assign_shards(df: DataFrame, key: str, text: str, shards: int, buckets: int = 256) -> DataFrame:
    """Rows ``(key, size, text_crc32, law, shard, slot, grown_shard)``.

    ``size`` is the UTF-8 length of the text plus eight bytes of header. Only
    sizes and checksums travel: the text itself is read and not shuffled.
    """
    rows = df.select(
        F.col(f"`{key}`").alias("key"),
        (F.coalesce(F.octet_length(F.col(f"`{text}`")), F.lit(0)) + 8).cast("long").alias("size"),
        F.crc32(F.coalesce(F.col(f"`{text}`"), F.lit("")).cast("binary")).alias("text_crc32"),
        key_hex(F.col(f"`{key}`")).alias("digest"),
    )
    placed = rows.select(
        "key", "size", "text_crc32",
        jump_column(F.col("digest"), shards).alias("shard"),
        jump_column(F.col("digest"), shards + 1).alias("grown_shard"),
        (F.conv(F.substring("digest", 25, 8), 16, 10).cast("long") % buckets).cast("int").alias("bucket"),
    )
    counts = placed.groupBy("shard", "bucket").agg(F.count(F.lit(1)).alias("n"))
    earlier = Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    first = counts.select("shard", "bucket", F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("first_slot"))
    inside = Window.partitionBy("shard", "bucket").orderBy("key", "text_crc32", "size")
    return (
        placed.withColumn("at", F.row_number().over(inside) - 1)
        .join(F.broadcast(first), ["shard", "bucket"])
        .select(
            F.col("key").alias(key), "size", "text_crc32", F.lit("key").alias("law"), "shard",
            (F.col("first_slot") + F.col("at")).cast("long").alias("slot"), "grown_shard",
        )
    )


def op8_sharding(spark, sf_dir):
    """All documents into shards 0 to 23 by the ``key`` law."""
    return assign_shards(read_table(spark, sf_dir, "documents"), "doc_id", "text", 24)


OP8_SQL = """
WITH RECURSIVE crc_table AS (
  SELECT list(v ORDER BY i) AS t
  FROM (SELECT i, list_reduce(list_prepend(i, [0,0,0,0,0,0,0,0]::BIGINT[]), lambda c, z: CASE WHEN c % 2 = 1 THEN xor(c // 2, 3988292384) ELSE c // 2 END) AS v FROM range(256) AS r(i))
), base AS (
  SELECT doc_id, coalesce(strlen(text), 0) + 8 AS size, md5(coalesce(CAST(doc_id AS VARCHAR), '')) AS digest,
         xor(list_reduce(list_prepend(4294967295::BIGINT, list_transform(range(1, 1 + coalesce(strlen(text), 0)), lambda k: CAST('0x' || substr(h, CAST(2 * k - 1 AS BIGINT), 2) AS BIGINT))), lambda c, b: xor(c // 256, t[1 + (xor(c, b) % 256)])), 4294967295) AS text_crc32
  FROM (SELECT doc_id, text, hex(encode(coalesce(text, ''))) AS h FROM documents) CROSS JOIN crc_table
), keys AS (
  SELECT DISTINCT digest FROM base
), jump AS (
  SELECT digest, n, CAST(('0x' || substr(digest, 1, 16)) AS UHUGEINT) AS state, CAST(0 AS BIGINT) AS shard, CAST(0 AS BIGINT) AS ahead
  FROM keys CROSS JOIN (VALUES (24), (25)) AS c(n)
  UNION ALL
  SELECT digest, n, state2, ahead, CAST(trunc((ahead + 1) * (2147483648.0::DOUBLE / (CAST(state2 // 8589934592::UHUGEINT AS DOUBLE) + 1.0))) AS BIGINT)
  FROM (SELECT *, (state * 2862933555777941757::UHUGEINT + 1::UHUGEINT) % 18446744073709551616::UHUGEINT AS state2 FROM jump) AS s
  WHERE ahead < n
), last AS (
  SELECT digest, n, max(shard) AS shard FROM jump GROUP BY digest, n
), placed AS (
  SELECT b.doc_id, b.size, b.text_crc32, a.shard, g.shard AS grown_shard, CAST(('0x' || substr(b.digest, 25, 8)) AS BIGINT) % 256 AS bucket
  FROM base b JOIN last a ON a.digest = b.digest AND a.n = 24 JOIN last g ON g.digest = b.digest AND g.n = 25
)
SELECT doc_id, CAST(size AS BIGINT) AS size, CAST(text_crc32 AS BIGINT) AS text_crc32, 'key' AS law, CAST(shard AS INTEGER) AS shard,
       row_number() OVER (PARTITION BY shard ORDER BY bucket, doc_id, text_crc32, size) - 1 AS slot, CAST(grown_shard AS INTEGER) AS grown_shard
FROM placed
"""
