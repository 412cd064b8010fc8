"""Line dedup on content-defined chunks, in DataFrame functions only.

Chunks. A rolling hash over two neighbouring lines sets a boundary where it falls on a
residue, so a boundary depends on the lines next to it alone and survives any shift.
Lines without a word play no part. A passage that several texts share may begin and end
between two boundaries, so a chunk is read from every line on: forward to the first
boundary that gives it two lines and ``LEAST_WORDS`` words, and backward likewise; what
sets its end are lines of its own. Where no boundary comes before it holds
``LONG_LINE`` words it ends there, by content as well. A shared passage of that many
words therefore has a chunk from its first line on and one back from its last line
inside it, whatever stands around it and however its lines are cut; what its chunks
may leave in between has fewer than ``LEAST_WORDS`` words or is one line.

Removal. Chunk hashes are counted over all texts (with partial counts before the
shuffle); chunks whose hash occurs again are fetched and their bytes compared.
The first occurrence in the order of key, text hash and line stays, the lines of
the others go. What is removed stands in an earlier place, so nothing that the
corpus says is lost.

Defined cases: a null text stays null, with no lines; a null key sorts first;
rows that repeat both key and text are one text and stay alike; an empty table
gives no rows; a text of which all lines go is the empty text. Other columns are
carried along as they are, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from prefpat.llm.common import WORD_CHAR_RE, cut, let, read_table

#: One boundary in this many places, on average.
DIVISOR = 2
#: The factor of the rolling hash, and one that mixes its high bits.
ROLL, MIX = 31, 2654435761
LONG_LINE = 50
LEAST_WORDS = 10
#: Lines tried first for a chunk's end; ``LONG_LINE`` lines always hold enough words.
FEW_LINES = 4


def spans_of(text: Column) -> Column:
    """Array of ``(start, end, hash)``: the chunks of a text, by line numbers."""
    digit = lambda x: F.conv(F.substring(F.md5(x), 1, 6), 16, 10).cast("long")
    counted = F.transform(F.split(text, "\n"), lambda x, i: F.struct(i.alias("i"), x.alias("x"), F.regexp_count(x, F.lit(WORD_CHAR_RE + "+")).alias("w")))
    facts = F.transform(F.filter(counted, lambda s: s["w"] > 0), lambda s: F.struct(s["i"].alias("i"), digit(s["x"]).alias("d"), s["w"].alias("w"), F.xxhash64(s["x"]).alias("h")))

    def bounded(f: Column) -> Column:
        """Adds whether a boundary stands behind the line, by it and the one before, and
        whether one stands before it, by it and the next."""
        at = lambda j: F.coalesce(F.get(f, j)["d"], F.lit(0).cast("long"))
        rolled = lambda i, j: F.shiftrightunsigned((at(i) * ROLL + at(j)) * F.lit(MIX), 16) % DIVISOR == 0
        return F.transform(f, lambda x, j: F.struct(x["i"].alias("i"), x["w"].alias("w"), x["h"].alias("h"), ((j == 0) | rolled(j + 1, j)).alias("before"), ((j == F.size(f) - 1) | rolled(j - 1, j)).alias("behind")))

    def size(lines: Column, boundary: str) -> Column:
        """How many of the lines, from the first on, make a chunk; null if they do not."""
        start = F.struct(F.lit(0).alias("n"), F.lit(0).alias("w"), F.lit(None).cast("int").alias("end"))

        def step(s: Column, x: Column) -> Column:
            n, w = s["n"] + 1, s["w"] + x["w"]
            ends = (w >= LONG_LINE) | (x[boundary] & (w >= LEAST_WORDS) & (n >= 2))
            return F.struct(n.alias("n"), w.alias("w"), F.coalesce(s["end"], F.when(ends, n)).alias("end"))

        return F.aggregate(lines, start, step, lambda s: s["end"])

    def span(f: Column, first: Column, n: Column) -> Column:
        own = F.slice(f, first + 1, n)
        whole = F.struct(F.get(f, first)["i"].alias("start"), (F.get(f, first + n - 1)["i"] + 1).alias("end"), F.xxhash64(F.transform(own, lambda x: x["h"])).alias("hash"))
        return F.when(n.isNotNull(), whole)

    def chunks(f: Column) -> Column:
        ahead = lambda j, most: size(F.slice(f, j + 1, most), "behind")
        back = lambda j, most: size(F.reverse(F.slice(f, F.greatest(j + 2 - most, F.lit(1)), F.least(j + 1, F.lit(most)))), "before")
        long = lambda x: F.when(x["w"] >= LONG_LINE, 1)
        forward = F.transform(f, lambda x, j: let(F.coalesce(long(x), ahead(j, FEW_LINES), ahead(j, LONG_LINE)), lambda n: span(f, j, n)))
        # forward chunks differ in their starts and backward ones in their ends, so a backward one
        # can repeat only the forward one from its own start
        new = lambda known, x, first: ~F.get(known, first)["end"].eqNullSafe(x["i"] + 1)
        backward = lambda known: F.transform(f, lambda x, j: let(F.coalesce(long(x), back(j, FEW_LINES), back(j, LONG_LINE)), lambda n: F.when(new(known, x, j - n + 1), span(f, j - n + 1, n))))
        return F.filter(let(forward, lambda known: F.concat(known, backward(known))), lambda s: s.isNotNull())

    return let(facts, lambda f: let(bounded(f), chunks))


def text_key(text: Column) -> Column:
    return F.xxhash64(text)


def repeated_spans(df: DataFrame, key: str, text: str) -> DataFrame:
    """``(key, text_hash, start, end, hash, first)`` of spans whose hash occurs more
    than once; ``first`` tells whether the row is the occurrence that stays."""
    spans = df.where(F.col(f"`{text}`").isNotNull()).select(
        F.col(f"`{key}`").alias("key"), text_key(F.col(f"`{text}`")).alias("text_hash"), F.explode(spans_of(F.col(f"`{text}`"))).alias("s")
    )
    spans = cut(spans.select("key", "text_hash", "s.start", "s.end", "s.hash"))  # counted and joined: made once
    place = F.struct("key", "text_hash", "start")
    again = spans.groupBy("hash").agg(F.count(F.lit(1)).alias("n"), F.min(place).alias("stays")).where("n > 1").select("hash", "stays")
    return spans.join(cut(again), "hash").select("key", "text_hash", "start", "end", "hash", place.eqNullSafe(F.col("stays")).alias("first"))


def same_text(left: DataFrame, right: DataFrame, how: str) -> DataFrame:
    """Join rows of the same key and text; null keys are equal to each other."""
    on = left["key"].eqNullSafe(right["key"]) & (left["text_hash"] == right["text_hash"])
    return left.join(right, on, how).drop(right["key"], right["text_hash"])


def removable_lines(df: DataFrame, key: str, text: str) -> DataFrame:
    """``(key, text_hash, gone)``: line numbers to remove, after byte comparison.

    A span inside another one that goes from the same text adds nothing, so only
    the outer ones and the occurrences that they repeat are fetched.
    """
    found = cut(repeated_spans(df, key, text).dropDuplicates(["key", "text_hash", "start", "end"]))
    before = Window.partitionBy("key", "text_hash").orderBy("start", F.desc("end")).rowsBetween(Window.unboundedPreceding, -1)
    outer = found.where("not first").withColumn("reach", F.max("end").over(before)).where("reach is null or end > reach").drop("reach")
    outer = cut(outer)
    needed = outer.unionByName(found.where("first").join(outer.select("hash").distinct(), "hash", "left_semi"))
    of_text = needed.groupBy("key", "text_hash").agg(F.collect_list(F.struct("start", "end", "hash")).alias("spans"))
    texts = df.select(F.col(f"`{key}`").alias("key"), text_key(F.col(f"`{text}`")).alias("text_hash"), F.col(f"`{text}`").alias("text"))
    lines = same_text(texts, of_text, "inner").select(F.split("text", "\n").alias("lines"), F.explode("spans").alias("s"))
    worded = F.filter(F.slice("lines", F.col("s.start") + 1, F.col("s.end") - F.col("s.start")), lambda x: x.rlike(WORD_CHAR_RE))
    bodies = lines.select("s.hash", F.array_join(worded, "\n").alias("body"))
    # equal bodies become one before the shuffle; a hash with two different ones is a collision
    equal = bodies.groupBy("hash", "body").agg(F.count(F.lit(1)).alias("n")).groupBy("hash").agg(F.count(F.lit(1)).alias("bodies")).where("bodies = 1").select("hash")
    gone = outer.join(cut(equal), "hash").select("key", "text_hash", F.explode(F.sequence(F.col("start"), F.col("end") - 1)).alias("line"))
    return gone.groupBy("key", "text_hash").agg(F.collect_set("line").alias("gone"))


def dedup_lines(df: DataFrame, key: str, text: str) -> DataFrame:
    """``row`` (all columns of ``df`` as a struct), the cleaned ``text``, ``n_lines``
    and ``n_removed``."""
    gone = cut(removable_lines(df, key, text))
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), F.col(f"`{key}`").alias("key"), text_key(F.col(f"`{text}`")).alias("text_hash"))
    joined = same_text(rows, gone, "left")
    lines = F.split(F.col("row")[text], "\n")
    left = lambda x: F.array_join(F.transform(F.array_except(F.sequence(F.lit(0), F.size(x) - 1), F.col("gone")), lambda i: F.get(x, i)), "\n")
    return joined.select(
        "row",
        F.when(F.col("gone").isNull(), F.col("row")[text]).otherwise(let(lines, left)).alias("text"),
        F.coalesce(F.size(lines), F.lit(0)).alias("n_lines"),
        F.coalesce(F.size("gone"), F.lit(0)).alias("n_removed"),
    )


def without_repeats(df: DataFrame, key: str, text: str) -> DataFrame:
    """``df`` with repeated passages removed from its texts."""
    cleaned = dedup_lines(df, key, text)
    return cleaned.select(*[F.col("text").alias(c) if c == text else F.col("row")[c].alias(c) for c in df.columns])


def op10_line_dedup(spark, sf_dir):
    """All documents without the passages that stand in an earlier place."""
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    done = dedup_lines(docs, "doc_id", "text")
    return done.select(F.col("row")["doc_id"].alias("doc_id"), "text", F.greatest("n_lines", F.lit(0)).cast("long").alias("n_lines"), F.greatest("n_removed", F.lit(0)).cast("long").alias("n_removed"))


OP10_SQL = r"""
WITH docs AS (
  SELECT doc_id, text, string_split(text, chr(10)) AS l FROM documents
), lines AS (
  SELECT doc_id, text, l, CAST(u.i AS BIGINT) AS i, l[u.i + 1] AS x FROM docs, unnest(range(len(l))) AS u(i)
), facts AS (
  SELECT doc_id, i, x, CAST('0x' || substr(md5(x), 1, 6) AS BIGINT) AS d,
         len(list_filter(regexp_split_to_array(x, '[ \t\n\x0B\f\r]+'), lambda w: w <> '')) AS w, row_number() OVER (PARTITION BY doc_id ORDER BY i) AS j
  FROM lines WHERE regexp_matches(x, '[^ \t\n\x0B\f\r]')
), closed AS MATERIALIZED (
  SELECT *, j = 1 OR ((lead(d) OVER o * 31 + d) * 2654435761 // 65536) % 2 = 0 OR (lead(d) OVER o IS NULL AND (d * 2654435761 // 65536) % 2 = 0) AS before,
         lead(d) OVER o IS NULL OR ((coalesce(lag(d) OVER o, 0) * 31 + d) * 2654435761 // 65536) % 2 = 0 AS behind
  FROM facts WINDOW o AS (PARTITION BY doc_id ORDER BY j)
), reach AS MATERIALIZED (
  SELECT a.doc_id, a.j AS a, b.j AS b, a.before, b.behind, sum(c.w) AS w
  FROM closed a JOIN closed b ON b.doc_id = a.doc_id AND b.j BETWEEN a.j AND a.j + 49 JOIN closed c ON c.doc_id = a.doc_id AND c.j BETWEEN a.j AND b.j GROUP BY ALL
), spans AS (
  SELECT doc_id, a, min(b) AS b FROM reach WHERE w >= 50 OR (behind AND w >= 10 AND b > a) GROUP BY doc_id, a
  UNION
  SELECT doc_id, max(a) AS a, b FROM reach WHERE w >= 50 OR (before AND w >= 10 AND b > a) GROUP BY doc_id, b
), bodies AS (
  SELECT s.doc_id, min(c.i) AS lo, max(c.i) + 1 AS hi, string_agg(c.x, chr(10) ORDER BY c.i) AS body
  FROM spans s JOIN closed c ON c.doc_id = s.doc_id AND c.j BETWEEN s.a AND s.b GROUP BY s.doc_id, s.a, s.b
), counted AS (
  SELECT *, count(*) OVER (PARTITION BY body) AS n, row_number() OVER (PARTITION BY body ORDER BY doc_id, lo) AS r FROM bodies
), gone AS (
  SELECT DISTINCT doc_id, i FROM counted, unnest(range(lo, hi)) AS u(i) WHERE n > 1 AND r > 1
), kept AS (
  SELECT l.doc_id, string_agg(l.x, chr(10) ORDER BY l.i) FILTER (g.i IS NULL) AS text, count(*) AS n_lines, count(g.i) AS n_removed
  FROM lines l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.i = l.i GROUP BY l.doc_id
)
SELECT d.doc_id, CASE WHEN d.text IS NULL THEN NULL ELSE coalesce(k.text, '') END AS text, coalesce(n_lines, 0) AS n_lines, coalesce(n_removed, 0) AS n_removed
FROM docs d LEFT JOIN kept k ON k.doc_id = d.doc_id
"""
