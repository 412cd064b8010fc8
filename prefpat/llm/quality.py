"""Quality rules with risk-controlled thresholds, in DataFrame functions only.

Measures. Words, characters in words, symbols, lines that repeat an earlier line
and words in repeated three-word windows are counted per text inside one row, so
a text is never exploded or shuffled. Repeated windows are found by sorting the
window hashes with the position in their low bits; neighbours with equal hashes
are compared word by word.

Score. Four ratios (symbols, exclamation marks and repeated words per word,
repeated lines per line), each divided by a usual limit; the largest is a text's
score. Its cutoff is chosen in each stratum (a class of length, a fixed number)
from labelled texts: a cutoff is safe if an exact binomial test rejects, from
the good texts that it would reject, that more than ``risk`` of all good texts
of the stratum would be. Cutoffs are tested from lenient to strict and testing
stops at the first that is not safe, which needs no correction inside a stratum;
the error rate is divided by the number of strata and one for all of them together
(Bonferroni), so that with probability ``1 - error`` no stratum rejects more than
``risk`` of its good texts. Of the safe cutoffs the one that serves best is used: most
bad texts rejected, less ``good_weight`` times the good ones. A stratum with too few
good labels for any proof takes the cutoff of all strata together, whose promise is
about all good texts; without that too, only the base rule acts there. The promise
covers what a cutoff rejects and not what the base rule does.

Defined cases: a null or blank text has no words and fails the base rule; labels
with a null key or value are ignored, of several labels of a key the worst
counts; labels without a text play no part; repeated rows are judged alike; an
empty table gives no rows. Only key and text (and key and label) are read, so
other columns, whatever their names, play no part.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from prefpat.llm.common import SPACE_CHARS, WORD_CHAR_RE, cut, let, read_table, words_of

#: Symbols that count, and each ratio's usual limit.
SYMBOLS = "#*$%&|<>"
LIMITS = {"n_symbols": 0.1, "n_bangs": 0.1, "n_repeat_words": 0.2, "n_dup_lines": 0.3}
#: Cutoffs from lenient to strict, in units of the usual limit.
CUTOFFS = (8.0, 6.0, 5.0, 4.0, 3.0, 2.5, 2.0, 1.75, 1.5, 1.25, 1.0, 0.8, 0.6, 0.5, 0.4, 0.3)
#: First number of words of each length stratum.
STRATA = (0, 150, 600)
RISK, ERROR, GOOD_WEIGHT = 0.02, 0.05, 10.0
#: The number under which all strata are tested together.
POOLED = -1


def without(text: Column, characters: str) -> Column:
    for c in characters:
        text = F.replace(text, F.lit(c), F.lit(""))
    return text


def repeat_words(words: Column) -> Column:
    """Words covered by three-word windows that occur twice or more."""

    def covered(w: Column) -> Column:
        n = F.size(w)
        bits = F.length(F.bin(n.cast("long")))

        def sorted_keys(mask: Column) -> Column:
            key = lambda i: F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)).bitwiseAND(F.bitwise_not(mask)).bitwiseOR(i.cast("long"))
            return let(F.sort_array(F.transform(F.sequence(F.lit(0), n - 3), key)), lambda keys: marked(keys, mask))

        def marked(keys: Column, mask: Column) -> Column:
            place = lambda j: F.get(keys, j).bitwiseAND(mask).cast("int")
            alike = lambda j, k: F.get(keys, j).bitwiseAND(F.bitwise_not(mask)) == F.get(keys, k).bitwiseAND(F.bitwise_not(mask))
            same = lambda j: alike(j, j + 1) & (F.get(w, place(j)) == F.get(w, place(j + 1))) & (F.get(w, place(j) + 1) == F.get(w, place(j + 1) + 1)) & (F.get(w, place(j) + 2) == F.get(w, place(j + 1) + 2))
            last = n - 4  # the last neighbour pair's first index
            return let(
                F.filter(F.sequence(F.lit(0), last), same),
                lambda first: F.when(F.size(first) == 0, F.lit(0).cast("long")).otherwise(total(F.sort_array(F.array_distinct(F.transform(F.concat(first, F.transform(first, lambda j: j + 1)), place))))),
            )

        def total(places: Column) -> Column:
            start = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-3).alias("end"))
            step = lambda s, p: F.struct((s["n"] + p + 3 - F.greatest(p, s["end"])).cast("long").alias("n"), (p + 3).alias("end"))
            return F.aggregate(places, start, step, lambda s: s["n"])

        return F.when(n < 4, F.lit(0).cast("long")).otherwise(let(F.call_function("shiftleft", F.lit(1).cast("long"), bits) - 1, sorted_keys))

    return let(words, covered)


def measures(df: DataFrame, key: str, text: str) -> DataFrame:
    """The key, the counts, the score and the stratum of every row."""
    return df.select(F.col(f"`{key}`").alias("key"), *measure_columns(F.col(f"`{text}`"))).select("*", *judged_columns())


def measure_columns(column: Column) -> list[Column]:
    text = F.coalesce(column, F.lit(""))
    words = words_of(text)
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD_CHAR_RE))
    counted = let(lines, lambda x: F.struct(F.size(x).alias("n"), (F.size(x) - F.size(F.array_distinct(x))).alias("dup")))
    worded = let(words, lambda w: F.struct(F.size(w).cast("long").alias("n"), repeat_words(w).alias("rep")))
    return [
        worded.alias("_words"),
        F.length(without(text, SPACE_CHARS)).cast("long").alias("word_chars"),
        (F.length(text) - F.length(without(text, SYMBOLS))).cast("long").alias("n_symbols"),
        (F.length(text) - F.length(without(text, "!"))).cast("long").alias("n_bangs"),
        counted.alias("_lines"),
    ]


def judged_columns() -> list[Column]:
    n, lines = F.greatest(F.col("_words.n"), F.lit(1)), F.greatest(F.col("_lines.n"), F.lit(1))
    ratios = {"n_symbols": F.col("n_symbols") / n, "n_bangs": F.col("n_bangs") / n, "n_repeat_words": F.col("_words.rep") / n, "n_dup_lines": F.col("_lines.dup") / lines}
    stratum = sum(((F.col("_words.n") >= first).cast("int") for first in STRATA[1:]), F.lit(0))
    return [
        F.col("_words.n").alias("n_words"),
        F.col("_lines.dup").cast("long").alias("n_dup_lines"),
        F.col("_words.rep").alias("n_repeat_words"),
        F.greatest(*[ratios[k] / F.lit(limit) for k, limit in LIMITS.items()]).alias("score"),
        stratum.alias("stratum"),
        ((F.col("_words.n") < 50) | (100 * F.col("_words.rep") > 50 * F.col("_words.n"))).alias("base_failed"),
    ]


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(X <= k) for X binomial(n, p): exact, by ratios of neighbouring terms.

    The last term comes from logarithms and the others from it downwards, so
    nothing underflows. From the mean on, where no test can succeed, it is 1.
    """
    up = F.aggregate(F.sequence(F.lit(1), k), F.lit(0.0), lambda s, j: s + F.ln((n - k + j) / j))
    log_last = F.when(k < 1, F.lit(0.0)).otherwise(up) + k * math.log(p) + (n - k) * math.log1p(-p)
    start = F.struct(F.lit(1.0).alias("term"), F.lit(1.0).alias("total"))

    def down(s: Column, i: Column) -> Column:
        m = k - i
        term = s["term"] * m * (1 - p) / ((n - m + 1) * p)
        return F.struct(term.alias("term"), (s["total"] + term).alias("total"))

    total = F.when(k < 1, F.lit(1.0)).otherwise(F.aggregate(F.sequence(F.lit(0), k - 1), start, down, lambda s: s["total"]))
    return F.when(k >= n * p, F.lit(1.0)).otherwise(F.least(F.lit(1.0), F.exp(log_last) * total))


def safe_cutoffs(measured: DataFrame, labels: DataFrame, key: str, good: str, risk: float = RISK, error: float = ERROR, good_weight: float = GOOD_WEIGHT) -> DataFrame:
    """``(stratum, cutoff)``, at most one row for each stratum.

    Labelled rows are counted by stratum and step of the cutoff scale before
    anything is gathered; all later frames have at most strata * cutoffs rows.
    """
    known = labels.where(F.col(f"`{key}`").isNotNull() & F.col(f"`{good}`").isNotNull())
    known = known.groupBy(F.col(f"`{key}`").alias("key")).agg(F.min(F.col(f"`{good}`").cast("int")).alias("good"))
    step = sum(((F.col("score") < c).cast("int") for c in CUTOFFS), F.lit(0))
    counts = measured.select("key", "stratum", step.alias("step")).join(known, "key").groupBy("stratum", "step").agg(F.count_if(F.col("good") == 1).alias("goods"), F.count_if(F.col("good") == 0).alias("bads"))
    counts = cut(counts)  # a few rows that are used several times, behind a pass over all texts
    counts = counts.unionByName(counts.groupBy(F.lit(POOLED).alias("stratum"), "step").agg(F.sum("goods").alias("goods"), F.sum("bads").alias("bads")))
    wide = counts.groupBy("stratum").agg(F.sum("goods").alias("n"), F.collect_list(F.struct("step", "goods", "bads")).alias("steps"))
    part = lambda field: F.aggregate(F.filter("steps", lambda s: s["step"] <= F.col("at")), F.lit(0).cast("long"), lambda x, s: x + s[field])
    at = F.explode(F.array([F.struct(F.lit(i).alias("at"), F.lit(c).alias("cutoff")) for i, c in enumerate(CUTOFFS)]))
    tried = wide.select("stratum", "n", "steps", at.alias("t")).select("stratum", "n", "steps", "t.at", "t.cutoff").select("stratum", "n", "at", "cutoff", part("goods").alias("wrong"), part("bads").alias("right"))
    tested = tried.withColumn("p_value", binomial_tail(F.col("wrong").cast("int"), F.col("n").cast("int"), risk))
    so_far = Window.partitionBy("stratum").orderBy("at").rowsBetween(Window.unboundedPreceding, 0)
    level = error / (len(STRATA) + 1)
    safe = tested.withColumn("worst", F.max("p_value").over(so_far)).where(F.col("worst") <= level)
    gain = F.col("right") - good_weight * F.col("wrong")
    best = safe.groupBy("stratum").agg(F.max(F.struct(gain.alias("gain"), (-F.col("at")).alias("lenient"), "cutoff")).alias("best")).where("best.gain > 0")
    known = wide.join(best, "stratum", "left").select("stratum", F.struct(F.col("best.cutoff").alias("cutoff"), (F.pow(F.lit(1 - risk), F.col("n")) <= level).alias("provable")).alias("own"))
    every = known.agg(F.map_from_entries(F.collect_list(F.struct("stratum", "own"))).alias("known"))
    own = F.try_element_at("known", F.col("stratum"))
    cutoff = F.when(F.coalesce(own["provable"], F.lit(False)), own["cutoff"]).otherwise(F.try_element_at("known", F.lit(POOLED))["cutoff"])
    each = every.select("known", F.explode(F.sequence(F.lit(0), F.lit(len(STRATA) - 1))).alias("stratum"))
    return each.select("stratum", cutoff.alias("cutoff")).where("cutoff is not null")


def judge(measured: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """Adds ``kept``. The cutoffs are at most one row a stratum: a proven bound."""
    joined = measured.join(F.broadcast(cutoffs), "stratum", "left")
    return joined.withColumn("kept", ~F.col("base_failed") & F.coalesce(F.col("score") < F.col("cutoff"), F.lit(True)))


def keep_good(df: DataFrame, key: str, text: str, labels: DataFrame, good: str) -> DataFrame:
    """The rows of ``df`` that the rules keep, all columns as they were.

    Of the base rule only repetition acts here: a short text is no bad text. The
    texts are measured twice, once for the cutoffs and once for the verdict;
    carrying verdicts back to them by a join would shuffle every text.
    """
    cutoffs = cut(safe_cutoffs(measures(df, key, text), labels, key, good))
    tagged = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), *measure_columns(F.col(f"`{text}`")))
    measured = tagged.select("row", *judged_columns()).withColumn("base_failed", 100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return judge(measured, cutoffs).where("kept").select("row.*")


def op7_quality(spark, sf_dir):
    """Counts, base rule and verdict for all documents, cutoffs from ``labels``."""
    measured = cut(measures(read_table(spark, sf_dir, "documents"), "doc_id", "text"))
    cutoffs = safe_cutoffs(measured, read_table(spark, sf_dir, "labels"), "doc_id", "quality")
    counts = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]
    return judge(measured, cutoffs).select(F.col("key").alias("doc_id"), *counts)


OP7_SQL = r"""
WITH docs AS (
  SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents
), split AS (
  SELECT r, doc_id, text, list_filter(regexp_split_to_array(text, '[ \t\n\x0B\f\r]+'), lambda w: w <> '') AS w,
         list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^ \t\n\x0B\f\r]')) AS l
  FROM docs
), grams AS (
  SELECT r, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM split, unnest(range(1, len(w) - 1)) AS u(i)
), repeats AS (
  SELECT r, i FROM grams QUALIFY count(*) OVER (PARTITION BY r, g) > 1
), covered AS (
  SELECT r, count(DISTINCT i + k) AS n FROM repeats, unnest([0, 1, 2]) AS o(k) GROUP BY r
), counts AS (
  SELECT s.r, doc_id, CAST(len(w) AS BIGINT) AS n_words,
         CAST(length(regexp_replace(text, '[ \t\n\x0B\f\r]', '', 'g')) AS BIGINT) AS word_chars,
         CAST(length(regexp_replace(text, '[^#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols,
         length(regexp_replace(text, '[^!]', '', 'g')) AS n_bangs,
         CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines, len(l) AS n_lines, CAST(coalesce(c.n, 0) AS BIGINT) AS n_repeat_words
  FROM split s LEFT JOIN covered c ON c.r = s.r
), scored AS (
  SELECT *, greatest(n_symbols / greatest(n_words, 1) / 0.1, n_bangs / greatest(n_words, 1) / 0.1, n_repeat_words / greatest(n_words, 1) / 0.2, n_dup_lines / greatest(n_lines, 1) / 0.3) AS score,
         CASE WHEN n_words >= 600 THEN 2 WHEN n_words >= 150 THEN 1 ELSE 0 END AS stratum,
         n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed
  FROM counts
), known AS (
  SELECT doc_id, min(quality) AS good FROM labels WHERE quality IS NOT NULL GROUP BY doc_id
), scale AS (
  SELECT unnest([8.0, 6.0, 5.0, 4.0, 3.0, 2.5, 2.0, 1.75, 1.5, 1.25, 1.0, 0.8, 0.6, 0.5, 0.4, 0.3]) AS cutoff, unnest(range(16)) AS pos
), placed AS (
  SELECT stratum, score, good FROM scored JOIN known USING (doc_id) UNION ALL SELECT -1, score, good FROM scored JOIN known USING (doc_id)
), tried AS (
  SELECT stratum, pos, cutoff, count(*) FILTER (good = 1) AS n, count(*) FILTER (good = 1 AND score >= cutoff) AS wrong, count(*) FILTER (good = 0 AND score >= cutoff) AS "right"
  FROM placed CROSS JOIN scale GROUP BY ALL
), tested AS (
  SELECT *, list_sum(list_transform(range(wrong + 1), lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln(0.02) + (n - i) * ln(0.98)))) AS p FROM tried WHERE n > 0
), safe AS (
  SELECT *, max(p) OVER (PARTITION BY stratum ORDER BY pos) AS worst FROM tested
), best AS (
  SELECT stratum, cutoff, "right" - 10 * wrong AS gain FROM safe WHERE worst <= 0.05 / 4
  QUALIFY row_number() OVER (PARTITION BY stratum ORDER BY "right" - 10 * wrong DESC, pos) = 1
), goods AS (
  SELECT stratum, count(*) FILTER (good = 1) AS n FROM placed GROUP BY stratum
), cutoffs AS (
  SELECT s.stratum, CASE WHEN 0.98 ** coalesce(g.n, 0) <= 0.05 / 4 THEN own.cutoff ELSE pooled.cutoff END AS cutoff
  FROM range(3) AS s(stratum) LEFT JOIN goods g ON g.stratum = s.stratum LEFT JOIN best own ON own.stratum = s.stratum AND own.gain > 0 LEFT JOIN best pooled ON pooled.stratum = -1 AND pooled.gain > 0
)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND coalesce(score < cutoff, true) AS kept
FROM scored LEFT JOIN cutoffs USING (stratum)
"""
