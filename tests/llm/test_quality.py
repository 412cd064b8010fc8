import math
import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from prefpat.llm import quality

SPACE = " \t\n\x0b\x0c\r"


def plain(text):
    text = text or ""
    words = [w for w in re.split(f"[{SPACE}]+", text) if w]
    windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    seen = Counter(windows)
    covered = {i + k for i, w in enumerate(windows) if seen[w] > 1 for k in range(3)}
    lines = [x for x in text.split("\n") if re.search(f"[^{SPACE}]", x)]
    return len(words), sum(map(len, words)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(covered)


TEXTS = [
    None, "", " \n\t", "one", "a b c", "a b c d", "a b c a b c", "a a a", "a a a a a a", "a b a b a b a", "x\ny\nx\n\n x\nx ",
    "the cat sat the cat sat on the cat sat", "ü ö # $$ %|<>&*     é", "\x0bA\x0cb\rc", " lead and trail ", "a b c x a b c y b c x a",
    " ".join(str(i % 700) for i in range(5000)), " ".join(str(i) for i in range(3000)), "w" * 100000, "line\n" * 400, "😀 😀 😀 😀",
]


def test_counts_match_brute_force(spark):
    df = spark.createDataFrame([(i, t, "clash", 7) for i, t in enumerate(TEXTS)], "doc_id long, text string, n_words string, score int")
    got = {r.key: (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in quality.measures(df, "doc_id", "text").collect()}
    assert got == {i: plain(t) for i, t in enumerate(TEXTS)}


def test_binomial_tail_is_exact(spark):
    cases = [(0, 1), (0, 500), (1, 500), (3, 700), (9, 500), (10, 500), (250, 20000), (5, 100000)]
    df = spark.createDataFrame(cases, "k int, n int")
    for r in df.withColumn("p", quality.binomial_tail(F.col("k"), F.col("n"), 0.02)).collect():
        want = 1.0 if r.k >= 0.02 * r.n else sum(math.exp(math.lgamma(r.n + 1) - math.lgamma(i + 1) - math.lgamma(r.n - i + 1) + i * math.log(0.02) + (r.n - i) * math.log(0.98)) for i in range(r.k + 1))
        assert r.p == pytest.approx(want, rel=1e-6)


def labelled(spark, n_good, n_bad, overlap=0):
    rows = [(i, " ".join(f"w{i}x{j}" for j in range(60))) for i in range(n_good)]
    rows += [(n_good + i, " ".join(f"w{j}#" for j in range(60))) for i in range(n_bad)]
    labels = [(i, 1) for i in range(n_good - overlap)] + [(i, 0) for i in range(n_good - overlap, n_good + n_bad)] + [(None, 0), (n_good, None), (10**6, 1)]
    return spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int")


def test_cutoffs_need_enough_proof(spark):
    for n_good, proven in ((150, False), (400, True)):
        df, labels = labelled(spark, n_good, 50)
        cutoffs = quality.safe_cutoffs(quality.measures(df, "doc_id", "text"), labels, "doc_id", "quality").collect()
        assert bool(cutoffs) == proven
        kept = quality.keep_good(df, "doc_id", "text", labels, "quality").count()
        assert kept == (n_good if proven else n_good + 50)


def test_keep_good_returns_whole_rows(spark):
    df, labels = labelled(spark, 400, 30)
    df = df.select("doc_id", "text", F.lit("a").alias("row"), F.lit(1).alias("stratum"), F.lit(2).alias("kept")).union(spark.createDataFrame([(None, None, "b", 3, 4)], "doc_id long, text string, row string, stratum int, kept int"))
    out = quality.keep_good(df, "doc_id", "text", labels, "quality")
    assert out.columns == ["doc_id", "text", "row", "stratum", "kept"]
    assert out.count() == 401


def test_no_rows(spark):
    df, labels = labelled(spark, 3, 1)
    assert quality.keep_good(df.limit(0), "doc_id", "text", labels, "quality").count() == 0
    assert quality.keep_good(df, "doc_id", "text", labels.limit(0), "quality").count() == 4
