import duckdb
import pandas as pd
import pytest

import corpus_pipeline
from prefpat.llm import linededup, quality, simhash
from test_packing import check
from test_quality import plain as plain_counts
from test_simhash import plain_components

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    """The stages' results, each written and read again."""
    folder = tmp_path_factory.mktemp("stages")
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    results = [("documents", docs)]
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        results.append((name, docs))
    return dict(results)


def texts(df):
    return {r.doc_id: r.text for r in df.select("doc_id", "text").collect()}


def test_columns(stages):
    columns = stages["documents"].columns
    assert [stages[n].columns == columns for n, _ in corpus_pipeline.STAGES] == [True] * 4 + [False]


def test_quality_stage(spark, stages):
    before, after = texts(stages["documents"]), texts(stages["quality_rules"])
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    cutoffs = {r.stratum: r.cutoff for r in quality.safe_cutoffs(quality.measures(stages["documents"], "doc_id", "text"), labels, "doc_id", "quality").collect()}
    want = set()
    for key, text in before.items():
        n, _, symbols, dup_lines, repeats = plain_counts(text)
        lines = sum(bool(x.strip(" \t\n\x0b\x0c\r")) for x in text.split("\n"))
        score = max(symbols / max(n, 1) / 0.1, text.count("!") / max(n, 1) / 0.1, repeats / max(n, 1) / 0.2, dup_lines / max(lines, 1) / 0.3)
        stratum = (n >= 150) + (n >= 600)
        if 100 * repeats <= 50 * n and score < cutoffs.get(stratum, float("inf")):
            want.add(key)
    assert set(after) == want and all(after[k] == before[k] for k in after)


def test_language_stage(stages):
    before, after = texts(stages["quality_rules"]), texts(stages["language_id"])
    assert set(after) <= set(before)
    gone = [t for k, t in before.items() if k not in after]
    assert len(gone) <= 0.02 * len(before) + sum(not any(c.isalpha() for c in t) for t in gone)


def test_line_stage(stages):
    documents = pd.DataFrame(list(texts(stages["language_id"]).items()), columns=["doc_id", "text"])  # noqa: F841
    want = duckdb.sql(f"SELECT doc_id, text FROM ({linededup.OP10_SQL})").fetchall()
    assert texts(stages["line_dedup"]) == dict(want)


def test_near_stage(stages):
    before = sorted(texts(stages["line_dedup"]).items())
    pairs = [simhash.text_fingerprints(t.encode(), 5, True) for _, t in before]
    root = list(range(len(before)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(before)):
        for j in range(i):
            one, two = ((a ^ b).bit_count() for a, b in zip(pairs[i], pairs[j]))
            if one <= 10 and one + two <= 20:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    want = {k: t for i, (k, t) in enumerate(before) if find(i) == i}
    assert texts(stages["near_dedup"]) == want
    assert plain_components([(k, p[0]) for (k, _), p in zip(before, pairs)], 0)  # the shared helper runs on these too


def test_packing_stage_and_run(spark, stages):
    left = texts(stages["near_dedup"])
    rows = corpus_pipeline.run(spark, SF).withColumnRenamed("doc_id", "key").collect()
    check(rows, {k: [t] for k, t in left.items()}, 2048)


def test_stages_take_odd_rows(spark):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    odd = [(None, None, None, None, None), (1, None, "en", "s", 0), (2, "", "en", "s", 0), (2, "", "en", "s", 0), (3, "word " * 9, None, None, 5), (3, "word " * 9, None, None, 5), (None, "a b c", "en", None, None)]
    for rows in (odd, []):
        df = spark.createDataFrame(rows, schema)
        for _, stage in corpus_pipeline.STAGES:
            stage(spark, df, SF).collect()


def test_exact_copies_leave_one(spark):
    rows = [(i, "the same text of a few words that is long enough to have shingles", "en", "s", i) for i in range(50, 0, -1)] + [(7, "another text", "en", "s", 1), (None, "another text", "en", "s", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r.doc_id for r in corpus_pipeline.near_dedup(spark, df, SF).collect()) == [1, 7]
