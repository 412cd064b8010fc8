import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefpat.llm import langid

SYLLABLES = {"aa": ["ka", "to", "mi", "re"], "bb": ["sch", "ung", "ein", "ber"], "cc": ["éau", "què", "oux", "tré"]}


def rows(n, seed=1):
    random.seed(seed)
    out = []
    for i in range(n):
        lang = random.choice(list(SYLLABLES))
        out.append((i, " ".join("".join(random.choices(SYLLABLES[lang], k=random.randint(1, 4))) for _ in range(random.randint(5, 200))), lang))
    return out


def test_held_out_accuracy(spark):
    df = spark.createDataFrame(rows(900), "doc_id long, text string, lang string")
    model = langid.learn(df, "doc_id", "text", "lang")
    assert model.languages == ("aa", "bb", "cc")
    told = df.select("lang", langid.is_held_out(F.col("doc_id")).alias("held"), langid.predict_column(model, F.col("text")).alias("p")).where("held")
    n, right, low, high = told.agg(F.count(F.lit(1)), F.count_if(F.col("p.lang") == F.col("lang")), F.min("p.score"), F.max("p.score")).first()
    assert n > 150 and right / n > 0.98
    assert 0 <= low <= high <= 1


def test_held_out_rows_do_not_teach(spark):
    df = spark.createDataFrame(rows(300), "doc_id long, text string, lang string")
    wrong = df.withColumn("lang", F.when(langid.is_held_out(F.col("doc_id")), F.lit("zz")).otherwise(F.col("lang")))
    assert langid.learn(wrong, "doc_id", "text", "lang").languages == ("aa", "bb", "cc")


def test_real_documents(spark):
    r = langid.op5_langid(spark, "/root/testdata/sf0.01").join(spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "lang"), "doc_id")
    n, right, accepted = r.where("held_out").agg(F.count(F.lit(1)), F.count_if(F.col("lang_pred") == F.col("lang")), F.count_if("accepted")).first()
    assert right / n >= 0.99 and accepted / n >= 0.99


def test_odd_rows(spark):
    odd = [(1000, None, "aa"), (1001, "", "aa"), (1002, "12 ² !!", "bb"), (None, "kato mire", None), (1003, "kato " * 50000, None), (1004, "kato", None), (1004, "kato", None)]
    df = spark.createDataFrame([(*r, "x", 0.5) for r in rows(300) + odd], "doc_id long, text string, lang string, score string, p double")
    model = langid.learn(df, "doc_id", "text", "lang")
    got = {r.doc_id: (r.q.lang, r.q.score, r.q.accepted) for r in df.where("doc_id >= 1000 or doc_id is null").select("doc_id", langid.predict_column(model, F.col("text")).alias("q")).collect()}
    assert got[1000] == got[1001] == got[1002] == ("und", 0.0, False)
    assert got[None][0] == got[1003][0] == "aa" and got[1003][2] and got[1003][1] > got[1004][1]
    kept = langid.keep_known(df, "doc_id", "text", "lang")
    assert kept.columns == df.columns and kept.where("doc_id in (1000, 1001, 1002)").count() == 0


def test_nothing_to_learn(spark):
    df = spark.createDataFrame([(0, "kato", None), (1, None, "aa")], "doc_id long, text string, lang string")
    assert langid.learn(df, "doc_id", "text", "lang") is None
    assert langid.keep_known(df, "doc_id", "text", "lang").count() == 0
    assert langid.keep_known(df.limit(0), "doc_id", "text", "lang").count() == 0


def made_languages(rng, names, n):
    letters = {"aa": "abcdefg", "bb": "hijklmn", "cc": "opqrstu"}
    word = lambda name: "".join(rng.choice(list(letters[name]), rng.integers(2, 8)))
    return [(i, " ".join(word(name) for _ in range(rng.integers(20, 80))), name) for i, name in enumerate(names * n)]


def test_prediction_equals_the_plain_sum(spark):
    """A text's mean of table rows, multiplied out word by word."""
    rows = made_languages(np.random.default_rng(1), ["aa", "bb", "cc"], 60)
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.learn(df, "doc_id", "text", "lang")
    got = {r.doc_id: r.p for r in df.select("doc_id", langid.predict_column(model, df.text).alias("p")).collect()}
    for i, text, _ in rows[::7]:
        total, n = np.zeros(len(model.languages)), 0
        for w in text.lower().split():
            for row in langid.subword_rows(w):
                total, n = total + model.table[row], n + 1
        logits = (total / (n + langid.PRIOR) + model.bias) / model.temperature
        chances = np.exp(logits - logits.max())
        chances /= chances.sum()
        assert got[i].lang == model.languages[int(chances.argmax())] and got[i].score == pytest.approx(chances.max(), abs=1e-4)


def test_rejection_is_calibrated(spark):
    """Few texts of the learned languages fall; most of what is none of them does."""
    rng = np.random.default_rng(2)
    rows = made_languages(rng, ["aa", "bb"], 1500)
    other = [(10_000 + i, t, None) for i, t, _ in made_languages(rng, ["cc"], 200)]
    df = spark.createDataFrame(rows + other, "doc_id long, text string, lang string")
    model = langid.learn(df, "doc_id", "text", "lang")
    kept = {r.doc_id: r.p.accepted for r in df.select("doc_id", langid.predict_column(model, df.text).alias("p")).collect()}
    own = np.mean([kept[i] for i, _, _ in rows])
    strange = np.mean([kept[i] for i, _, _ in other])
    assert own >= 0.98 and strange <= 0.5
