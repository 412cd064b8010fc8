import math
import random
from collections import Counter

import pytest

from prefpat.llm import ngram


def plain(texts, alpha=0.4):
    words = [(t or "").encode().lower().split() for t in texts]
    grams = lambda w, n: [tuple(w[i : i + n]) for i in range(len(w) - n + 1)]
    whole = {n: Counter(g for w in words for g in grams(w, n)) for n in (1, 2, 3)}
    out = []
    for w in words:
        own = {n: Counter(grams(w, n)) for n in (1, 2, 3)}
        count = lambda g: whole[len(g)][g] - own[len(g)][g]  # noqa: B023, E731
        rest = sum(whole[1].values()) - len(w)
        score, used = 0.0, Counter()
        for i in range(len(w) if rest else 0):
            factor = 1.0
            for n in range(min(3, i + 1), -1, -1):
                if n == 0:
                    score, used[0] = score + math.log(factor / rest), used[0] + 1
                elif (c := count(tuple(w[i - n + 1 : i + 1]))) > 0:
                    below = count(tuple(w[i - n + 1 : i])) if n > 1 else rest
                    score, used[n] = score + math.log(factor * c / below), used[n] + 1
                    break
                factor *= alpha
        out.append((len(w), score, *(used[n] for n in range(4))))
    return out


def test_scores_match_brute_force(spark, monkeypatch):
    random.seed(3)
    vocabulary = [f"w{i}" for i in range(60)] + ["Ü", "THE", "the"]
    texts = [" ".join(random.choices(vocabulary, weights=[1 / (i + 1) for i in range(63)], k=random.randint(0, 80))) for _ in range(150)]
    texts += [None, "", " \n", texts[3], texts[3], "only here once", "x " * 20000]
    df = spark.createDataFrame([(i, t, 1, "y") for i, t in enumerate(texts)], "doc_id long, text string, block int, words string").repartition(7)
    got = {r.key: r for r in ngram.backoff_scores(df, "doc_id", "text").collect()}
    assert len(got) == len(texts)
    for i, want in enumerate(plain(texts)):
        r = got[i]
        assert (r.n_words, r.used_0, r.used_1, r.used_2, r.used_3) == (want[0], *want[2:]), i
        assert r.log_score == pytest.approx(want[1], abs=1e-6)


def test_many_small_blocks_score_alike(monkeypatch):
    texts = [b"a b c a b", b"b c a", b"", b"c a b c d", None]
    grams, owner, at = ngram.hashed_texts(texts)
    assert [int((g > 0).sum()) for g in grams] == [13, 10, 7]
    hashes, counts = ngram.counted(grams)
    assert (ngram.unsqueeze_sorted(ngram.squeeze_sorted(hashes)) == hashes).all() and (ngram.unsqueeze(ngram.squeeze(counts)) == counts).all()
    whole = ngram.scored(texts, 0 * counts, 13)
    want = plain([t.decode() if t else t for t in texts])
    assert list(whole[0]) == [w[0] for w in want] and whole[1] == pytest.approx([w[1] for w in want])


def test_one_text_and_no_rows(spark):
    df = spark.createDataFrame([(1, "alone in the corpus")], "doc_id long, text string")
    r = ngram.backoff_scores(df, "doc_id", "text").first()
    assert r.n_words == 4 and r.log_score == 0.0
    assert ngram.backoff_scores(df.limit(0), "doc_id", "text").count() == 0
