"""Language identification by averaged hashed subword embeddings.

Every word gives itself and its letter n-grams, with marked word ends; each is
hashed to a row of an embedding table. A text is the average of its rows, over
the whole text, and a linear softmax over it gives the languages. Both parts are
trained together by stochastic gradient descent in numpy on the driver.

Training sees a bounded sample: of each learned language's rows those with the
smallest hashes of their keys, ``PER_LANGUAGE`` of them, ``SAMPLE_ROWS`` in all.
Only hashed counts of whole texts come to the driver, at most ``BUCKETS`` for a
row; of more than ``LANGUAGES`` languages the commonest are learned.

Other rows, ``CALIBRATION_ROWS`` at most, calibrate; only their scores come to the
driver. A temperature makes scores probabilities, and of the ``n`` best scores the k-th
least rejects what is below it, k being ``REJECTED`` times n + 1, rounded down. A text
like those learned from is then rejected with a chance of at most ``REJECTED``; where
the rows are too few to show that, nothing but texts without a letter is rejected.

For prediction the two linear maps are multiplied into one table of rows by
languages, a few hundred kilobytes that do not grow with the input; words met
before are looked up by their sums.

Defined cases: null text, or text without a letter: ``und``, score 0, rejected;
rows with a null key, text or language are not learned from; without any learned
language all is ``und``; repeated rows are predicted alike; an empty table gives
no rows. Only the named columns are read.
"""

from __future__ import annotations

import functools
import re
import zlib
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.llm.common import read_table

BUCKETS = 1 << 14
DIMENSIONS = 16
GRAMS = (2, 3, 4)
PER_LANGUAGE = 400
SAMPLE_ROWS = 4096
EPOCHS = 6
RATE = 4.0
REJECTED = 0.002
CALIBRATION_ROWS = 8192
#: Most languages that are learned.
LANGUAGES = 512
#: Neutral subwords added to every text, so that a short one is not told surely.
PRIOR = 20
#: Temperatures tried; the least one keeps an error-free sample from certainty.
TEMPERATURES = np.geomspace(0.25, 20, 60)
UNKNOWN = "und"
KEPT_WORDS = 1 << 18
LETTERS = re.compile(r"[^\W\d_]+")


def words_in(text: str | None) -> list[str]:
    """Lower-cased runs of letters; none if the text has no letter at all."""
    words = LETTERS.findall((text or "").lower())
    if words and not words[0].isalpha() and not any(c.isalpha() for w in words for c in w):
        return []  # characters that count as letters in patterns only, such as superscripts
    return words


def subword_rows(word: str) -> list[int]:
    marked = f"<{word}>"
    grams = [marked, *(marked[i : i + n] for n in GRAMS for i in range(len(marked) - n + 1))]
    return [zlib.crc32(g.encode()) % BUCKETS for g in grams]


def text_counts(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Rows of the table that a text has, and the share of each."""
    seen: dict[str, int] = {}
    for word in words_in(text):
        seen[word] = seen.get(word, 0) + 1
    counts = np.zeros(BUCKETS)
    for word, n in seen.items():
        for row in subword_rows(word):
            counts[row] += n
    rows = np.flatnonzero(counts)
    return rows.astype(np.int32), (counts[rows] / (counts.sum() + PRIOR)).astype(np.float32)


@dataclass(frozen=True)
class Model:
    languages: tuple[str, ...]
    table: np.ndarray  # BUCKETS x languages
    bias: np.ndarray
    temperature: float
    threshold: float

    def probabilities(self, means: np.ndarray) -> np.ndarray:
        return softmax((means + self.bias) / self.temperature)


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def fit(samples: list[tuple[np.ndarray, np.ndarray, str]], seed: int = 7) -> Model | None:
    """Train on (rows, shares, language) of texts; None without any. Not calibrated yet."""
    samples = [s for s in samples if len(s[0])]
    languages = tuple(sorted({s[2] for s in samples}))
    if not languages:
        return None
    rng = np.random.default_rng(seed)
    embedding = rng.normal(0, 0.3, (BUCKETS, DIMENSIONS))
    weights, bias = rng.normal(0, 0.3, (DIMENSIONS, len(languages))), np.zeros(len(languages))
    target = np.array([languages.index(s[2]) for s in samples])
    steps, done = EPOCHS * len(samples), 0
    for _ in range(EPOCHS):
        for i in rng.permutation(len(samples)):
            rows, shares, _ = samples[i]
            rate = RATE * (1 - done / steps)
            mean = shares @ embedding[rows]
            error = softmax(mean @ weights + bias)
            error[target[i]] -= 1
            embedding[rows] -= rate * np.outer(shares, weights @ error) * len(rows) ** 0.5
            weights -= 0.1 * rate * np.outer(mean, error)
            bias -= 0.01 * rate * error
            done += 1
    return Model(languages, (embedding @ weights).astype(np.float32), bias.astype(np.float32), 1.0, 0.0)


def calibrated(model: Model, logits: np.ndarray, languages: list[str]) -> Model:
    """Temperature and threshold from the logits of other texts and their languages."""
    if not len(logits):
        return model
    own = np.array([model.languages.index(x) for x in languages])

    def loss(temperature: float) -> float:
        return float(-np.log(softmax(logits / temperature)[np.arange(len(own)), own] + 1e-300).mean())

    temperature = float(min(TEMPERATURES, key=loss))
    scores = np.sort(softmax(logits / temperature).max(axis=1))
    k = int(REJECTED * (len(scores) + 1))
    return replace(model, temperature=temperature, threshold=float(scores[k - 1]) if k else 0.0)


def known_rows(df: DataFrame, key: str, text: str, lang: str) -> DataFrame:
    known = df.select(F.col(f"`{key}`").cast("string").alias("key"), F.col(f"`{text}`").alias("text"), F.col(f"`{lang}`").alias("lang"))
    return known.where("key is not null and text is not null and lang is not null").withColumn("h", F.abs(F.xxhash64("key") % 1_000_000))


def bounds_of(known: DataFrame) -> tuple[DataFrame | None, int, int]:
    """``(lang, below, above)``: hashes below the first bound are trained on, those between
    it and the second calibrate; and how many rows of a language are trained on, at most."""
    totals = {r.lang: r.n for r in known.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "lang").limit(LANGUAGES).collect()}
    if not totals:
        return None, 0, 0
    each = max(1, min(PER_LANGUAGE, SAMPLE_ROWS // len(totals)))
    more = CALIBRATION_ROWS / 2 / sum(totals.values())  # as the languages come, whatever is trained on
    rows = [(lang, below, below + 1_000_000 * more) for lang, n in totals.items() for below in [min(1_000_000 * 1.5 * each / n, 800_000.0)]]
    return known.sparkSession.createDataFrame(rows, "lang string, below double, above double"), each, len(totals)


def sample(known: DataFrame, bounds: DataFrame, each: int, languages: int) -> list[tuple[np.ndarray, np.ndarray, str]]:
    """Hashed counts of a bounded sample of labelled rows, the same at every run."""

    @F.pandas_udf("rows binary, shares binary")
    def counted(texts: pd.Series) -> pd.DataFrame:
        return pd.DataFrame([[a.tobytes() for a in text_counts(t)] for t in texts], columns=["rows", "shares"])

    chosen = known.join(F.broadcast(bounds), "lang").where("h < below").withColumn("c", counted("text")).select("lang", "h", "key", "c.rows", "c.shares")
    out: list[tuple[np.ndarray, np.ndarray, str]] = []
    taken: dict[str, int] = {}
    for r in sorted(chosen.limit(2 * each * languages).collect(), key=lambda r: (r.h, r.key)):
        if taken.setdefault(r.lang, 0) < each:
            taken[r.lang] += 1
            out.append((np.frombuffer(r.rows, np.int32), np.frombuffer(r.shares, np.float32), r.lang))
    return out


def calibrate(model: Model, known: DataFrame, bounds: DataFrame) -> Model:
    rows = known.join(F.broadcast(bounds), "lang").where("h >= below and h < above").where(F.col("lang").isin(*model.languages))
    found = rows.select("lang", logit_column(model, F.col("text")).alias("z")).limit(CALIBRATION_ROWS).collect()
    found = [r for r in found if r.z is not None]  # a filter in the plan would tell every text twice
    return calibrated(model, np.array([r.z for r in found]).reshape(len(found), -1), [r.lang for r in found])


class WordSums:
    """Table sums of words, kept up to a bound and then gathered anew."""

    def __init__(self, model: Model):
        self.model = model
        self.sums = np.zeros((KEPT_WORDS, len(model.languages) + 1), dtype=np.float32)
        self.places: dict[str, int] = {}

    def mean(self, words: list[str]) -> np.ndarray:
        total = np.zeros(self.sums.shape[1])
        for at in range(0, len(words), KEPT_WORDS):
            total += self.part(words[at : at + KEPT_WORDS])
        return total[:-1] / (total[-1] + PRIOR)

    def part(self, words: list[str]) -> np.ndarray:
        places = self.places
        try:
            found = [places[w] for w in words]
        except KeyError:
            new = [w for w in dict.fromkeys(words) if w not in places]
            if len(places) + len(new) > KEPT_WORDS:
                places.clear()
                new = list(dict.fromkeys(words))
            for w in new:
                rows = subword_rows(w)
                place = places[w] = len(places)
                self.sums[place, :-1] = self.model.table[rows].sum(axis=0)
                self.sums[place, -1] = len(rows)
            found = [places[w] for w in words]
        return self.sums[found].sum(axis=0, dtype=np.float64)


@functools.lru_cache(maxsize=2)
def word_sums(number: int, loaded) -> WordSums:
    return WordSums(loaded.value)


def predict_column(model: Model | None, text: Column) -> Column:
    """Struct of ``lang``, ``score`` and ``accepted`` of a text."""
    from pyspark import SparkContext

    loaded = SparkContext._active_spark_context.broadcast(model)
    has_model, number = model is not None, loaded._jbroadcast.id()

    @F.pandas_udf("lang string, score double, accepted boolean")
    def predict(texts: pd.Series) -> pd.DataFrame:
        rows = []
        for t in texts:
            words = words_in(t) if has_model else []
            if not words:
                rows.append((UNKNOWN, 0.0, False))
                continue
            chances = loaded.value.probabilities(word_sums(number, loaded).mean(words))
            best = int(chances.argmax())
            rows.append((loaded.value.languages[best], float(chances[best]), bool(chances[best] >= loaded.value.threshold)))
        return pd.DataFrame(rows, columns=["lang", "score", "accepted"])

    return predict(text)


def logit_column(model: Model, text: Column) -> Column:
    """A text's sums before any temperature; null for texts without a letter."""
    from pyspark import SparkContext

    loaded = SparkContext._active_spark_context.broadcast(model)
    number = loaded._jbroadcast.id()

    @F.pandas_udf("array<double>")
    def logits(texts: pd.Series) -> pd.Series:
        sums = word_sums(number, loaded)
        return pd.Series([(sums.mean(words) + loaded.value.bias).tolist() if (words := words_in(t)) else None for t in texts], dtype=object)

    return logits(text)


def is_held_out(key: Column) -> Column:
    """Rows that are never learned from: a fixed quarter of the keys."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def learn(df: DataFrame, key: str, text: str, lang: str) -> Model | None:
    known = known_rows(df.where(~is_held_out(F.col(f"`{key}`"))), key, text, lang)
    bounds, each, languages = bounds_of(known)
    if bounds is None:
        return None
    model = fit(sample(known, bounds, each, languages))
    return model and calibrate(model, known, bounds)


def keep_known(df: DataFrame, key: str, text: str, lang: str) -> DataFrame:
    """The rows whose language is told surely enough, all columns as they were."""
    model = learn(df, key, text, lang)
    told = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), predict_column(model, F.col(f"`{text}`")).alias("p"))
    return told.where("p.accepted").select("row.*")


def op5_langid(spark, sf_dir):
    """Language of all documents, learned from the rows that are not held out."""
    docs = read_table(spark, sf_dir, "documents")
    model = learn(docs, "doc_id", "text", "lang")
    told = docs.select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), predict_column(model, F.col("text")).alias("p"))
    return told.select("doc_id", "held_out", F.col("p.lang").alias("lang_pred"), F.col("p.score").alias("score"), F.col("p.accepted").alias("accepted"))
