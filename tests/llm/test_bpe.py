import hashlib
from array import array

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from prefpat.llm import bpe

LIBRARY = Tokenizer.from_file(bpe.DEFAULT_VOCABULARY)
OWN = bpe.vocabulary(bpe.DEFAULT_VOCABULARY)
TEXTS = [
    "", " \n\t", "Hello  wörld's 123", "<|endoftext|>", "a<|startoftext|>b<|endoftext|><|endoftext|> <|ENDOFTEXT|> <|", "ΑΣ ΑΣΑ Σ", "I'll don'T 's'S ''s",
    "²½ Ⅷ ٣ ๓ 12３ 4", "é é Å K ŉ ß ẞ İ ǅ ﬁ", "a\x00b \x1ca\x1db\x85c\xa0d", "中文字 ひらがな 한국어", "😀😀 ‍́ _a_ __", "x" * 5000, "ab" * 3000 + "'s",
]


@pytest.mark.parametrize("vocabulary", [OWN, bpe.LibraryVocabulary(bpe.DEFAULT_VOCABULARY)])
def test_ids_and_strings_are_the_librarys(vocabulary):
    for text in TEXTS:
        want = LIBRARY.encode(text, add_special_tokens=False).ids
        ids = vocabulary.encode(text)
        assert list(array("I", ids)) == want, text
        assert vocabulary.decode(ids) == LIBRARY.decode(want, skip_special_tokens=False)


@settings(max_examples=300, deadline=None)
@given(st.text(st.characters(exclude_categories=["Cs", "Cn"]), max_size=40))
def test_any_text(text):
    assert list(array("I", OWN.encode(text))) == LIBRARY.encode(text, add_special_tokens=False).ids


def test_kept_words_are_bounded(monkeypatch):
    monkeypatch.setattr(bpe, "KEPT_WORDS", 4)
    small = bpe.Vocabulary(bpe.DEFAULT_VOCABULARY)
    text = " ".join(f"w{'abcdefghij'[i % 10]}x" for i in range(50))
    assert list(array("I", small.encode(text))) == LIBRARY.encode(text, add_special_tokens=False).ids
    assert len(small.words) <= 4 and len(small.words.older) <= 4


def test_columns(spark):
    df = spark.createDataFrame([(i, t, "x", 3) for i, t in enumerate([None, *TEXTS])], "doc_id long, text string, d string, n_tokens int")
    for r in bpe.encoded_digests(df, "doc_id", "text").collect():
        ids = LIBRARY.encode(([None, *TEXTS])[r.key] or "", add_special_tokens=False).ids
        assert r.n_tokens == len(ids)
        assert r.ids_sha256 == hashlib.sha256(b"".join(i.to_bytes(4, "little") for i in ids)).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(LIBRARY.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    back = df.select("doc_id", bpe.decode_column(bpe.encode_column(F.col("text"))).alias("t")).collect()
    assert {r.doc_id: r.t for r in back}[3] == LIBRARY.decode(LIBRARY.encode(TEXTS[2]).ids)
    assert bpe.encoded_digests(df.limit(0), "doc_id", "text").count() == 0
