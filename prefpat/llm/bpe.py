"""BPE encoding and decoding with public vocabularies.

A word starts as its single symbols in a doubly linked list; a priority queue
holds the merge ranks of neighbours. The least rank is merged first, which makes
new neighbours; entries whose symbols have changed since they were queued are
stale and skipped. A text's words repeat, so encoded words are kept, in two
generations of bounded size.

The tokenizer file gives the vocabulary, the merges and the special tokens; its
kind (NFC, lower case, words, single digits, runs of other characters, word ends
marked) is fixed here and checked when the file is loaded. The file's path is a
parameter: it must name the same file on every executor.

Defined cases: a null text is the empty text, with no ids; special tokens in a
text are taken as such, as the file's own library does; repeated rows are encoded
alike; an empty table gives no rows. Only key and text are read.
"""

from __future__ import annotations

import functools
import hashlib
import heapq
import json
import re
import sys
import unicodedata
from array import array
from collections.abc import Iterator

import pandas as pd
import public_tokenizers
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from prefpat.llm.common import read_table

DEFAULT_VOCABULARY = public_tokenizers.path("word_bpe_49k.json")
#: Encoded words kept in each of two generations, and the longest ones that are kept.
KEPT_WORDS, KEPT_LETTERS = 1 << 19, 64
#: What counts as a word, by Unicode classes; and the same for
#: texts without the characters on which the two engines' classes differ, and for
#: lower-cased texts of Latin-1 alone.
WORDS = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")
PLAIN_WORDS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\w\s]|_)+")
LATIN_WORDS = re.compile(r"[a-zªµºß-öø-ÿ]+|'(?:[stmd]|re|ve|ll)|[0-9]|[^\sa-zªµºß-öø-ÿ0-9]+")
SPACES_OF_ONE = "\x1c\x1d\x1e\x1f"
BEYOND_LATIN = re.compile(f"[{SPACES_OF_ONE}²³¹¼½¾Ā-\U0010ffff]")


@functools.cache
def odd_characters() -> re.Pattern:
    """Characters on which the two patterns may differ: numbers that are no decimal
    digits, the separators that only one engine takes for white space, and, to
    keep the set small, all beyond the basic plane."""
    odd = [c for c in map(chr, range(0x10000)) if c.isalnum() and not c.isalpha() and not c.isdecimal()]
    return re.compile(f"[{re.escape(''.join(odd))}{SPACES_OF_ONE}\U00010000-\U0010ffff]")


def words_in(text: str) -> list[str]:
    """A text's words, normalised: composed, lower-cased character by character."""
    if not text.isascii():
        text = unicodedata.normalize("NFC", text)
        text = text.replace("Σ", "σ")  # lower() alone would look at a sigma's place in its word
    text = text.lower()
    if not BEYOND_LATIN.search(text):
        return LATIN_WORDS.findall(text)
    return (WORDS if odd_characters().search(text) else PLAIN_WORDS).findall(text)


def byte_symbols() -> list[str]:
    """The printable character that stands for each byte in the vocabulary.

    Printable bytes of Latin-1 stand for themselves, the others for the
    characters from 256 on, in order.
    """
    own = [*range(ord("!"), ord("~") + 1), *range(ord("¡"), ord("¬") + 1), *range(ord("®"), ord("ÿ") + 1)]
    rest = iter(range(256, 512))
    return [chr(b) if b in own else chr(next(rest)) for b in range(256)]


class Words(dict):
    """Encoded words: a dictionary that fills itself and forgets the oldest half. Words
    are bounded in number and in length, so the whole is bounded in bytes."""

    def __init__(self, encode):
        super().__init__()
        self.encode, self.older = encode, {}

    def __missing__(self, word: str) -> bytes:
        return self.keep(word, self.older.get(word) or self.encode(word))

    def keep(self, word: str, ids: bytes) -> bytes:
        if len(word) <= KEPT_LETTERS:
            if len(self) >= KEPT_WORDS:
                self.older = dict(self)
                self.clear()
            self[word] = ids
        return ids


class Vocabulary:
    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        model = spec["model"]
        if model["type"] != "BPE" or not model["end_of_word_suffix"] or model["unk_token"] or spec["decoder"] or spec["post_processor"]:
            raise ValueError(f"{path} is not of the kind that this encoder knows")
        self.word_end = model["end_of_word_suffix"]
        ids = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.strings = [""] * (1 + max([*ids.values(), *self.special.values()]))
        for token, number in (ids | self.special).items():
            self.strings[number] = token
        pairs = (m if isinstance(m, list) else m.split(" ") for m in model["merges"])
        #: (left id, right id) -> (rank, id of the merged token)
        self.merges = {(ids[a], ids[b]): (rank, ids[a + b]) for rank, (a, b) in enumerate(pairs)}
        symbols = byte_symbols()
        self.inner, self.last = [ids[c] for c in symbols], [ids[c + self.word_end] for c in symbols]
        self.special_pattern = re.compile("|".join(map(re.escape, self.special)))
        self.words = Words(lambda w: array("I", self.word_ids(w)).tobytes())

    def word_ids(self, word: str) -> list[int]:
        raw = word.encode()
        symbols = [self.inner[b] for b in raw]
        symbols[-1] = self.last[raw[-1]]
        n, merges = len(symbols), self.merges
        before, after = list(range(-1, n - 1)), [*range(1, n), -1]
        queue = [(*found, i) for i in range(n - 1) if (found := merges.get((symbols[i], symbols[i + 1])))]
        heapq.heapify(queue)  # entries: rank, merged id, place of the left symbol
        while queue:
            _, merged, i = heapq.heappop(queue)
            j = after[i]
            if symbols[i] < 0 or j < 0:
                continue  # the symbol is gone, or has no neighbour any more
            found = merges.get((symbols[i], symbols[j]))
            if not found or found[1] != merged:
                continue  # stale: one of the two has changed since
            symbols[i], symbols[j] = merged, -1
            k = after[i] = after[j]
            if k >= 0:
                before[k] = i
                if found := merges.get((merged, symbols[k])):
                    heapq.heappush(queue, (*found, i))
            h = before[i]
            if h >= 0 and (found := merges.get((symbols[h], merged))):
                heapq.heappush(queue, (*found, h))
        return [s for s in symbols if s >= 0]

    def encode(self, text: str | None) -> bytes:
        """A text's ids as unsigned 32-bit integers, in this machine's order."""
        if not text:
            return b""
        known = self.known
        if "<" not in text or not (marks := list(self.special_pattern.finditer(text))):
            return b"".join(known(words_in(text)))
        parts, at = [], 0
        for mark in marks:
            parts += known(words_in(text[at : mark.start()]))
            parts.append(array("I", [self.special[mark[0]]]).tobytes())
            at = mark.end()
        return b"".join([*parts, *known(words_in(text[at:]))])

    def known(self, words: list[str]) -> Iterator[bytes]:
        return map(self.words.__getitem__, words)

    def decode(self, ids: bytes) -> str:
        return " ".join(map(self.strings.__getitem__, array("I", ids)))


class LibraryVocabulary(Vocabulary):
    """The same ids, with new words encoded by the tokenizer's own library, all
    those of a text at a time; for operators that need ids and not this encoder."""

    def __init__(self, path: str):
        super().__init__(path)
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.ends = [s.endswith(self.word_end) for s in self.strings]

    def known(self, words: list[str]) -> Iterator[bytes]:
        kept, older = self.words, self.words.older
        fresh: dict[str, bytes] = {}  # this text's own new words
        if new := [w for w in set(words) if w not in kept and w not in older]:
            found, own = iter(new), array("I")
            for number in self.library.encode(" ".join(new), add_special_tokens=False).ids:
                own.append(number)
                if self.ends[number]:
                    fresh[next(found)] = own.tobytes()
                    own = array("I")
            known = [fresh[w] if w in fresh else kept[w] for w in words]
            for word, ids in fresh.items():
                kept.keep(word, ids)
            return iter(known)
        return super().known(words)


@functools.cache
def library_vocabulary(path: str) -> LibraryVocabulary:
    return LibraryVocabulary(path)


@functools.cache
def vocabulary(path: str) -> Vocabulary:
    """One per Python worker, kept from task to task."""
    return Vocabulary(path)


def little_endian(ids: bytes) -> bytes:
    if sys.byteorder == "little":
        return ids
    turned = array("I", ids)
    turned.byteswap()
    return turned.tobytes()


def encode_column(text: Column, path: str = DEFAULT_VOCABULARY) -> Column:
    """Token ids of a text."""

    @F.pandas_udf("array<int>")
    def encode(texts: pd.Series) -> pd.Series:
        known = vocabulary(path)
        return texts.map(lambda t: list(array("I", known.encode(t))))

    return encode(text)


def decode_column(ids: Column, path: str = DEFAULT_VOCABULARY) -> Column:
    """Vocabulary strings of token ids, joined; null ids give the empty text."""

    @F.pandas_udf("string")
    def decode(rows: pd.Series) -> pd.Series:
        known = vocabulary(path)
        return rows.map(lambda r: known.decode(array("I", [] if r is None else r).tobytes()))

    return decode(ids)


def digest_column(text: Column, path: str = DEFAULT_VOCABULARY) -> Column:
    """Number of ids and digests of the ids and of the text decoded from them."""

    @F.pandas_udf("n_tokens long, ids_sha256 string, decoded_sha256 string")
    def digest(texts: pd.Series) -> pd.DataFrame:
        known, rows = vocabulary(path), []
        for text in texts:
            ids = known.encode(text)
            rows.append((len(ids) // 4, hashlib.sha256(little_endian(ids)).hexdigest(), hashlib.sha256(known.decode(ids).encode()).hexdigest()))
        return pd.DataFrame(rows, columns=["n_tokens", "ids_sha256", "decoded_sha256"])

    return digest(text)


def encoded_digests(df: DataFrame, key: str, text: str, path: str = DEFAULT_VOCABULARY) -> DataFrame:
    return df.select(F.col(f"`{key}`").alias("key"), digest_column(F.col(f"`{text}`"), path).alias("d")).select("key", "d.*")


def op1_bpe(spark, sf_dir):
    """All documents encoded and decoded."""
    done = encoded_digests(read_table(spark, sf_dir, "documents"), "doc_id", "text")
    return done.withColumnRenamed("key", "doc_id")
