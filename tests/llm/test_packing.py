import random
import zlib
from collections import defaultdict

from tokenizers import Tokenizer

from prefpat.llm import bpe, packing

LIBRARY = Tokenizer.from_file(bpe.DEFAULT_VOCABULARY)


def plain_best_fit(lengths, capacity):
    rooms = []
    for length in sorted(lengths, reverse=True):
        fitting = [r for r in rooms if r >= length]
        if fitting:
            rooms.remove(min(fitting))
            rooms.append(min(fitting) - length)
        else:
            rooms.append(capacity - length)
    return len(rooms)


def test_best_fit_matches_a_plain_one():
    random.seed(1)
    for _ in range(30):
        lengths = [random.randint(1, 100) for _ in range(random.randint(0, 200))]
        bins = packing.best_fit(lengths, 100)
        assert sorted(i for b in bins for i in b) == list(range(len(lengths)))
        assert all(sum(lengths[i] for i in b) <= 100 for b in bins)
        assert len(bins) == plain_best_fit(lengths, 100)


def check(rows, texts, capacity):
    by_doc, by_sequence = defaultdict(list), defaultdict(list)
    for r in rows:
        by_doc[r.key].append(r)
        by_sequence[r.sequence_id].append(r)
    assert set(by_doc) == set(texts)
    for key, own in by_doc.items():
        copies = [[*LIBRARY.encode(t or "", add_special_tokens=False).ids, 0] for t in texts[key]]
        want = sorted((n, at, len(c[at : at + capacity]), zlib.crc32(b"".join(i.to_bytes(4, "little") for i in c[at : at + capacity]))) for c in copies for n, at in enumerate(range(0, len(c), capacity)))
        assert sorted((r.piece, r.start, r.length, r.ids_crc32) for r in own) == want
    for own in by_sequence.values():
        at = 0
        for r in sorted(own, key=lambda r: r.offset):
            assert r.offset == at
            at += r.length
        assert at <= capacity
    return len(by_sequence)


def test_packing(spark):
    random.seed(2)
    rows = [(i, " ".join(random.choices(["tree", "of", "words", "x1"], k=random.randint(0, 90)))) for i in range(3000)]
    rows += [(5000, None), (5001, ""), (None, "no key"), (5002, "long " * 700), (7, "again"), (7, "again")]
    df = spark.createDataFrame([(k, t, 1, True) for k, t in rows], "doc_id long, text string, bin int, done boolean").repartition(20)
    texts = defaultdict(list)
    for k, t in rows:
        texts[k].append(t)
    found = packing.pack(df, "doc_id", "text", capacity=128).collect()
    used = check(found, texts, 128)
    lengths = [r.length for r in found]
    assert used <= max(plain_best_fit(lengths, 128) * 1.03, -(-sum(lengths) // 128) * 1.03)


def test_small_pools_and_no_rows(spark, monkeypatch):
    df = spark.createDataFrame([(str(i), "word " * (i % 50)) for i in range(200)], "doc_id string, text string")
    check(packing.pack(df, "doc_id", "text", capacity=64).collect(), {str(i): ["word " * (i % 50)] for i in range(200)}, 64)
    assert packing.pack(df.limit(0), "doc_id", "text").count() == 0


def test_all_underfull_bins_meet_those_of_other_tasks(spark, monkeypatch):
    """A task of long texts alone has more underfull bins than any bound on what it sends up."""
    long, short = "tree " * 40, "of " * 20
    one, two = (len(LIBRARY.encode(t, add_special_tokens=False).ids) + 1 for t in (long, short))
    assert one + two <= 64 < 2 * one
    rows = [(i, long if i < 20_000 else short) for i in range(40_000)]
    df = spark.createDataFrame(spark.sparkContext.parallelize(rows, 2), "doc_id long, text string")
    for first, pool in ((1 << 17, 1 << 17), (4096, 64)):  # one pool, and many
        monkeypatch.setattr(packing, "FIRST_ITEMS", first, raising=False)
        monkeypatch.setattr(packing, "POOL_ITEMS", pool)
        found = packing.pack(df, "doc_id", "text", capacity=64).select("key", "sequence_id", "length").collect()
        used = defaultdict(int)
        for r in found:
            used[r.sequence_id] += r.length
        assert sorted(r.key for r in found) == list(range(40_000)) and max(used.values()) <= 64
        assert len(used) <= 20_000 * 1.02


def test_kept_words_are_bounded(monkeypatch):
    """Both vocabularies forget, whatever words come, and long words are not kept."""
    monkeypatch.setattr(bpe, "KEPT_WORDS", 10)
    for kind in (bpe.Vocabulary, bpe.LibraryVocabulary):
        known = kind(bpe.DEFAULT_VOCABULARY)
        fresh = bpe.Vocabulary(bpe.DEFAULT_VOCABULARY)
        for i in range(60):
            text = " ".join(f"{chr(97 + i % 26)}{chr(97 + j)}x{'long' * 30}" if j % 5 == 0 else f"{chr(97 + i % 26)}{chr(97 + j)}word" for j in range(25))
            assert known.encode(text + " again again") == fresh.encode(text + " again again")
            assert len(known.words) <= 10 and len(known.words.older) <= 10
            assert all(len(w) <= bpe.KEPT_LETTERS for w in known.words)
