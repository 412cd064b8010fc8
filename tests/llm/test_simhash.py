import itertools
import random

import numpy as np
import pyarrow as pa
import pytest
import xxhash

from prefpat.llm import simhash


def plain_print(text, shingle):
    words = "".join(c.lower() if c.isascii() else c for c in (text or "")).encode().split()
    grams = [b" ".join(words[i : i + shingle]) for i in range(len(words) - shingle + 1)] or ([b" ".join(words)] if words else [])
    hashes = [xxhash.xxh64_intdigest(g, seed=42) for g in grams]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes))


def plain_components(rows, budget):
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(rows)), 2):
        if (rows[i][1] ^ rows[j][1]).bit_count() <= budget:
            root[find(i)] = find(j)
    least = {}
    for i, (key, _) in enumerate(rows):
        if key is not None:
            least[find(i)] = min(key, least.get(find(i), key))
    return [least.get(find(i)) for i in range(len(rows))]


def test_fingerprint_bits():
    for text in ["", "  \t\n", "one", "One TWO three", "a b c d e", "é Ü A b c\x0bd e f g", "x " * 9]:
        assert simhash.text_fingerprint(text.encode(), 4) == plain_print(text, 4)
    assert simhash.text_fingerprint(None, 4) == 0


@pytest.mark.parametrize("budget", [0, 3, 4, 10])
def test_trie_join_links_what_all_pairs_link(budget):
    random.seed(budget)
    base = [random.getrandbits(64) for _ in range(60)]
    prints = set(base)
    for b in base[:30]:
        for _ in range(12):
            x = b
            for _ in range(random.randint(1, 6)):
                x ^= 1 << random.randrange(64)
            prints.add(x)
    values = np.array(sorted(prints), dtype=np.uint64)
    u, v = simhash.trie_self_join(np.zeros(len(values), dtype=np.int64), values, values, budget)
    rows = [(i, int(x)) for i, x in enumerate(values)]
    at = {int(x): i for i, x in enumerate(values)}
    want = plain_components(rows, budget)
    root = list(range(len(values)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in zip(u.tolist(), v.tolist()):
        assert (a ^ b).bit_count() <= 64
        root[max(find(at[a]), find(at[b]))] = min(find(at[a]), find(at[b]))
    assert [find(i) for i in range(len(values))] == want


def near(text, n):
    words = text.split()
    for i in range(n):
        words[(i * 37) % len(words)] = f"changed{i}"
    return " ".join(words)


def fixture_rows():
    random.seed(5)
    vocabulary = [f"w{i}" for i in range(400)]
    rows = [(i, " ".join(random.choices(vocabulary, k=random.randint(3, 300)))) for i in range(60)]
    rows += [(100 + i, rows[i % 7][1]) for i in range(40)]
    rows += [(200 + i, near(rows[10 + i % 3][1] + " tail" * 3, i % 3)) for i in range(40)]
    rows += [(300, None), (301, ""), (302, " \n"), (None, rows[3][1]), (303, "Ü"), (304, "x " * 30000), (5, rows[5][1])]
    return rows


@pytest.mark.parametrize("budget,shingle", [(4, 4), (9, 5)])
def test_components_match_brute_force(spark, budget, shingle):
    rows = fixture_rows()
    df = spark.createDataFrame([(k, t, 1, "x") for k, t in rows], "doc_id long, text string, print int, component string")
    got = sorted(((r.key, r.print & (2**64 - 1), r.component) for r in simhash.simhash_components(df, "doc_id", "text", shingle, budget, None).collect()), key=str)
    prints = [(k, plain_print(t, shingle)) for k, t in rows]
    want = sorted(((k, p, c) for (k, p), c in zip(prints, plain_components(prints, budget))), key=str)
    assert got == want


def test_long_chain_is_one_component(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(300)] + [(1000, 1001)], "u long, v long")
    got = {r.node: r.root for r in simhash.connected(links).collect()}
    assert got == {**{i: 0 for i in range(1, 301)}, 1001: 1000}


def test_empty_table(spark):
    df = spark.createDataFrame([], "doc_id long, text string")
    assert simhash.simhash_components(df, "doc_id", "text").count() == 0


def plain_kept(rows, shingle, similarity):
    sets = []
    for _, text in rows:
        words = (text or "").lower().split()
        sets.append({tuple(words[i : i + shingle]) for i in range(len(words) - shingle + 1)} or {tuple(words)})
    prints = [simhash.text_fingerprints((t or "").encode(), shingle, True) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, j in itertools.combinations(range(len(rows)), 2):
        one, two = ((a ^ b).bit_count() for a, b in zip(prints[i], prints[j]))
        if (one <= 10 and one + two <= 20) or len(sets[i] & sets[j]) >= similarity * len(sets[i] | sets[j]) - 1e-9:
            a, b = find(i), find(j)
            root[max(a, b)] = min(a, b)
    return sorted(k for i, (k, _) in enumerate(rows) if find(i) == i)


def test_no_pair_of_the_similarity_stays(spark):
    """Near copies of a similarity around 0.8, many of which differ in over 20 of 128 bits."""
    random.seed(8)
    rows = []
    for i in range(150):
        words = [f"w{random.randrange(3000)}" for _ in range(random.choice([40, 84, 200, 850]))]
        other = list(words)
        for at in random.sample(range(len(words)), max(1, round(len(words) * random.choice([0.008, 0.016, 0.02, 0.024, 0.03])))):
            other[at] = f"changed{at}"
        rows += [(2 * i, " ".join(words)), (2 * i + 1, " ".join(other))]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(7)
    assert sorted(r.doc_id for r in simhash.keep_representatives(df, "doc_id", "text").collect()) == plain_kept(rows, 5, 0.8)


def test_the_descent_prunes_and_leaves_little_to_compare():
    """Random prints and near ones: most pairs fall with a pair of nodes."""
    rng = np.random.default_rng(8)
    values = rng.integers(0, 1 << 64, 3000, dtype=np.uint64)
    near = values[:200] ^ (np.uint64(1) << rng.integers(0, 64, 200, dtype=np.uint64)) ^ (np.uint64(1) << rng.integers(0, 64, 200, dtype=np.uint64))
    values, counts = np.unique(np.r_[values, near]), {}
    zeros = np.zeros(len(values), dtype=np.int64)
    u, v = simhash.trie_self_join(zeros, values, values, 4, leaf=1, counts=counts)
    wide = simhash.trie_self_join(zeros, values, values, 4)
    assert len(u) == len(wide[0]) >= 190
    assert counts["pruned"] > 0.85 * len(values) ** 2 / 2 and counts["compared"] < 0.12 * len(values) ** 2 / 2


def test_links_of_one_block_are_those_of_all_pairs(spark):
    rng = np.random.default_rng(9)
    values = rng.integers(0, 1 << 64, 300, dtype=np.uint64)
    for flips in (1, 3, 4, 5):
        own = values[:60].copy()
        for _ in range(flips):
            own ^= np.uint64(1) << rng.integers(0, 64, 60, dtype=np.uint64)
        values = np.r_[values, own]
    values = np.unique(values)
    want = reference_roots(values, 4)
    df = spark.createDataFrame([(int(x), 0) for x in values.view(np.int64)], "print long, guard long")
    for agree, leaf in ((1, 1), (2, 64)):
        links = [(r.u, r.v) for r in simhash.near_links(df, 4, None, agree, leaf).collect()]
        place = {int(x): i for i, x in enumerate(values.view(np.int64))}
        forest = simhash.Forest(len(values))
        forest.add(np.array([place[a] for a, _ in links]), np.array([place[b] for _, b in links]))
        assert forest.root.tolist() == want


def reference_roots(values, budget):
    root = list(range(len(values)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(values)):
        for j in np.flatnonzero(np.bitwise_count(values ^ values[i]) <= budget).tolist():
            a, b = find(i), find(j)
            root[max(a, b)] = min(a, b)
    return [find(x) for x in range(len(values))]


def test_equal_prints_with_other_guards_keep_their_links():
    """A print that occurs with several guards links by any of them."""
    one, two = 0x0F0F, 0x0F00
    prints, guards = np.array([one, one, two], dtype=np.uint64), np.array([0, (1 << 40) - 1, (1 << 40) - 1], dtype=np.uint64)
    u, v = simhash.trie_self_join(np.zeros(3, dtype=np.int64), prints, guards, 10, 20)
    assert {frozenset((int(a), int(b))) for a, b in zip(u, v)} == {frozenset((one, two))}


def test_a_group_of_many_blocks_keeps_its_links(spark, monkeypatch):
    """Chains of near copies, compared whole and by two texts at a time: the same components."""
    random.seed(9)
    rows = []
    for chain in range(3):
        words = [f"c{chain}w{i}" for i in range(120)]
        for step in range(12):
            rows.append((len(rows), " ".join(words)))
            words = list(words)
            words[random.randrange(120)] = f"c{chain}s{step}"
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    want = plain_kept(rows, 5, 0.8)
    met = []
    plain = simhash.exact_links
    for limits in ({}, {"block_texts": 2}, {"block_bytes": 1}):
        monkeypatch.setattr(simhash, "exact_links", lambda *a, limits=limits: met.append(plain(*a, **limits)) or met[-1])
        assert sorted(r.doc_id for r in simhash.keep_representatives(df, "doc_id", "text").collect()) == want
    reach = []
    for links in met:
        edges = [(r.u % (1 << 64), r.v % (1 << 64)) for r in links.collect()]
        names = sorted({x for e in edges for x in e})
        forest = simhash.Forest(len(names))
        forest.add(np.array([names.index(a) for a, _ in edges]), np.array([names.index(b) for _, b in edges]))
        reach.append((names, forest.root.tolist()))
    assert reach[0] == reach[1] == reach[2] and len(reach[0][0]) == len(rows)


def test_long_texts_are_compared_before_many_rows_have_come(monkeypatch):
    """Groups go on once their bytes, and not only their rows, reach the limit."""
    monkeypatch.setattr(simhash, "GROUP_BYTES", 1000)
    words = " ".join(f"w{i}" for i in range(400))
    batches = [pa.RecordBatch.from_pydict({"g": pa.array([g, g], pa.int64()), "id": pa.array([2 * g, 2 * g + 1], pa.int64()), "text": pa.array([words.encode()] * 2)}) for g in range(5)]
    out = list(simhash.exact_components(5, 0.8)(iter(batches)))
    assert len(out) == 5 and [b["component"].to_pylist() for b in out] == [[2 * g] * 2 for g in range(5)]


@pytest.mark.parametrize("close", [True, False])
def test_shared_counts_as_matrix_and_by_marks(close):
    """Close sets make a matrix of bits, those of a long chain are marked; both count
    what sets share."""
    rng = np.random.default_rng(5)
    sets = [np.unique(rng.integers(0, 60, size)) for size in (0, 1, *rng.integers(1, 40, 70))] if close else [np.arange(i, i + 3) for i in range(300)]
    begins = np.r_[0, np.cumsum([len(s) for s in sets])]
    count = simhash.shared_counts(np.concatenate(sets), begins)
    assert (count.__name__ == "by_marks") == (not close)
    rest = rng.permutation(len(sets))[:50]
    for one in range(len(sets)):
        assert count(one, rest).tolist() == [len(np.intersect1d(sets[one], sets[i])) for i in rest]
        assert count(one, rest[:0]).tolist() == []
