import itertools

import pytest

from prefpat.functions.rng import u32_py
from prefpat.operators import measures, mine, xorcells
from prefpat.operators.encode import encode
from prefpat.plans.lazy import approx_count, enumerate_lazy

ROWS, ITEMS = 30, 12


@pytest.fixture(scope="module")
def toy(spark):
    """Thirty transactions over twelve items from portable bits; half are positive."""
    long = [(t, f"i{i:02d}", t % 2) for t in range(ROWS) for i in range(ITEMS) if u32_py("toy", t, i) % 5 < 3] + [(ROWS, None, None)]
    return encode(spark.createDataFrame(long, "tid long, item string, label int"), "toy").persist()


@pytest.fixture(scope="module")
def brute(toy):
    rows = [(set(r["items"]), r.label) for r in toy.transactions.collect()]
    out = {}
    for n in range(1, ITEMS + 1):
        for s in itertools.combinations(range(ITEMS), n):
            own = [label for items, label in rows if set(s) <= items]
            if len(own) >= 8:
                out[",".join(map(str, s))] = (len(own), own.count(1))
    return out


def test_encoding(toy):
    assert (toy.n, toy.n_pos, toy.n_labelled, toy.n_items, toy.words) == (ROWS + 1, ROWS // 2, ROWS, ITEMS, 1)
    supports = [r.support for r in toy.items.orderBy("item_id").collect()]
    assert supports == sorted(supports, reverse=True)


@pytest.mark.parametrize("engine", list(mine.ENGINES))
def test_miners_match_brute_force(toy, brute, engine):
    assert {r.pattern: (r["sup"], r.sup_pos) for r in mine.frequent(toy, 8, engine).collect()} == brute


def test_limits_and_empty_set(toy, brute):
    found = mine.frequent(toy, 8, max_len=2, include_empty=True).collect()
    assert {r.pattern for r in found} == {p for p in brute if p.count(",") < 2} | {""}


def test_partitioned_over_many_chunks(toy, brute):
    found = mine.frequent_partitioned(toy, 8, rows_per_task=3, local_least=2)
    assert mine.chunks_for(toy, 8, 3, 2) == 4
    assert {r.pattern: (r["sup"], r.sup_pos) for r in found.collect()} == brute


def test_partitioned_does_not_list_all_subsets_of_small_partitions(spark):
    """One-row partitions of thirty items each: a threshold of one would give 2^30 sets."""
    rows = [(t, f"i{i:02d}", t % 2) for t in range(24) for i in range(30) if u32_py("one", t, i) % 4]
    ds = encode(spark.createDataFrame(rows, "tid long, item string, label int"))
    ds.transactions = ds.transactions.repartition(24, "tid").persist()
    found = mine.frequent(ds, 14, "partitioned").select("pattern", "sup", "sup_pos")
    other = mine.frequent(ds, 14, "vertical").select("pattern", "sup", "sup_pos")
    assert found.count() > 0 and found.exceptAll(other).isEmpty() and other.exceptAll(found).isEmpty()


def test_support_of_given_patterns_and_classes(toy, brute):
    every = mine.frequent(toy, 8, include_empty=True).persist()
    got = {r.pattern: (r["sup"], r.sup_pos, r.sup_neg) for r in mine.support(every, toy).collect()}
    assert got.pop("") == (ROWS + 1, ROWS // 2, ROWS // 2)
    assert {p: v[:2] for p, v in got.items()} == brute and all(a - b == c for a, b, c in got.values())


def test_length_bounds_every_engine(toy, brute):
    want = {p: v for p, v in brute.items() if p.count(",") < 2}
    for engine in mine.ENGINES:
        assert {r.pattern: (r["sup"], r.sup_pos) for r in mine.frequent(toy, 8, engine, max_len=2).collect()} == want, engine


def test_closed_and_rules(toy, brute):
    patterns = mine.frequent(toy, 8).persist()
    sets = {frozenset(p.split(",")): s for p, (s, _) in brute.items()}
    want = {p for p, s in sets.items() if not any(p < q and s == t for q, t in sets.items())}
    assert {frozenset(r.pattern.split(",")) for r in mine.closed(patterns).collect()} == want
    for r in mine.rules(patterns, 0.7, toy.n).collect():
        whole = frozenset(r.left.split(",")) | {str(r.right)}
        assert r["sup"] == sets[whole] and r.confidence == pytest.approx(sets[whole] / sets[frozenset(r.left.split(","))]) and r.confidence >= 0.7


def test_calibration(toy):
    theta, count = mine.calibrate_min_sup(toy, 100, 0.5)
    assert count == mine.frequent(toy, theta).count() and abs(count - 100) <= 60


def test_cells_partition_the_patterns(spark, toy, brute):
    patterns = mine.frequent(toy, 8).persist()
    draws = xorcells.draw(spark, 3, ITEMS, 2, 5)
    assert [tuple(x)[1:] for r in draws.orderBy("draw_id").collect() for x in r.xors] == [(c[0], p) for d in xorcells.draw_py(3, ITEMS, range(2), 5) for c, p in d]
    one = draws.where("draw_id = 0")
    joined = patterns.crossJoin(one).select("pattern", xorcells.cell_id(toy.masks, mine.F.col("xors")).alias("c"))
    assert joined.count() == len(brute) and {r.c for r in joined.select("c").distinct().collect()} <= set(range(8))
    nested = xorcells.enumerate_cells(patterns, draws, toy.masks, at_least=0)
    full = xorcells.enumerate_cells(patterns, draws, toy.masks)
    assert {(r.draw_id, r.pattern) for r in nested.where("matched = 3").collect()} == {(r.draw_id, r.pattern) for r in full.collect()}
    sizes = {(r.draw_id, r.m): r.size for r in xorcells.cell_weights(nested.withColumn("w", mine.F.lit(1.0))).collect()}
    assert sizes[0, 0] == len(brute)


def test_lazy_cells_are_the_same(spark, toy):
    patterns = mine.frequent(toy, 8).persist()
    for d, constraints in enumerate(xorcells.draw_py(3, ITEMS, range(4), 9)):
        lazy = {(r.pattern, r["sup"]) for r in enumerate_lazy(toy, 8, constraints).collect()}
        draws = xorcells.draws_frame(spark, [constraints], toy.words)
        assert lazy == {(r.pattern, r["sup"]) for r in xorcells.enumerate_cells(patterns, draws, toy.masks).collect()}, d
    assert enumerate_lazy(toy, 8, [([3], 0), ([3], 1)]).count() == 0
    assert approx_count(toy, 8, 2, 5, 1).first().total > 0


def test_bounds_of_cells():
    bounds = xorcells.CellBounds(0.9)
    assert bounds.pivot == 18 and bounds.low == pytest.approx(9.47, abs=0.01) and bounds.high == pytest.approx(35.2)
    ten = [(0.974, 0.044), (0.990, 0.034), (0.993, 0.039), (0.980, 0.036), (0.985, 0.034), (0.980, 0.038), (0.993, 0.041), (0.965, 0.032), (0.972, 0.036), (0.988, 0.033)]
    assert all(bounds.low <= q / p <= bounds.high for q, p in ten)


def test_entropy(spark):
    rows = [(0, "a", None), (0, "b", None), (1, "a", None), (2, "b", None), (3, None, None)]
    ds = encode(spark.createDataFrame(rows, "tid long, item string, label int"))
    patterns = mine.frequent(ds, 1, "levelwise", max_len=1, by_class=False)
    assert measures.joint_entropy(patterns, ds).first().entropy == pytest.approx(2)
    assert measures.joint_entropy(patterns.limit(1), ds).first().entropy == pytest.approx(1)
    assert measures.joint_entropy(patterns, ds, normalise=True).first().entropy == pytest.approx(1)


def test_sparse_sets_are_searched_on_their_own_rows(monkeypatch):
    """Below sets of few rows the bitmaps are cut to these rows, and nothing else changes."""
    import numpy as np

    from prefpat.operators import vertical

    rng = np.random.default_rng(4)
    held = rng.random((40_001, 9)) < 0.2
    number = lambda flags: int.from_bytes(np.packbits(flags, bitorder="little").tobytes(), "little")
    positive = rng.random(len(held)) < 0.4
    maps = vertical.Bitmaps([number(c) for c in held.T], number(positive), number(~positive))
    cuts, whole = [], vertical.narrowed
    monkeypatch.setattr(vertical, "narrowed", lambda cover, b: cuts.append(len(held) / cover.bit_count()) or whole(cover, b))
    found = {s: (sup, pos) for i in range(8) for s, sup, pos in vertical.below(maps, (i,), maps.columns[i], 5, None)}
    assert cuts and min(cuts) > vertical.NARROW_PART
    for items, got in found.items():
        own = held[:, list(items)].all(axis=1)
        assert got == (own.sum(), (own & positive).sum())
    monkeypatch.setattr(vertical, "NARROW_BITS", 1 << 40)
    plain = {s: (sup, pos) for i in range(8) for s, sup, pos in vertical.below(maps, (i,), maps.columns[i], 5, None)}
    assert plain == found and any(len(s) > 4 for s in found)


@pytest.mark.parametrize("name", ["xor_draws", "udtf_xor_draws"])
def test_draws_are_over_the_items_of_the_table(spark, tmp_path, name):
    from prefpat import oracles
    from prefpat.queries import QUERIES

    rows = [(i, [0.5 if (i >> d) % 2 else -0.5 for d in range(5)], i) for i in range(8)]
    spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    got = sorted(map(tuple, QUERIES[name](spark, str(tmp_path)).collect()))
    assert len(got) == 12 and got == [(d, x, c[0], p) for d, one in enumerate(xorcells.draw_py(4, 3, range(3), 7)) for x, (c, p) in enumerate(one)]
    import duckdb

    con = duckdb.connect()
    con.sql("CREATE VIEW embeddings AS FROM '/root/testdata/sf0.001/embeddings.parquet'")
    want = con.sql(oracles.oracles()[name]).fetchall()
    assert sorted(map(tuple, QUERIES[name](spark, "/root/testdata/sf0.001").collect())) == sorted(want)


def plain_path(supports, n, target, tol):
    """The supports that a calibration asks for, with a search of its own for each, and its result."""
    import math

    cap, low, high, at, best, asked = int(target * (1 + tol)), 1, n, max(1, int(n * 0.6)), (n, 0), []
    while low <= high:
        at = min(max(at, low), high)
        asked.append(at)
        total = sum(s >= at for s in supports)
        if total > cap:
            low = at + 1
            at = int((low * (high + 1)) ** 0.5)
            continue
        best = min([best, *((s, sum(x >= s for x in supports)) for s in set(supports) if s >= at)], key=lambda k: (abs(k[1] - target), k[0]))
        if best[1] >= int(target * (1 - tol)):
            break
        high, earlier = at - 1, sum(s >= 1.15 * at for s in supports)
        growth = math.log(total / earlier) / math.log(1.15) if earlier and total > earlier else 1.0
        at = max(at // 2, int(at * (total / target) ** (1 / growth))) if total else at // 2
    return best, asked


def test_calibration_searches_less_often_than_it_asks(toy, monkeypatch):
    from prefpat.operators import vertical

    supports = [r["sup"] for r in mine.frequent(toy, 1).select("sup").collect()]
    whole, searched, asked = vertical.count_by_support, [], []
    monkeypatch.setattr(vertical, "count_by_support", lambda *a: searched.append(a[2]) or whole(*a))
    for target, tol in ((100, 0.5), (300, 0.01), (1500, 0.02), (10**6, 0.1)):
        best, path = plain_path(supports, toy.n, target, tol)
        assert mine.calibrate_min_sup(toy, target, tol) == best, target
        asked += path
    assert len(searched) < len(asked)


def test_counts_from_a_rising_floor_are_whole(toy, brute):
    from collections import Counter

    from prefpat.operators import vertical

    supports = [r["sup"] for r in mine.frequent(toy, 1).select("sup").collect()]
    for most in (5, 40, 10**6):
        floor, counts = vertical.count_by_support(toy, vertical.sent_bitmaps(toy), 1, most)
        assert counts == Counter(s for s in supports if s >= floor) and (floor == 1 or most < len(supports)), most
    maps = vertical.collect_bitmaps(toy)
    tally = vertical.Tally(1, 5)
    tally.search(maps.columns, vertical.own_pairs(0, 1, ITEMS))
    assert tally.floor > 1 and tally.seen <= 10 and sum(s >= tally.floor - 1 for s in supports) > 5
    assert sorted(p for t in range(5) for p in vertical.own_pairs(t, 5, 9)) == [(i, j) for i in range(9) for j in range(i, 9)]


def test_labels_are_made_before_rows_are_multiplied(spark):
    """Above the explosion a label's expression would be computed again for every item."""
    from pyspark.sql import functions as F

    from prefpat.operators.encode import binarise

    texts = spark.range(3).select("id", F.concat(F.lit("a b "), F.col("id").cast("string")).alias("text")).repartition(2)
    long = binarise(texts, F.col("id"), F.split("text", " "), F.instr("text", "b") > F.col("id"))
    plan = long._jdf.queryExecution().optimizedPlan().toString().splitlines()
    assert next(i for i, x in enumerate(plan) if "instr" in x) > next(i for i, x in enumerate(plan) if "Generate" in x)


def test_items_of_repeated_rows_are_numbered_by_transactions(spark, monkeypatch):
    """Item a has the most rows, b and c the most transactions; d has rows enough but not transactions."""
    from prefpat.operators import encode as enc

    rows = [(0, "a", 1)] * 9 + [(t, i, t % 2) for t in range(4) for i in "bc" if (t, i) != (3, "c")] + [(2, "a", 0)] + [(1, "d", 1)] * 5 + [(9, None, None)]
    long = spark.createDataFrame(rows, "tid long, item string, label int")
    for most in (enc.MAX_ITEMS, 3):
        monkeypatch.setattr(enc, "MAX_ITEMS", most)
        ds = encode(long, min_sup=2)
        assert [tuple(r) for r in ds.items.orderBy("item_id").collect()] == [(0, "b", 4), (1, "c", 3), (2, "a", 2)]
        assert {r.tid: (r["items"], r.m0, r.label) for r in ds.transactions.collect()} == {0: ([0, 1, 2], 7, 1), 1: ([0, 1], 3, 1), 2: ([0, 1, 2], 7, 0), 3: ([0], 1, 1), 9: ([], 0, None)}
        assert (ds.n, ds.n_pos, ds.n_labelled, ds.n_items, ds.n_items_all) == (5, 3, 4, 3, 4)


@pytest.mark.parametrize("name", ["doc_words", "conv_words", "page_words"])
def test_transactions_of_words_are_counted_without_texts(spark, name):
    from prefpat.queries import least_support
    from prefpat.sources.encodings import ENCODINGS, word_transactions

    sf = "/root/testdata/sf0.001"
    ids = word_transactions(spark, sf, name)
    assert {r.tid for r in ids.collect()} == {r.tid for r in ENCODINGS[name](spark, sf).select("tid").collect()}
    assert "regexp_extract_all" not in ids._jdf.queryExecution().optimizedPlan().toString() and least_support(spark, sf, name, 1.0) == ids.count()


def test_documents_are_joined_by_their_words(spark, tmp_path):
    """Whole texts are not sent to the join with the labels; a text without words stays a transaction."""
    from prefpat.sources.encodings import doc_words

    spark.createDataFrame([(1, "One two, one TWO three! ab"), (2, "?"), (3, None), (4, "unlabelled words")], "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, 1), (2, 0), (3, None)], "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    long = doc_words(spark, str(tmp_path))
    assert sorted(map(str, map(tuple, long.collect()))) == sorted(map(str, [(1, "one", 1), (1, "two", 1), (1, "three", 1), (2, None, 0), (3, None, None)]))
    plan = long._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Join") < plan.index("regexp_extract_all")
