import numpy as np
import pandas as pd
import pytest

from prefpat import queries as q
from prefpat.functions.model import Weights
from prefpat.plans import experiments, learn
from prefpat.plans.baselines import multiplicative, poolrank
from prefpat.plans.session import LoopConfig, PreferenceLoop
from prefpat.plans.spaces import SparkSpace
from prefpat.plans.users import CallbackRanker, LikeRanker, NoisyRanker, QualityRanker, liked_items

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def prepared(spark):
    return q.prepared(spark, SF, part=0.2, max_len=3)


@pytest.fixture(scope="module")
def space(prepared):
    return prepared.space("surprisingness")


def test_transactions_score_patterns_never_shown(space):
    """Every transaction with a weight counts for every pattern that it contains."""
    loop = PreferenceLoop(space, LoopConfig(seed=2))
    loop.run(5, QualityRanker())
    w = loop.weights
    shown = {s.pattern for r in loop.rounds for s, _ in r.ordered}
    rest = space.score(Weights(w.items, w.length, w.frequency))
    rows = {tuple(t) for t in space.transactions.view(np.int64).tolist()}
    assert 0 < len(w.transactions) <= loop.cfg.T and {m for m, _ in w.transactions} <= rows
    for p in np.linspace(0, len(space.pattern) - 1, 60).astype(int):
        if space.pattern[p] not in shown:
            inside = [x for m, x in w.transactions if all(np.int64(a) & np.int64(b) == np.int64(a) for a, b in zip(space.masks[p].view(np.int64), m))]
            assert space.score(w)[p] == pytest.approx(rest[p] + sum(inside))


def test_grouped_transactions_give_shown_patterns_the_literal_columns(space):
    """A group's weight is shared among all its members, so unseen patterns get their part."""
    loop = PreferenceLoop(space, LoopConfig(transactions="grouped"))
    loop.run(4, QualityRanker())
    shown = loop.all_shown()
    inside, sizes, groups = space.coverage(shown)
    assert sizes.sum() == space.n and (inside @ sizes == [s.sup for s in shown]).all()
    members = space.members(shown, groups)
    assert [len(members[g]) for g in groups] == sizes.tolist()
    with pytest.raises(ValueError):
        LoopConfig(active_only=True)


def test_updates_fall_on_all_transactions_alike(space):
    """Drawing first and fetching only what was drawn is the same as a fit over all columns."""
    loop = PreferenceLoop(space, LoopConfig(seed=5))
    loop.run(3, QualityRanker())
    shown = loop.all_shown()
    whole = np.concatenate([loop.plain_features(shown), space.inside(shown).astype(float)], axis=1)
    w = learn.scd_l1(loop.deltas(shown, whole), loop.cfg.lam, loop.cfg.T, "5/3").weights
    width = space.n_items + 2
    assert loop.weights.items == pytest.approx(w[: space.n_items])
    want = sorted((tuple(space.transactions[i - width].view(np.int64).tolist()), w[i]) for i in range(width, len(w)) if w[i])
    assert sorted(loop.weights.transactions) == pytest.approx(want) if not want else [m for m, _ in sorted(loop.weights.transactions)] == [m for m, _ in want]


def test_queries_keep_their_promises(space):
    loop = PreferenceLoop(space, LoopConfig(k=5, l=2))
    loop.run(8, QualityRanker())
    best = -1.0
    for before, now in zip([None, *loop.rounds], loop.rounds):
        names = [s.pattern for s, _ in now.query]
        assert len(set(names)) == 5
        if before:
            assert names[:2] == [s.pattern for s, _ in before.ordered[:2]]
        assert max(s.phi for s, _ in now.query) >= best
        best = max(s.phi for s, _ in now.query)
    assert len(loop.current()) == 5 and len(loop.more(4)) == 4


@pytest.mark.parametrize("cfg", [LoopConfig(), LoopConfig(transactions="grouped"), LoopConfig(k=3, A=0.1, features="I", cell="random"), LoopConfig(l=0, cell=("top", 3), features="ILF")])
def test_spark_and_matrix_run_the_same_session(prepared, space, cfg):
    graded = q.graded(prepared, "surprisingness")
    one, two = PreferenceLoop(SparkSpace(graded, prepared.ds), cfg), PreferenceLoop(space, cfg)
    for loop in (one, two):
        loop.run(2, QualityRanker())
    assert [r["pattern"] for r in one.rows("s")] == [r["pattern"] for r in two.rows("s")]
    shown = one.current()
    assert one.space.entropy(shown) == pytest.approx(two.space.entropy(shown))


def test_same_seed_same_session_and_other_users(space):
    runs = [[r["pattern"] for r in (lambda loop: (loop.run(3, ranker), loop)[1])(PreferenceLoop(space, LoopConfig(seed=4))).rows("s")] for ranker in (QualityRanker(), QualityRanker(), NoisyRanker(QualityRanker(), 0.0), CallbackRanker(lambda sets: sorted(range(len(sets)), key=lambda i: -len(sets[i]))))]
    assert runs[0] == runs[1] == runs[2] != runs[3]


def test_learning_beats_no_learning(space):
    rows = [experiments.run_session(space.with_quality(space.sup / space.n, np.argsort(np.argsort(space.sup)) / len(space.sup)), r) for m in ("loop", "uniform") for r in experiments.grid(["x"], ["frequency"], seeds=[1], rounds=12, method=m).itertuples(index=False)]
    loop, uniform = (sum(1 - r[1] for r in session) for session in rows)
    assert loop < 0.7 * uniform


def test_liked_items(space):
    chosen, share = liked_items(space)
    hits = np.array([2 * chosen[i].sum() > len(i) for i in space.items])
    assert share == pytest.approx(hits.mean()) and share >= 0.15


def test_multiplicative_forms_agree_until_overflow(space):
    likes = LikeRanker(space)
    one, two = (multiplicative.run(space, likes, 60, weights=w) for w in ("log", "double"))
    assert [s.pattern for s in one.samples] == [s.pattern for s in two.samples]

    class Always:
        def likes(self, items):
            return True

    assert multiplicative.run(space, Always(), 40, b=1e60, weights="double").status == "overflow"
    assert multiplicative.run(space, Always(), 40, b=1e60).status == "ok"
    assert [len(w) for w in multiplicative.windows(one.samples)] == [5] * 6


def test_pool_ranking_learns_frequency(prepared):
    out = poolrank.run(prepared.space("frequency"), QualityRanker(), poolrank.PoolConfig(features="ILF", pool=300), 6)
    assert np.mean([s.pct for s in out[-1][1]]) > 0.9


def wide_space(n, n_items=12, seed=3):
    """All pairs and single items over random transactions, with the empty pattern."""
    from itertools import combinations

    from prefpat.plans.spaces import MatrixSpace, masks_of

    rng = np.random.default_rng(seed)
    held = rng.random((n, n_items)) < np.linspace(0.2, 0.8, n_items)
    rows = np.array([[x] for x in (held * (1 << np.arange(n_items))).sum(axis=1)], np.uint64)
    sets = [(), *[(i,) for i in range(n_items)], *combinations(range(n_items), 2)]
    names = np.array([",".join(map(str, i)) for i in sets], object)
    masks = np.array([masks_of(i, 1) for i in sets], np.int64).view(np.uint64)
    sup = np.array([held[:, list(i)].all(axis=1).sum() for i in sets])
    phi = rng.random(len(sets))
    return MatrixSpace(names, [np.array(i, np.int64) for i in sets], masks, np.array(list(map(len, sets))), sup, phi, phi, rows, n_items), held, sets


def test_pool_ranking_learns_from_every_transaction(monkeypatch):
    """Inner products by common covers are those of the written-out columns."""
    from prefpat.plans import spaces

    space, held, sets = wide_space(1003)
    inside = np.stack([held[:, list(i)].all(axis=1) for i in sets]).astype(int)
    monkeypatch.setattr(spaces, "COVER_ROWS", 200)
    monkeypatch.setattr(spaces, "COVER_PATTERNS", 7)
    places = np.array([0, 5, 40])
    assert (space.common_covers(places) == inside[places] @ inside.T).all()
    cfg = poolrank.PoolConfig(pool=40)
    out = poolrank.run(space, QualityRanker(), cfg, 4)
    at = {p: i for i, p in enumerate(space.pattern)}
    plain = poolrank.plain_features(space, np.arange(len(sets)), poolrank.FeatureSpec.of("ILFT"))
    whole = np.concatenate([plain, inside], axis=1)
    deltas = [whole[at[a.pattern]] - whole[at[b.pattern]] for q, _ in out for i, a in enumerate(q) for b in q[i + 1 :]]
    score = whole @ learn.rank_svm(np.array(deltas), cfg.c, seed=cfg.seed)
    assert [s.pattern for s in out[-1][1]] == space.pattern[np.lexsort((space.pattern.astype(str), -score))[:5]].tolist()


def test_pool_ranking_makes_no_table_of_patterns_by_transactions():
    import tracemalloc

    space, _, sets = wide_space(200_000)
    tracemalloc.start()
    poolrank.run(space, QualityRanker(), poolrank.PoolConfig(), 2)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < len(sets) * space.n  # a byte for each would be too much; numbers of eight took 16 times that


def test_grid_and_marginals(spark, prepared):
    rows = pd.concat([experiments.grid(["emb_sign"], ["frequency"], seeds=[0], rounds=3, cell=c) for c in (["random", "top1"],)])
    results = experiments.run_grid(spark, rows, {"emb_sign": prepared}).persist()
    assert results.count() == 6
    found = {(r.factor, r.level): r.sessions for r in experiments.marginals(experiments.session_regret(results)).collect()}
    assert found[("cell", "random")] == 1 and found[("k", "5")] == 2
    cells = experiments.ten_cells(experiments.characteristic(prepared.space("frequency"), rounds=2))
    assert len(cells) == 10 and cells.pattern.nunique() > 5 and (cells.within_cell_prob <= 0.2).all()


def regrets(space, seeds, **level):
    rows = experiments.grid(["x"], ["frequency"], seeds=seeds, rounds=15, **level).itertuples(index=False)
    sums = [[sum(1 - v for v in c) for c in list(zip(*experiments.run_session(space, r)))[1:3]] for r in rows]
    return np.mean(sums, axis=0)


def test_published_directions(prepared):
    """Which level of a factor is better, on average over seeds: cells, retention, size."""
    space = prepared.space("frequency")
    seeds = range(6)
    preset = regrets(space, seeds)
    assert preset[0] < regrets(space, seeds, cell=["random"])[0]
    assert preset[1] < regrets(space, seeds, l=[0])[1]
    assert regrets(space, seeds, k=[10])[1] < preset[1]
    assert regrets(space, seeds, features=["ILF"])[0] < regrets(space, seeds, features=["I"])[0]


def test_whole_grid_has_every_level():
    rows = experiments.factor_grid(["a"], seeds=[0])
    assert {c: set(rows[c]) for c in experiments.FACTORS} == {"k": {5, 10}, "features": {"I", "ILF", "ILFT"}, "A": {0.5, 0.1}, "l": {0, 1, 2, 3}, "cell": {"random", "top1", "top2", "top3"}}
    assert rows.session_id.is_unique and len(rows) == 11 * 3


def test_levels_are_compared_at_the_preset(spark):
    rows = [(f"s{i}", k, "ILFT", 0.5, l, "top1", float(v), 0.0, 0.0, 0.0) for i, (k, l, v) in enumerate([(5, 1, 1), (5, 1, 3), (10, 1, 5), (5, 0, 7)])]
    df = spark.createDataFrame(rows, "session_id string, k int, features string, A double, l int, cell string, avg_regret double, max_regret double, entropy_regret double, entropy_bits double")
    got = {(r.factor, r.level): (r.sessions, r.avg_regret) for r in experiments.one_at_a_time(df).collect()}
    assert got == {("k", "5"): (2, 2), ("k", "10"): (1, 5), ("features", "ILFT"): (2, 2), ("A", "0.5"): (2, 2), ("l", "1"): (2, 2), ("l", "0"): (1, 7), ("cell", "top1"): (2, 2)}


def test_axes_are_those_of_a_plain_decomposition(prepared):
    from prefpat.operators import measures

    rows = measures.item_pca(prepared.patterns, prepared.ds.n_items, 2, keep=1.0).select("items", "pc1", "pc2").collect()
    x = np.zeros((len(rows), prepared.ds.n_items))
    for i, r in enumerate(rows):
        x[i, r["items"]] = 1
    x -= x.mean(axis=0)
    u, s, _ = np.linalg.svd(x, full_matrices=False)
    for a in range(2):
        own = np.array([r[f"pc{a + 1}"] for r in rows])
        assert own.var() == pytest.approx(s[a] ** 2 / len(x), rel=1e-9)


def test_total_variation(spark):
    from prefpat.operators import measures

    draws = spark.createDataFrame([("a",), ("a",), ("b",), ("a",)], "pattern string")
    weights = spark.createDataFrame([("a", 1.0), ("b", 1.0), ("c", 2.0)], "pattern string, w double")
    assert measures.total_variation(draws, weights).first().total_variation == pytest.approx(0.5)


def test_regret_of_the_shown_session(spark):
    from prefpat.operators import measures

    pct = [(".51", 0.51), (".13", 0.13), (".84", 0.84), (".46", 0.46), (".41", 0.41), (".99", 0.99), (".97", 0.97)]
    shown = [("s", 1, i, p) for i, p in enumerate((".51", ".13", ".84"))] + [("s", 2, i, p) for i, p in enumerate((".84", ".46", ".41"))] + [("s", 30, i, p) for i, p in enumerate((".99", ".97", ".51"))]
    quality = measures.query_quality(spark.createDataFrame(shown, "session_id string, iter int, pos int, pattern string"), spark.createDataFrame(pct, "pattern string, pct double"))
    got = {r.iter: (round(1 - r.avg_quality, 4), round(1 - r.max_quality, 2)) for r in quality.collect()}
    assert got[1] == (0.5067, 0.16) and got[2][1] == 0.16 and got[30][1] == 0.01


def test_configuration_is_checked():
    with pytest.raises(ValueError):
        LoopConfig(k=3, l=3)
    with pytest.raises(ValueError):
        LoopConfig(A=0)
    assert LoopConfig.recommended() == LoopConfig(k=5, features="ILFT", A=0.5, l=1, cell=("top", 1))
