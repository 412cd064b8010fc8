"""Experiment grids: whole sessions as single tasks, results as plans.

A grid row is a session. Sessions of one dataset and quality share a pattern matrix,
broadcast once; its size is checked when it is collected.
"""

from __future__ import annotations

import functools
import itertools
import time
from collections.abc import Iterable, Sequence
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prefpat.functions import quality
from prefpat.operators import measures, mine
from prefpat.operators.encode import EncodedDataset
from prefpat.plans.baselines import multiplicative, poolrank
from prefpat.plans.session import LoopConfig, PreferenceLoop
from prefpat.plans.spaces import MatrixSpace, Shown
from prefpat.plans.users import LikeRanker, QualityRanker

GRID_SCHEMA = "session_id string, method string, dataset string, phi string, k int, l int, A double, features string, cell string, seed int, rounds int"
RESULT_SCHEMA = GRID_SCHEMA + ", iter int, avg_quality double, max_quality double, entropy double, entropy_share double, pairs int, seconds double, status string"
FACTORS = ["k", "features", "A", "l", "cell"]
QUALITIES = ("frequency", "chi2", "surprisingness")


@dataclass
class Prepared:
    """A dataset with its frequent patterns; spaces by hidden quality."""

    ds: EncodedDataset
    patterns: DataFrame
    min_sup: int

    def space(self, phi: str) -> MatrixSpace:
        graded = quality.with_percentile(quality.with_quality(self.patterns, self.ds, phi))
        return MatrixSpace.collect(graded, self.ds)


def prepare(ds: EncodedDataset, min_sup: int | None = None, target: int = 140_000, max_len: int | None = None) -> Prepared:
    if min_sup is None:
        min_sup, _ = mine.calibrate_min_sup(ds, target)
    return Prepared(ds, mine.frequent(ds, min_sup, max_len=max_len).persist(), min_sup)


def cell_of(name: str):
    return "random" if name == "random" else ("top", int(name.removeprefix("top")))


def grid(datasets: Sequence[str], phis: Iterable[str] = QUALITIES, k=(5,), l=(1,), A=(0.5,), features=("ILFT",), cell=("top1",), seeds=range(3), rounds: int = 30, method: str = "loop") -> pd.DataFrame:  # noqa: E741
    """Rows of all combinations."""
    rows = []
    for d, p, kk, ll, a, f, c, s in itertools.product(datasets, phis, k, l, A, features, cell, seeds):
        rows.append((f"{method}/{d}/{p}/k{kk}/l{ll}/A{a}/{f}/{c}/s{s}", method, d, p, kk, ll, a, f, c, s, rounds))
    return pd.DataFrame(rows, columns=["session_id", "method", "dataset", "phi", "k", "l", "A", "features", "cell", "seed", "rounds"])


def judged(space: MatrixSpace, shown: list[Shown], for_entropy: list[Shown] | None = None) -> tuple[float, float, float, float]:
    """Average and best percentile, entropy in bits and its share of the most there can be."""
    own = for_entropy if for_entropy is not None else shown
    entropy = space.entropy(own)
    pct = [s.pct for s in shown]
    return sum(pct) / len(pct), max(pct), entropy, entropy / len(own)


def run_session(space: MatrixSpace, row) -> list[tuple]:
    """One session of any method: (iter, measures, pairs, seconds, status) rows."""
    out, began = [], time.perf_counter()

    def lap() -> float:
        nonlocal began
        now = time.perf_counter()
        spent, began = now - began, now
        return spent

    if row.method in ("loop", "uniform"):
        cfg = LoopConfig(k=row.k, l=row.l if row.method == "loop" else 0, A=row.A, features=row.features, cell=cell_of(row.cell) if row.method == "loop" else "random", seed=row.seed, learn=row.method == "loop")
        loop, ranker = PreferenceLoop(space, cfg), QualityRanker()
        for _ in range(row.rounds):
            done = loop.step(ranker)
            out.append((done.iter, *judged(space, [s for s, _ in done.ordered]), done.pairs, lap(), "ok"))
    elif row.method.startswith("multiplicative"):
        found = multiplicative.run(space, LikeRanker(space), 10 * row.rounds, seed=row.seed, weights="double" if row.method.endswith("double") else "log")
        spent = lap() / max(1, row.rounds)
        for i, query in enumerate(multiplicative.windows(found.samples)):
            out.append((i + 1, *judged(space, query), 0, spent, found.status))
        if not out:
            out.append((0, None, None, None, None, 0, spent, found.status))
    elif row.method == "poolrank":
        cfg = poolrank.PoolConfig(k=row.k, features=row.features, seed=row.seed)
        for i, (query, best) in enumerate(poolrank.run(space, QualityRanker(), cfg, row.rounds)):
            out.append((i + 1, *judged(space, best), len(query) * (len(query) - 1) // 2, lap(), "ok"))
    else:
        raise ValueError(row.method)
    return out


def session_kernel(sent):
    """A grid row to the result rows of its session."""

    def kernel(group: pd.DataFrame) -> pd.DataFrame:
        row = next(group.itertuples(index=False))
        return pd.DataFrame([(*row, *f) for f in run_session(sent.value, row)], columns=[c.split()[0] for c in RESULT_SCHEMA.split(", ")])

    return kernel


def run_grid(spark: SparkSession, rows: pd.DataFrame, prepared: dict[str, Prepared]) -> DataFrame:
    """A result row for every session and round; sessions run side by side."""
    parts = []
    for (dataset, phi), own in rows.groupby(["dataset", "phi"], sort=True):
        kernel = session_kernel(spark.sparkContext.broadcast(prepared[dataset].space(phi)))
        sessions = spark.createDataFrame(own, GRID_SCHEMA).repartition(min(len(own), 4 * spark.sparkContext.defaultParallelism), "session_id")
        parts.append(sessions.groupBy("session_id").applyInPandas(kernel, RESULT_SCHEMA))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def session_regret(results: DataFrame) -> DataFrame:
    """Regret sums of a session's rounds, for each measure."""
    keys = [c.split()[0] for c in GRID_SCHEMA.split(", ")]
    sums = [F.sum(1 - F.col(c)).alias(n) for c, n in (("avg_quality", "avg_regret"), ("max_quality", "max_regret"), ("entropy_share", "entropy_regret"))]
    return results.groupBy(*keys).agg(*sums, F.sum("entropy").alias("entropy_bits"), F.avg("seconds").alias("seconds"), F.max("status").alias("status"))


def marginals(regret: DataFrame, factors: Sequence[str] = FACTORS) -> DataFrame:
    """Mean and deviation for every level of every factor, in one grouping-sets query."""
    view = f"regret_{abs(hash(tuple(factors))) % 10**8}"
    regret.createOrReplaceTempView(view)
    sets = ", ".join(f"({f})" for f in factors)
    factor = "CASE " + " ".join(f"WHEN grouping({f}) = 0 THEN '{f}'" for f in factors) + " END"
    level = "coalesce(" + ", ".join(f"CASE WHEN grouping({f}) = 0 THEN CAST({f} AS STRING) END" for f in factors) + ")"
    stats = ", ".join(f"avg({m}) AS {m}, stddev_samp({m}) AS {m}_sd" for m in ("avg_regret", "max_regret", "entropy_regret", "entropy_bits"))
    return regret.sparkSession.sql(f"SELECT {factor} AS factor, {level} AS level, count(*) AS sessions, {stats} FROM {view} GROUP BY GROUPING SETS ({sets})")


#: The levels of the recommended preset, as a grid names them.
PRESET = {"k": 5, "features": "ILFT", "A": 0.5, "l": 1, "cell": "top1"}


def one_at_a_time(regret: DataFrame, preset: dict = PRESET) -> DataFrame:
    """Mean and deviation for every level of every factor, over the sessions in which all
    other factors are at the preset; a session of the preset counts for each factor."""
    at = {f: F.col(f) == F.lit(v) for f, v in preset.items()}
    others = lambda f: functools.reduce(lambda a, b: a & b, [c for g, c in at.items() if g != f])
    named = F.array_compact(F.array(*[F.when(others(f), F.struct(F.lit(f).alias("factor"), F.col(f).cast("string").alias("level"))) for f in preset]))
    stats = [agg(m).alias(m + end) for m in ("avg_regret", "max_regret", "entropy_regret", "entropy_bits") for agg, end in ((F.avg, ""), (F.stddev_samp, "_sd"))]
    return regret.withColumn("own", F.explode(named)).groupBy("own.factor", "own.level").agg(F.count(F.lit(1)).alias("sessions"), *stats)


def factor_grid(datasets: Sequence[str], phis: Iterable[str] = QUALITIES, seeds=range(2), rounds: int = 30) -> pd.DataFrame:
    """The preset and every level of every factor, one changed at a time."""
    base = dict(datasets=datasets, phis=list(phis), seeds=seeds, rounds=rounds)
    levels = [{}, {"k": [10]}, {"features": ["I", "ILF"]}, {"A": [0.1]}, {"l": [0, 2, 3]}, {"cell": ["random", "top2", "top3"]}]
    return pd.concat([grid(**base, **level) for level in levels], ignore_index=True)


def items_scaling(spark: SparkSession, prepared: dict[str, Prepared], rounds: int = 5) -> DataFrame:
    """``(dataset, items, transactions, patterns, seconds)``: time of a round against the
    number of items, under the preset. Sessions run one after the other on the driver."""
    rows = []
    for name, p in prepared.items():
        space = p.space("surprisingness")
        loop = PreferenceLoop(space, LoopConfig.recommended())
        began = time.perf_counter()
        loop.run(rounds, QualityRanker())
        rows.append((name, space.n_items, space.n, len(space.pattern), (time.perf_counter() - began) / rounds))
    return spark.createDataFrame(rows, "dataset string, items int, transactions int, patterns int, seconds double")


def scatter_points(prepared: Prepared, phi: str, rounds: Sequence[int] = (1, 29), seed: int = 0) -> pd.DataFrame:
    """Learned and hidden quality of every pattern after given rounds."""
    space, parts = prepared.space(phi), []
    loop = PreferenceLoop(space, CHARACTERISTIC.replace(seed=seed))
    for i in range(1, max(rounds) + 1):
        loop.step(QualityRanker())
        if i in rounds:
            parts.append(pd.DataFrame({"rounds": i, "pattern": space.pattern, "learned": space.weights(loop.weights, loop.cfg.A), "hidden": space.phi}))
    return pd.concat(parts, ignore_index=True)


def comparison(regret: DataFrame) -> DataFrame:
    """Methods by qualities: mean and deviation; sessions that failed are counted apart."""
    good = regret.where("status = 'ok'")
    stats = good.groupBy("method", "phi").agg(F.avg("avg_regret").alias("avg_regret"), F.stddev_samp("avg_regret").alias("avg_regret_sd"), F.avg("entropy_regret").alias("entropy_regret"), F.stddev_samp("entropy_regret").alias("entropy_regret_sd"))
    return measures.failures(regret).join(stats, ["method", "phi"], "left")


def compare(spark: SparkSession, prepared: dict[str, Prepared], seeds=range(3), phis=QUALITIES, rounds: int = 30) -> DataFrame:
    rows = pd.concat([grid(list(prepared), phis, seeds=seeds, rounds=rounds, method=m) for m in ("loop", "multiplicative_log", "multiplicative_double", "poolrank", "uniform")])
    return comparison(session_regret(run_grid(spark, rows, prepared)))


CHARACTERISTIC = LoopConfig(k=3, l=1, A=0.1, features="I", cell="random")


def characteristic(space, seed: int = 0, rounds: int = 30) -> PreferenceLoop:
    """The session that is shown round by round: items only, three patterns a query."""
    loop = PreferenceLoop(space, CHARACTERISTIC.replace(seed=seed))
    loop.run(rounds, QualityRanker())
    return loop


def scatter(prepared: Prepared, phi: str, rounds: Sequence[int] = (1, 29), seed: int = 0) -> list[tuple[int, float, float]]:
    """Correlation of learned and hidden quality after given rounds."""
    import numpy as np

    space, out = prepared.space(phi), []
    loop = PreferenceLoop(space, CHARACTERISTIC.replace(seed=seed))
    for i in range(1, max(rounds) + 1):
        loop.step(QualityRanker())
        if i in rounds:
            learned = pd.Series(space.weights(loop.weights, loop.cfg.A))
            hidden = pd.Series(space.phi)
            value = 0.0 if learned.std() == 0 else float(np.corrcoef(learned, hidden)[0, 1])
            out.append((i, value, float(learned.rank().corr(hidden.rank())) if learned.std() else 0.0))
    return out


def ten_cells(loop: PreferenceLoop, n: int = 10) -> pd.DataFrame:
    """Best pattern of each of ``n`` accepted cells, its learned quality and its chance
    under a weighted draw."""
    from prefpat.operators.xorcells import draw_py, estimate_m

    total, w_max = loop.space.total_and_max(loop.weights, loop.cfg.A)
    first, last = estimate_m(total, w_max, loop.bounds)
    rows, attempt = [], 0
    while len(rows) < n and attempt < 20:
        drawn = draw_py(last, loop.space.n_items, range(n), f"{loop.cfg.seed}/cells/{attempt}")
        for cell in loop.space.cells(loop.weights, loop.cfg.A, drawn, first):
            own = loop.pick(cell, w_max, first, last)
            if own and len(rows) < n:
                best = min(own, key=lambda s: (-s.w, s.pattern))
                weight = sum(s.w for s in own)
                rows.append((len(rows), best.pattern, best.w, best.w / weight, weight / w_max, len(own)))
        attempt += 1
    return pd.DataFrame(rows, columns=["cell", "pattern", "quality", "within_cell_prob", "cell_weight", "size"])


def dataset_table(prepared: dict[str, Prepared]) -> DataFrame:
    out = None
    for p in prepared.values():
        row = measures.dataset_stats(p.ds, p.patterns, p.min_sup)
        out = row if out is None else out.unionByName(row)
    return out


def match_unseen(patterns: DataFrame, ds: EncodedDataset, unseen: DataFrame) -> DataFrame:
    """``(tid, pattern)``: given patterns in transactions from elsewhere, under the
    dataset's dictionary."""
    from prefpat.operators.encode import pack

    other = EncodedDataset("unseen", pack(unseen, ds.items, ds.words), ds.items, 0, 0, 0, ds.n_items, ds.n_items)
    return mine.cover(patterns, other).select("tid", "pattern")


def pca_map(prepared: Prepared, loop: PreferenceLoop, keep: float = 0.01) -> DataFrame:
    """A kept share of the patterns on two axes, with their learned quality."""
    from prefpat.functions.model import with_weight

    kept = measures.item_pca(prepared.patterns, prepared.ds.n_items, 2, keep)
    return with_weight(kept, loop.weights, prepared.ds, loop.cfg.A).select("pattern", "pc1", "pc2", "w")
