"""The library's queries by name, with SQL for those that SQL can express.

Pattern queries run over the patterns of up to three items of the embeddings' signs,
with a support of a fifth of the transactions; weights of models are fixed by a rule.
"""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from prefpat.functions import features, model, quality
from prefpat.functions.features import FeatureSpec
from prefpat.functions.lineage import shared_folder
from prefpat.functions.model import Weights
from prefpat.operators import measures, mine, pairs, relational, sample, xorcells
from prefpat.operators.encode import EncodedDataset, item_supports
from prefpat.plans import experiments, learn, sqlsurface
from prefpat.plans.baselines import multiplicative, poolrank
from prefpat.plans.session import ROW_SCHEMA, LoopConfig, PreferenceLoop
from prefpat.plans.spaces import SparkSpace
from prefpat.plans.users import LikeRanker, QualityRanker, liked_items
from prefpat.sources.encodings import ENCODINGS, dataset, table, word_transactions
from prefpat.streaming import streams

FLOOR = 0.1
#: Shares of the transactions at which the query's patterns are mined.
CLOSED_PART, CLOSED_LONGEST = 0.6, 6
#: The grid's encodings and patterns; the published size is 140,000 on ten datasets.
GRID_DATASETS, GRID_PATTERNS = ["emb_sign", "doc_words"], 20_000
#: Samples of a multiplicative session.
SAMPLES = 300


def share(n: int, part: float) -> int:
    return -int(-(n * part) // 1)


def emb(spark, sf, part: float = 0.2, max_len: int | None = 3, engine: str = "auto", name: str = "emb_sign"):
    ds = dataset(spark, sf, name, least_support(spark, sf, name, part)).persist()
    return ds, mine.frequent(ds, share(ds.n, part), engine, max_len).persist()


def least_support(spark, sf, name: str, part: float) -> int:
    """Of word encodings only the items that can be frequent are packed."""
    if not name.endswith("_words"):
        return 1
    return share(word_transactions(spark, sf, name).count(), part)


def fixed_weights(ds: EncodedDataset) -> Weights:
    w = Weights.zero(ds.n_items)
    for i in range(ds.n_items):
        w.items[i] = (i * 37 % 11 - 5) / 10
    w.length, w.frequency = 0.5, -0.3
    return w


def weighted(spark, sf):
    ds, patterns = emb(spark, sf)
    return ds, model.with_weight(patterns, fixed_weights(ds), ds, FLOOR)


def r6(*columns):
    return [F.round(c, 6).alias(c) for c in columns]


# --- encoding and mining -----------------------------------------------------------


def encoding(name):
    def query(spark, sf):
        long = ENCODINGS[name](spark, sf).where("item is not null")
        return long.groupBy("item").agg(F.count_distinct("tid").alias("support"), F.count_distinct(F.when(F.col("label") == 1, F.col("tid"))).alias("sup_pos"))

    return query


def dataset_stats(spark, sf):
    ds, patterns = emb(spark, sf)
    return measures.dataset_stats(ds, patterns, share(ds.n, 0.2))


def frequent(engine="auto", name="emb_sign", part=0.2):
    def query(spark, sf):
        _, patterns = emb(spark, sf, part, 3, engine, name)
        return patterns.select("pattern", "len", "sup", "sup_pos")

    return query


def support_by_class(spark, sf):
    ds, patterns = emb(spark, sf)
    return mine.support(patterns, ds)


def closed_patterns(spark, sf):
    """Over all lengths: words of conversations, of which some always come together."""
    patterns = emb(spark, sf, CLOSED_PART, None, "auto", "conv_words")[1]
    return mine.closed(patterns).select("pattern", "sup")


def topk_by_support(spark, sf):
    return mine.top_k(emb(spark, sf)[1].where("len >= 2"), "sup", 25).select("pattern", "sup")


def association_rules(spark, sf):
    ds, patterns = emb(spark, sf)
    return mine.rules(patterns, 0.5, ds.n).select(F.col("left").alias("lhs"), F.col("right").alias("rhs"), "sup", *r6("confidence", "lift"))


def calibrated_min_sup(spark, sf):
    ds = dataset(spark, sf, "emb_sign").persist()
    theta, count = mine.calibrate_min_sup(ds, 20_000)
    return spark.createDataFrame([(ds.name, theta, count)], "dataset string, min_sup int, patterns int")


def constrained_patterns(spark, sf):
    _, patterns = emb(spark, sf)
    return mine.where(patterns, mine.has_item(3), F.col("len") >= 2).select("pattern", "sup")


# --- qualities, features, model -------------------------------------------------------


def of_quality(name, column="phi"):
    def query(spark, sf):
        ds, patterns = emb(spark, sf)
        return quality.with_quality(patterns, ds, name, column).select("pattern", *r6(column))

    return query


def q_chi2_literal(spark, sf):
    ds, patterns = emb(spark, sf)
    return patterns.withColumn("phi", quality.chi2(ds.n_labelled, ds.n_pos, "literal")).select("pattern", *r6("phi"))


def percentile_rank(spark, sf):
    ds, patterns = emb(spark, sf)
    return quality.with_percentile(patterns, "sup").select("pattern", *r6("pct"))


def quality_boxplot(spark, sf):
    ds, patterns = emb(spark, sf)
    return measures.five_numbers(quality.with_surprisingness(patterns, ds), "surprisingness").select(*r6("least", "lower", "median", "upper", "most"))


def feat_ilf(spark, sf):
    ds, patterns = emb(spark, sf)
    return features.feature_rows(patterns, ds, FeatureSpec.of("ILF")).select("pattern", "feature_id", *r6("value"))


def feat_transactions(spark, sf):
    ds, patterns = emb(spark, sf)
    return mine.cover(mine.top_k(patterns.where("len >= 2"), "sup", 5), ds)


def score_fixed_weights(spark, sf):
    return weighted(spark, sf)[1].select("pattern", F.round("score", 9).alias("score"))


def logistic_quality(spark, sf):
    return weighted(spark, sf)[1].select("pattern", *r6("w"))


# --- rankings and learning ---------------------------------------------------------------


def feedback(spark, sf):
    """Thirty patterns by the order of their hashes, in six rankings by support."""
    from pyspark.sql import Window

    _, patterns = emb(spark, sf)
    thirty = patterns.select("pattern", "sup", F.md5("pattern").alias("h")).orderBy("h").limit(30)
    numbered = thirty.withColumn("iter", F.floor((F.row_number().over(Window.orderBy("h")) - 1) / 5).cast("int"))
    return numbered.select(F.lit("s").alias("session_id"), "iter", F.row_number().over(Window.partitionBy("iter").orderBy(F.desc("sup"), "pattern")).alias("pos"), F.col("sup").cast("double").alias("level"), "pattern")


def pairs_from_rankings(spark, sf):
    return pairs.from_rankings(feedback(spark, sf)).select("iter", "winner", "loser")


def pair_deltas(spark, sf):
    _, patterns = emb(spark, sf)
    return pairs.deltas(pairs.from_rankings(feedback(spark, sf)), features.item_rows(patterns)).select("iter", "winner", "loser", "feature_id", "delta")


def discordant_pairs(spark, sf):
    _, scored = weighted(spark, sf)
    return pairs.discordant(pairs.from_rankings(feedback(spark, sf)), scored.withColumn("score", F.round("score", 9)))


def user_effort(spark, sf):
    return measures.effort(feedback(spark, sf)).select("shown", "distinct_shown", F.col("pairs"))


def scd_objective_drop(spark, sf):
    rows = pair_deltas(spark, sf).toPandas()  # three hundred pairs at most
    d = rows.pivot_table(index=["iter", "winner", "loser"], columns="feature_id", values="delta", fill_value=0.0).to_numpy()
    trace = learn.scd_l1(d, trace=True).trace
    return spark.createDataFrame([(i, float(trace[i])) for i in range(0, len(trace), 50)], "updates int, objective double")


# --- parity cells -----------------------------------------------------------------------------


def xor_draws(spark, sf):
    """Constraints over the items of the embeddings' signs."""
    drawn = xorcells.draw(spark, 4, dataset(spark, sf, "emb_sign").n_items, 3, 7)
    return drawn.select("draw_id", F.explode("xors").alias("x")).select("draw_id", F.col("x.x").alias("x"), F.col("x.c0").alias("c0"), F.col("x.parity").alias("parity"))


def udtf_xor_draws(spark, sf):
    """The same by the table function, which gets the number of items within SQL."""
    sqlsurface.register(spark)
    items = item_supports(ENCODINGS["emb_sign"](spark, sf))
    return spark.sql("SELECT d.draw_id, d.x, d.words[0] AS c0, d.parity FROM (SELECT CAST(count(*) AS INT) AS n FROM {items}) i, LATERAL xor_draws('7', 4, i.n, 3) d", items=items)


def cells(spark, sf, m: int, draws: int):
    ds, patterns = weighted(spark, sf)
    return xorcells.enumerate_cells(patterns, xorcells.draw(spark, m, ds.n_items, draws, 7), ds.masks)


def xor_cell_members(spark, sf):
    return cells(spark, sf, 4, 3).select("draw_id", "pattern")


def xor_cell_sizes(spark, sf):
    ds, patterns = emb(spark, sf)
    one = xorcells.draw(spark, 4, ds.n_items, 1, 7)
    joined = patterns.withColumn("one", F.lit(1)).join(F.broadcast(one.withColumn("one", F.lit(1))), "one")
    return joined.groupBy(xorcells.cell_id(ds.masks, F.col("xors")).alias("cell_id")).agg(F.count(F.lit(1)).alias("size"))


def nested_cells(spark, sf):
    ds, patterns = weighted(spark, sf)
    nested = xorcells.enumerate_cells(patterns, xorcells.draw(spark, 4, ds.n_items, 3, 7), ds.masks, at_least=0)
    return xorcells.cell_weights(nested).select("draw_id", "m", *r6("weight"), "size")


def cell_top(m):
    def query(spark, sf):
        return sample.from_cell(cells(spark, sf, 4, 3).withColumn("w", F.round("w", 9)), ("top", m)).select("draw_id", "pattern")

    return query


def cell_random(spark, sf):
    return sample.from_cell(cells(spark, sf, 4, 3), "random", 5).select("draw_id", "pattern")


def sample_batch(spark, sf):
    """Four distinct patterns from the best of accepted cells, all draws in one job."""
    ds, patterns = weighted(spark, sf)
    patterns = patterns.withColumn("w", F.round("w", 9))
    total, w_max = patterns.agg(F.sum("w"), F.max("w")).first()
    bounds = xorcells.CellBounds()
    first, last = xorcells.estimate_m(total, w_max, bounds)
    nested = xorcells.enumerate_cells(patterns, xorcells.draw(spark, last, ds.n_items, 8, 7), ds.masks, at_least=first).persist()
    accepted = xorcells.accept(xorcells.cell_weights(nested).where(F.col("m") >= first), w_max, bounds)
    own = nested.join(F.broadcast(accepted), "draw_id").where("matched >= m")
    return sample.batch(sample.from_cell(own, ("top", 1)), 4).select("draw_id", "pattern")


def predicted_ranking(spark, sf):
    """Patterns in the order that the model predicts, best first."""
    _, scored = weighted(spark, sf)
    return relational.numbered_rows(model.rank_keys(scored), "rank_key").select("pattern", (F.col("row") + 1).alias("place"))


def within_cell_prob(spark, sf):
    return sample.within_cell_prob(cells(spark, sf, 4, 3)).select("draw_id", "pattern", *r6("prob"))


def xor_count_estimate(spark, sf):
    _, patterns = weighted(spark, sf)
    total, w_max = patterns.agg(F.sum("w"), F.max("w")).first()
    first, last = xorcells.estimate_m(total, w_max, xorcells.CellBounds())
    return spark.createDataFrame([(round(total, 6), round(w_max, 6), first, last)], "total double, w_max double, first_m int, last_m int")


def uniform_pool(spark, sf):
    return sample.uniform(emb(spark, sf)[1], 50, 3).select("pattern")


def ideal_sampler(spark, sf):
    ds, patterns = emb(spark, sf)
    return sample.exact(patterns, F.col("sup").cast("double"), 20, 3, replace=True).select("draw_id", "pattern")


# --- the loop and its baselines ---------------------------------------------------------------------


def prepared(spark, sf, name="emb_sign", part=0.16, max_len=None, min_item=0.0):
    ds = dataset(spark, sf, name)
    if min_item:
        ds = dataset(spark, sf, name, share(ds.n, min_item)) if ds.n else ds
    return experiments.prepare(ds.persist(), share(ds.n, part), max_len=max_len)


def doc_prepared(spark, sf):
    n = table(spark, sf, "labels").count()
    theta = share(n, 0.25)
    return experiments.prepare(dataset(spark, sf, "doc_words", theta).persist(), theta, max_len=4)


def graded(p, phi):
    return quality.with_percentile(quality.with_quality(p.patterns, p.ds, phi))


def loop_rows(spark, loop, name):
    rows = spark.createDataFrame([tuple(r.values()) for r in loop.rows(name)], ROW_SCHEMA)
    return rows.select("session_id", "iter", "pos", "pattern", "origin", *r6("level", "w", "phi", "pct"))


def loop_session(phi, cfg, rounds, name):
    """A session in which every round is Spark jobs."""

    def query(spark, sf):
        p = prepared(spark, sf, part=0.2, max_len=3)
        loop = PreferenceLoop(SparkSpace(graded(p, phi), p.ds), cfg)
        loop.run(rounds, QualityRanker())
        return loop_rows(spark, loop, name)

    return query


def matrix_session(phi, cfg, docs=False, rounds=30, part=0.16):
    def query(spark, sf):
        p = doc_prepared(spark, sf) if docs else prepared(spark, sf, part=part)
        loop = PreferenceLoop(p.space(phi), cfg)
        loop.run(rounds, QualityRanker())
        return loop_rows(spark, loop, phi)

    return query


def scd_weights(spark, sf):
    """Non-zero weights of a fit over the fixed feedback's items: 1000 updates."""
    rows = pair_deltas(spark, sf).toPandas()  # sixty pairs at most
    n = rows.feature_id.max() + 1
    d = rows.pivot_table(index=["iter", "winner", "loser"], columns="feature_id", values="delta", fill_value=0.0).reindex(columns=range(n), fill_value=0.0).to_numpy()
    w = learn.scd_l1(d, seed="fit").weights
    return spark.createDataFrame([(int(i), round(float(w[i]), 6)) for i in w.nonzero()[0]], "feature_id int, w double")


def like_items(spark, sf):
    p = prepared(spark, sf, part=0.2, max_len=3)
    chosen, liked = liked_items(p.space("frequency"))
    return spark.createDataFrame([(int(i), round(float(liked), 6)) for i in chosen.nonzero()[0]], "item_id int, liked_share double")


def multiplicative_round1(spark, sf):
    ds, patterns = emb(spark, sf)
    return multiplicative.first_draw(patterns, ds.items.select("item_id", ((F.col("item_id") % 7 - 3) / 10).alias("lw")), 3)


def multiplicative_session(spark, sf):
    space = prepared(spark, sf, part=0.2, max_len=3).space("frequency")
    found = multiplicative.run(space, LikeRanker(space), SAMPLES)
    return spark.createDataFrame([(i, s.pattern, bool(v)) for i, (s, v) in enumerate(zip(found.samples, found.liked))], "sample int, pattern string, liked boolean")


def mmr_pick(spark, sf):
    import numpy as np

    space = prepared(spark, sf, part=0.2, max_len=3).space("frequency")
    pool = np.lexsort((space.pattern.astype(str), -space.sup))[:200]
    picks = poolrank.mmr(space.masks[pool], 1 - np.arange(len(pool)) / (len(pool) - 1), [0, 1], 0.3, 0.7, 5)
    return spark.createDataFrame([(i, space.pattern[pool[p]]) for i, p in enumerate(picks)], "pick int, pattern string")


def source_ranking(spark, sf):
    return poolrank.source_rank(sample.uniform(emb(spark, sf)[1], 100, 3)).select("pattern", "source_rank")


def poolrank_session(spark, sf):
    space = prepared(spark, sf, part=0.2, max_len=3).space("frequency")
    out = poolrank.run(space, QualityRanker(), poolrank.PoolConfig(), 30)
    return spark.createDataFrame([(i, s.pattern, s.pct) for i, (_, best) in enumerate(out) for s in best], "iter int, pattern string, pct double")


# --- measures -------------------------------------------------------------------------------------------


def top_five(patterns):
    return mine.top_k(patterns.where("len = 2"), "sup", 5)


def joint_entropy_fixed(spark, sf):
    ds, patterns = emb(spark, sf)
    return measures.joint_entropy(top_five(patterns), ds).select("k", *r6("entropy"))


def sampler_sessions(spark, sf):
    """Sessions without learning, uniform or by the hidden quality: five rounds each."""
    ds, patterns = emb(spark, sf)
    parts = []
    for phi in ("frequency", "chi2"):
        own = quality.with_quality(patterns, ds, phi)
        for method in ("uniform", "ideal"):
            rows = [(f"{method}/{phi}/k{k}/s{s}", f"{method}{s}", 5, k) for k in (5, 10) for s in range(3)]
            grid = spark.createDataFrame(rows, "session_id string, seed string, rounds int, k int")
            parts.append(sample.sessions(own, F.lit(1.0) if method == "uniform" else F.col("phi"), grid).withColumn("phi_name", F.lit(phi)))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return ds, patterns, out


def session_measures(spark, sf):
    """Average and best percentile, entropy and its share of every query."""
    ds, patterns, shown = sampler_sessions(spark, sf)
    shown = shown.persist()
    parts = []
    for phi in ("frequency", "chi2"):
        pct = quality.with_percentile(quality.with_quality(patterns, ds, phi).withColumn("phi", F.round("phi", 9)))
        parts.append(measures.query_quality(shown.where(F.col("phi_name") == phi), pct))
    good = parts[0].unionByName(parts[1])
    return good.join(measures.query_entropy(shown, patterns, ds), ["session_id", "iter"])


def session_quality(spark, sf):
    return session_measures(spark, sf).select("session_id", "iter", *r6("avg_quality", "max_quality", "entropy", "entropy_share"))


def session_series(spark, sf):
    kept = session_measures(spark, sf)
    names = ["avg_quality", "max_quality", "entropy_share"]
    return kept.select("session_id", "iter", F.explode(F.array(*[F.struct(F.lit(n).alias("measure"), F.col(n).alias("value")) for n in names])).alias("m")).select("session_id", "iter", "m.*")


def cumulative_regret(spark, sf):
    return measures.regret(session_series(spark, sf)).select("session_id", "measure", "iter", *r6("regret", "cumulative"))


def regret_grouping_sets(spark, sf):
    """Mean and deviation of summed regrets for every level of method, quality and size."""
    part = lambda i: F.element_at(F.split("session_id", "/"), i)
    rows = session_measures(spark, sf).select(part(1).alias("method"), part(2).alias("phi"), part(3).alias("k"), part(4).alias("seed"), "avg_quality", "max_quality", "entropy", "entropy_share")
    sums = [F.sum(1 - F.col(c)).alias(n) for c, n in (("avg_quality", "avg_regret"), ("max_quality", "max_regret"), ("entropy_share", "entropy_regret"))]
    regret = rows.groupBy("method", "phi", "k", "seed").agg(*sums, F.sum("entropy").alias("entropy_bits"))
    names = [f"{m}_regret{sd}" for m in ("avg", "max", "entropy") for sd in ("", "_sd")]
    return experiments.marginals(regret, ["method", "phi", "k"]).select("factor", "level", "sessions", *r6(*names, "entropy_bits"))


def jaccard_top(spark, sf):
    ds, patterns = emb(spark, sf)
    return measures.jaccard_spread(mine.top_k(patterns, "sup", 10), ds.masks).select(*r6("mean", "least", "most"))


def pca_gram(spark, sf):
    return measures.item_gram(emb(spark, sf)[1])


def agreement(spark, sf):
    ds, patterns = weighted(spark, sf)
    return measures.agreement(patterns.withColumn("w", F.round("w", 9)), "w", "sup").select(*r6("pearson", "spearman"))


def sampling_accuracy(spark, sf):
    """Total variation between 200 draws of each of two seeds and the weights' shares."""
    ds, patterns = weighted(spark, sf)
    patterns = patterns.persist()
    return measures.total_variation(sample.exact(patterns, F.col("w"), 400, 11, replace=True), patterns).select(*r6("total_variation"))


def principal_axes(spark, sf):
    """Variance of the patterns along the first two axes and how much of all it is."""
    ds, patterns = emb(spark, sf)
    placed = measures.item_pca(patterns, ds.n_items, 2, keep=1.0)
    return placed.agg(*[F.round(F.var_pop(f"pc{a}"), 6).alias(f"variance_{a}") for a in (1, 2)], F.round(F.abs(F.corr("pc1", "pc2")), 6).alias("correlation"), *[F.round(F.abs(F.avg(f"pc{a}")), 6).alias(f"mean_{a}") for a in (1, 2)])


def lazy_cell(spark, sf):
    from prefpat.plans.lazy import enumerate_lazy

    ds = dataset(spark, sf, "emb_sign")
    found = enumerate_lazy(ds, share(ds.n, 0.2), xorcells.draw_py(4, ds.n_items, range(1), 7)[0])
    return found.select("pattern", "sup")


# --- workloads --------------------------------------------------------------------------------------------


def characteristic(spark, sf):
    loop = experiments.characteristic(doc_prepared(spark, sf).space("surprisingness"))
    return loop_rows(spark, loop, "characteristic")


def ten_cells(spark, sf):
    p = prepared(spark, sf)
    loop = experiments.characteristic(p.space("surprisingness"))
    return spark.createDataFrame(experiments.ten_cells(loop))


def scatter(spark, sf):
    return spark.createDataFrame(experiments.scatter(prepared(spark, sf, part=0.2), "surprisingness"), "rounds int, pearson double, spearman double")


def scatter_points(spark, sf):
    points = experiments.scatter_points(prepared(spark, sf, part=0.2), "surprisingness")
    return spark.createDataFrame(points, "rounds int, pattern string, learned double, hidden double")


def calibrated(spark, sf, names, target):
    """Encodings with supports that give about ``target`` patterns each."""
    out = {}
    for name in names:
        ds = dataset(spark, sf, name, least_support(spark, sf, name, 0.1)).persist()
        out[name] = experiments.prepare(ds, target=target)
    return out


def dataset_table(spark, sf):
    """All ten encodings, near the published number of patterns."""
    return experiments.dataset_table(calibrated(spark, sf, ENCODINGS, 140_000))


def items_scaling(spark, sf):
    return experiments.items_scaling(spark, calibrated(spark, sf, ["cust_brands", "user_slots", "emb_sign", "page_words", "doc_words"], GRID_PATTERNS))


def parameter_grid(spark, sf):
    """Every level of every factor: two encodings, three qualities, two seeds, 30 rounds."""
    p = calibrated(spark, sf, GRID_DATASETS, GRID_PATTERNS)
    return experiments.one_at_a_time(experiments.session_regret(experiments.run_grid(spark, experiments.factor_grid(GRID_DATASETS), p)))


def method_comparison(spark, sf):
    """All methods: two encodings, three qualities, two seeds, 30 rounds."""
    return experiments.compare(spark, calibrated(spark, sf, GRID_DATASETS, GRID_PATTERNS), seeds=range(2))


def match_unseen(spark, sf):
    p = doc_prepared(spark, sf)
    from prefpat.operators.encode import binarise
    from prefpat.sources.encodings import tokens

    unseen = binarise(table(spark, sf, "benchmark"), F.col("item_id"), tokens(F.col("text")))
    return experiments.match_unseen(p.patterns.where("len >= 2"), p.ds, unseen)


def pca_map(spark, sf):
    p = prepared(spark, sf)
    return experiments.pca_map(p, experiments.characteristic(p.space("surprisingness")))


# --- streams and joins ------------------------------------------------------------------------------------------


def stream_user_slots(spark, sf):
    events = streams.event_stream(spark, sf)
    slots = streams.slot_items(events).groupBy("user_id", "item").agg(F.count(F.lit(1)).alias("events"))
    return streams.run_to_end(slots, "stream_user_slots", stream_folder(spark), "complete")


def stream_feedback(spark, sf):
    """Rankings of the fixed feedback as files, one round each, learned as they come."""
    folder = stream_folder(spark)
    rows = feedback(spark, sf).join(emb(spark, sf)[1].select("pattern", "items"), "pattern").select("session_id", "iter", "pos", "level", "items")
    rows.repartition("iter").write.mode("overwrite").parquet(folder)
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 2).parquet(folder)
    learned = streams.learn_from_feedback(stream, dataset(spark, sf, "emb_sign").n_items, updates=200)
    return streams.run_to_end(learned, "stream_feedback", stream_folder(spark))


def stream_folder(spark) -> str:
    """A new folder under the shared checkpoint folder."""
    return f"{shared_folder(spark)}/prefpat-stream-{uuid.uuid4().hex}"


def session_windows(spark, sf):
    """Users' events in sessions that a gap of a day ends."""
    events = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return streams.session_transactions(events).groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.max("events").alias("longest"), F.sum("events").cast("long").alias("events"))


def json_items(spark, sf):
    """Items from the JSON of events: the value of k by tens."""
    k = F.from_json("props", "k int")["k"]
    return table(spark, sf, "events").select("user_id", F.concat(F.lit("k"), F.floor(k / 10).cast("string")).alias("item")).groupBy("item").agg(F.count_distinct("user_id").alias("support"), F.count(F.lit(1)).alias("events"))


def result_sets(spark, sf):
    """The hundred best by class: in both, and only in one or the other."""
    _, patterns = emb(spark, sf)
    neg = patterns.withColumn("sup_neg", F.col("sup") - F.col("sup_pos"))
    one, two = (mine.top_k(neg, c, 100).select("pattern") for c in ("sup_pos", "sup_neg"))
    tagged = lambda df, name: df.select("pattern", F.lit(name).alias("kind"))
    return tagged(one.intersect(two), "both").unionByName(tagged(one.exceptAll(two), "positive")).unionByName(tagged(two.exceptAll(one), "negative"))


def pattern_rollup(spark, sf):
    """Patterns by length and tens of support, with subtotals."""
    _, patterns = emb(spark, sf)
    return patterns.withColumn("tens", F.floor(F.col("sup") / 10)).rollup("len", "tens").agg(F.count(F.lit(1)).alias("n"), F.max("sup").alias("most")).select("len", "tens", "n", "most")


def pattern_cube(spark, sf):
    """Patterns by length and the class that they are more frequent in, in all groupings."""
    _, patterns = emb(spark, sf)
    return patterns.withColumn("leans", F.col("sup_pos") * 2 > F.col("sup")).cube("len", "leans").agg(F.count(F.lit(1)).alias("n"), F.sum("sup").alias("covered"))


def distinct_shown(spark, sf):
    """Different patterns shown, exactly, and whether the sketch comes within 5 %."""
    _, _, shown = sampler_sessions(spark, sf)
    found = shown.agg(F.count_distinct("pattern").alias("n"), F.approx_count_distinct("pattern", 0.01).alias("a"))
    return found.select("n", (F.abs(F.col("a") - F.col("n")) <= 0.05 * F.col("n")).alias("close"))


def weight_map(spark, sf):
    """Weights by item name as a map, and the patterns' scores looked up in it."""
    ds, patterns = emb(spark, sf)
    w = fixed_weights(ds)
    rows = spark.createDataFrame([(i, float(x)) for i, x in enumerate(w.items)], "item_id int, w double")
    known = ds.items.join(F.broadcast(rows), "item_id").agg(F.map_from_entries(F.collect_list(F.struct("item_id", "w"))).alias("weights")).withColumn("_one", F.lit(1))
    scored = patterns.withColumn("_one", F.lit(1)).join(F.broadcast(known), "_one")
    return scored.select("pattern", F.round(F.aggregate("items", F.lit(0.0), lambda a, i: a + F.element_at("weights", i)), 6).alias("score"))


def asof_weights(spark, sf):
    """Each purchase with the user's last view before it."""
    events = table(spark, sf, "events").select("event_id", "user_id", "ts", "event_type")
    bought = events.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    viewed = events.where("event_type = 'view'").groupBy("user_id", F.col("ts").alias("seen_at")).agg(F.max("event_id").alias("seen_id"))
    return relational.as_of(bought, viewed, ["user_id"], "ts", "seen_at").select("event_id", "user_id", "seen_id")


def range_bins(spark, sf):
    edges = spark.createDataFrame([("low", 0.0, 10.0), ("middle", 10.0, 25.0), ("high", 25.0, 1000.0)], "bin string, lo double, hi double")
    return relational.range_bins(table(spark, sf, "lineitem").select("l_quantity"), F.col("l_quantity"), edges, 10.0).groupBy("bin").agg(F.count(F.lit(1)).alias("n"))


def unseen_patterns(spark, sf):
    _, patterns = emb(spark, sf)
    return relational.unseen(patterns, feedback(spark, sf)).select("pattern")


QUERIES = {f"enc_{n}": encoding(n) for n in ENCODINGS} | {
    "dataset_stats": dataset_stats, "frequent_emb_len3": frequent(), "frequent_levelwise": frequent("levelwise"), "frequent_partitioned": frequent("partitioned"),
    "frequent_cust_brands_len3": frequent(name="cust_brands", part=0.4), "support_by_class": support_by_class, "closed_patterns": closed_patterns, "topk_by_support": topk_by_support,
    "association_rules": association_rules, "calibrated_min_sup": calibrated_min_sup, "constrained_patterns": constrained_patterns, "lazy_cell": lazy_cell,
    "q_frequency": of_quality("frequency"), "q_surprisingness": of_quality("surprisingness"), "q_chi2": of_quality("chi2"), "q_chi2_literal": q_chi2_literal,
    "percentile_rank": percentile_rank, "quality_boxplot": quality_boxplot, "feat_ilf": feat_ilf, "feat_transactions": feat_transactions,
    "score_fixed_weights": score_fixed_weights, "logistic_quality": logistic_quality, "pairs_from_rankings": pairs_from_rankings, "pair_deltas": pair_deltas,
    "discordant_pairs": discordant_pairs, "user_effort": user_effort, "scd_objective_drop": scd_objective_drop, "xor_draws": xor_draws, "udtf_xor_draws": udtf_xor_draws,
    "xor_cell_members": xor_cell_members, "xor_cell_sizes": xor_cell_sizes, "nested_cells": nested_cells, "cell_top1": cell_top(1), "cell_top3": cell_top(3), "cell_random": cell_random,
    "within_cell_prob": within_cell_prob, "xor_count_estimate": xor_count_estimate, "uniform_pool": uniform_pool, "ideal_sampler": ideal_sampler,
    "loop_round1": loop_session("frequency", LoopConfig(), 1, "round1"), "loop_spark_session": loop_session("frequency", LoopConfig(), 3, "emb"),
    "loop_random_session": loop_session("chi2", experiments.CHARACTERISTIC, 3, "random"), "scd_weights": scd_weights, "sample_batch": sample_batch, "predicted_ranking": predicted_ranking, "loop_emb_session": matrix_session("surprisingness", LoopConfig()),
    "loop_doc_session": matrix_session("chi2", LoopConfig(), docs=True), "loop_retention": matrix_session("frequency", LoopConfig(l=3, features="ILF"), part=0.2),
    "loop_whole_session": matrix_session("frequency", LoopConfig(), part=0.2), "loop_chi2_session": matrix_session("chi2", LoopConfig(k=10, A=0.1, cell=("top", 3), seed=3), part=0.2), "like_items": like_items,
    "multiplicative_round1": multiplicative_round1, "multiplicative_session": multiplicative_session, "mmr_pick": mmr_pick, "source_ranking": source_ranking, "poolrank_session": poolrank_session,
    "joint_entropy_fixed": joint_entropy_fixed, "session_quality": session_quality, "cumulative_regret": cumulative_regret, "regret_grouping_sets": regret_grouping_sets, "jaccard_top": jaccard_top,
    "pca_gram": pca_gram, "agreement": agreement, "sampling_accuracy": sampling_accuracy, "characteristic": characteristic, "ten_cells": ten_cells, "scatter": scatter, "scatter_points": scatter_points, "principal_axes": principal_axes, "dataset_table": dataset_table, "items_scaling": items_scaling,
    "frequent_fpgrowth": frequent("fpgrowth"), "session_windows": session_windows, "json_items": json_items, "result_sets": result_sets, "pattern_rollup": pattern_rollup,
    "pattern_cube": pattern_cube, "distinct_shown": distinct_shown, "weight_map": weight_map,
    "parameter_grid": parameter_grid, "method_comparison": method_comparison, "match_unseen": match_unseen, "pca_map": pca_map,
    "stream_user_slots": stream_user_slots, "stream_feedback": stream_feedback, "asof_weights": asof_weights, "range_bins": range_bins, "unseen_patterns": unseen_patterns,
}


def entry(spark, sf_dir):
    """Two rounds of the loop on the smallest tables, driving Spark jobs."""
    return loop_session("surprisingness", LoopConfig(), 2, "entry")(spark, sf_dir)
