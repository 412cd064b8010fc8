"""Streams: transactions from events, windows, and the feedback loop with state."""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from prefpat.plans.learn import scd_l1

#: A run over what is there now is stopped after this long.
RUN_SECONDS = 600


def event_stream(spark: SparkSession, folder: str, files: str = "events*.parquet", files_at_a_time: int = 1) -> DataFrame:
    """The event files of a folder as a stream; ``ts`` becomes a timestamp with zone,
    which watermarks need. A stream reads folders, so files are told apart by name."""
    schema = spark.read.option("pathGlobFilter", files).parquet(folder).schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_at_a_time).option("pathGlobFilter", files).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def slot_items(events: DataFrame) -> DataFrame:
    """``(user_id, item)`` rows as in the batch encoding."""
    return events.select("user_id", "ts", F.concat_ws("/", "event_type", F.floor(F.dayofmonth("ts") / 4).cast("string")).alias("item"))


def windowed_transactions(events: DataFrame, size: str = "4 days", slide: str | None = None, late: str = "1 day") -> DataFrame:
    """User transactions of tumbling or sliding windows; later events are dropped."""
    window = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", late).groupBy(window.alias("w"), "user_id").agg(F.sort_array(F.collect_set("event_type")).alias("items"), F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "user_id", "items", "events")


def session_transactions(events: DataFrame, gap: str = "1 day", late: str = "1 day") -> DataFrame:
    """User transactions of sessions, which a gap ends."""
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.sort_array(F.collect_set("event_type")).alias("items"), F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "user_id", "items", "events")


def run_to_end(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """All that is there now, into a table in memory."""
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    if not query.awaitTermination(RUN_SECONDS):
        query.stop()
        raise TimeoutError(f"{name} did not end in {RUN_SECONDS} seconds")
    return stream.sparkSession.table(name)


WEIGHTS_SCHEMA = "session_id string, iter int, feature_id int, w double"


def learn_from_feedback(rankings: DataFrame, n_items: int, lam: float = 1e-3, updates: int = 1000, keep_rounds: int = 30) -> DataFrame:
    """A stream of ranked patterns to a stream of weights.

    Input rows are ``(session_id, iter, pos, level, items)``. The state of a session
    holds the rankings of its last ``keep_rounds`` rounds, which bounds it. Rows of a
    round may come in several batches: the round is then learned again, with the pairs
    between them. Every batch emits the weights after each round that it touches. There
    is no timeout: with one, a run over what is there now would wait for it and never end.
    """

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        held: dict[int, dict[int, tuple[float, list[int]]]] = pickle.loads(state.get[0]) if state.exists else {}
        rows, touched, out = pd.concat(list(frames)), set(), []
        for r in rows.itertuples(index=False):
            held.setdefault(int(r.iter), {})[int(r.pos)] = (float(r.level), list(map(int, r.items)))
            touched.add(int(r.iter))
        held = {i: held[i] for i in sorted(held)[-keep_rounds:]}
        deltas = np.zeros((0, n_items))
        for i, ranking in held.items():
            deltas = np.concatenate([deltas, ranking_deltas([ranking[p] for p in sorted(ranking)], n_items)])
            if i >= min(touched):
                w = scd_l1(deltas, lam, updates, f"{key[0]}/{i}").weights
                out += [(key[0], i, int(f), float(w[f])) for f in np.flatnonzero(w)]
        state.update((pickle.dumps(held),))
        yield pd.DataFrame(out, columns=["session_id", "iter", "feature_id", "w"])

    return rankings.groupBy("session_id").applyInPandasWithState(step, WEIGHTS_SCHEMA, "rankings binary", "append", GroupStateTimeout.NoTimeout)


def ranking_deltas(ranking: list[tuple[float, list[int]]], n_items: int) -> np.ndarray:
    """Difference vectors of a ranking's pairs, best first; ties give none."""
    vectors = np.zeros((len(ranking), n_items))
    for r, (_, items) in enumerate(ranking):
        vectors[r, items] = 1
    pairs = [(a, b) for a in range(len(ranking)) for b in range(a + 1, len(ranking)) if ranking[a][0] != ranking[b][0]]
    return np.array([vectors[a] - vectors[b] for a, b in pairs]).reshape(-1, n_items)


def loop_on_batches(triggers: DataFrame, loop, ranker, out: str, checkpoint: str):
    """One micro-batch is one round: the shown patterns are appended to a table.

    Batches are numbered, so a batch that is given again after a failure adds no
    second round.
    """
    from prefpat.plans.session import ROW_SCHEMA

    spark = triggers.sparkSession

    def round_(_: DataFrame, number: int) -> None:
        if len(loop.rounds) <= number:
            loop.step(ranker)
            rows = [r for r in loop.rows("stream") if r["iter"] == len(loop.rounds)]
            spark.createDataFrame([tuple(r.values()) for r in rows], ROW_SCHEMA).write.mode("append").parquet(out)

    return triggers.writeStream.foreachBatch(round_).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
