import tempfile

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from prefpat import queries as q
from prefpat.operators import mine, relational
from prefpat.operators.encode import encode
from prefpat.plans import learn, sqlsurface
from prefpat.plans.session import LoopConfig, PreferenceLoop
from prefpat.plans.users import QualityRanker
from prefpat.sources import files
from prefpat.streaming import streams

SF = "/root/testdata/sf0.001"


def test_windows_equal_batch(spark):
    stream = streams.windowed_transactions(streams.event_stream(spark, SF))
    got = streams.run_to_end(stream, "windowed", tempfile.mkdtemp(), "append")
    events = spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))
    batch = events.groupBy(F.window("ts", "4 days").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("events")).select(F.col("w.start").alias("start"), "user_id", "events")
    late = got.join(batch, ["start", "user_id", "events"], "left_anti").count()
    assert got.count() > 50 and late == 0  # windows that the watermark has closed are whole


def test_feedback_stream_ends_and_learns(spark):
    rows = q.stream_feedback(spark, SF).toPandas()
    assert set(rows.session_id) == {"s"} and set(rows.iter) == set(range(6)) and (rows.w != 0).all()


def test_a_ranking_split_over_batches_is_learned_whole(spark):
    schema = "session_id string, iter int, pos int, level double, items array<int>"
    rows = [("a", i, p, float(-p), [(i * 5 + p * 3 + j) % 12 for j in range(3)]) for i in range(3) for p in range(4)]
    folder = tempfile.mkdtemp()
    for at in range(0, len(rows), 3):  # a file holds parts of two rankings
        spark.createDataFrame(rows[at : at + 3], schema).coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)
    got = streams.run_to_end(streams.learn_from_feedback(stream, 12, updates=100), "split_feedback", tempfile.mkdtemp()).toPandas()
    deltas = np.concatenate([streams.ranking_deltas([(r[3], r[4]) for r in rows if r[1] == i], 12) for i in range(3)])
    want = learn.scd_l1(deltas, 1e-3, 100, "a/2").weights
    last = got[got.iter == 2].iloc[-int((want != 0).sum()) :]
    assert {int(f): w for f, w in zip(last.feature_id, last.w)} == {int(f): want[f] for f in want.nonzero()[0]}


def test_loop_on_batches(spark):
    folder, out = tempfile.mkdtemp(), tempfile.mkdtemp()
    spark.range(1).write.mode("overwrite").parquet(folder)
    space = q.prepared(spark, SF, part=0.2, max_len=2).space("frequency")
    triggers = spark.readStream.schema("id long").parquet(folder)
    query = streams.loop_on_batches(triggers, PreferenceLoop(space, LoopConfig()), QualityRanker(), f"{out}/rounds", tempfile.mkdtemp())
    assert query.awaitTermination(120)
    assert spark.read.parquet(f"{out}/rounds").count() == 5


def test_as_of(spark):
    events = spark.createDataFrame([(1, "u", 5), (2, "u", 10), (3, "v", 1)], "id int, k string, t int")
    states = spark.createDataFrame([("u", 5, "a"), ("u", 7, "b"), ("v", 2, "c")], "k string, at int, s string")
    got = {r.id: (r.s, r["at"]) for r in relational.as_of(events, states, ["k"], "t", "at").collect()}
    assert got == {1: ("a", 5), 2: ("b", 7), 3: (None, None)}


def test_range_and_retained(spark):
    edges = spark.createDataFrame([("a", 0.0, 1.5), ("b", 1.5, 9.0)], "bin string, lo double, hi double")
    df = spark.createDataFrame([(0.0,), (1.5,), (8.9,), (9.0,)], "v double")
    assert sorted((r.v, r.bin) for r in relational.range_bins(df, F.col("v"), edges, 1.0).collect()) == [(0.0, "a"), (1.5, "b"), (8.9, "b")]
    ordered = spark.createDataFrame([("s", i, p, f"{i}{p}") for i in (1, 2) for p in (1, 2, 3)], "session_id string, iter int, pos int, pattern string")
    assert sorted(r.pattern for r in relational.retained(ordered, 2).collect()) == ["21", "22"]


def test_sql_surface(spark):
    sqlsurface.register(spark)
    pd_rows = pd.DataFrame([(p, f, v) for p in range(20) for f, v in ((0, 1.0), (1, (-1.0) ** p))], columns=["pair_id", "feature_id", "delta"])
    spark.createDataFrame(pd_rows).createOrReplaceTempView("deltas_of_pairs")
    fitted = {r.feature_id: r.w for r in spark.sql("SELECT * FROM scd_fit(TABLE(SELECT * FROM deltas_of_pairs) WITH SINGLE PARTITION, 0.01D, 500, 'x')").collect()}
    assert fitted[0] > 1 and 1 not in fitted
    assert spark.sql("SELECT entropy_bits(x) AS e FROM VALUES (1), (1), (2), (2) AS t(x)").first().e == pytest.approx(1)
    assert spark.sql("SELECT floored_logistic(0.0D, 0.1D) AS w").first().w == pytest.approx(0.55)
    assert spark.sql("SELECT weighted_draw(p, w, u) AS d FROM VALUES ('a', 1.0D, 0.5D), ('b', 9.0D, 0.5D) AS t(p, w, u)").first().d == "b"


def test_entry_and_contract(spark):
    import __spark_entry__ as contract

    assert contract.entry(spark).count() == 10
    assert set(contract.oracle_sql()) <= set(contract.queries())


def test_numbers_and_running_counts(spark):
    values = [5, 1, 9, 3, 7, 20, 11, 2]
    df = spark.createDataFrame([(v,) for v in values], "v long").repartition(5)
    assert {r.v: r.row for r in relational.numbered_rows(df, "v").collect()} == {v: i for i, v in enumerate(sorted(values))}
    counts = spark.createDataFrame([(float(v), v) for v in values], "x double, n long")
    got = {r.n: (r["_before"], r["_all"]) for r in relational.running_counts(counts, "x", "n").collect()}
    assert got == {v: (sum(x for x in values if x < v), sum(values)) for v in values}


def test_files_in_and_out(spark, tmp_path):
    (tmp_path / "lines.txt").write_text("a b a\n\nb c\nb c\n")
    long = files.read_item_lines(spark, str(tmp_path / "lines.txt"))
    ds = encode(long)
    assert (ds.n, ds.n_items) == (4, 3)
    named = long.select("tid", "item", F.lit(1).alias("label"))
    for fmt in ("parquet", "csv", "json"):
        writer = named.write.mode("overwrite")
        (writer.option("header", True).csv if fmt == "csv" else getattr(writer, fmt))(str(tmp_path / fmt))
        back = files.read_long(spark, str(tmp_path / fmt), fmt)
        assert sorted(map(tuple, back.collect()), key=str) == sorted(map(tuple, named.collect()), key=str)
    patterns = mine.frequent(ds, 1)
    for name in ("one", "two"):
        files.write_patterns(patterns, str(tmp_path / "patterns"), name)
    kept = spark.read.parquet(str(tmp_path / "patterns")).where("dataset = 'one' and len = 2")
    assert kept.count() == patterns.where("len = 2").count() and "PartitionFilters: [isnotnull(dataset" in kept._jdf.queryExecution().toString()
    files.append_rows(long, str(tmp_path / "log"))
    files.append_rows(long, str(tmp_path / "log"))
    assert spark.read.parquet(str(tmp_path / "log")).count() == 2 * long.count()
    files.write_table(patterns.select("pattern", "sup"), str(tmp_path / "table"))
    assert spark.read.csv(str(tmp_path / "table"), header=True).count() == patterns.count()


def test_session_windows_in_a_stream(spark):
    stream = streams.session_transactions(streams.event_stream(spark, SF))
    got = streams.run_to_end(stream, "sessions", tempfile.mkdtemp(), "append").select("start", "user_id", "events")
    batch = streams.session_transactions(spark.read.parquet(f"{SF}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp")))
    assert got.count() > 20 and got.join(batch, ["start", "user_id", "events"], "left_anti").count() == 0
