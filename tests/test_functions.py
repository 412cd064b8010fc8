import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from prefpat.functions import bits, model, quality, rng
from prefpat.operators.encode import EncodedDataset


def test_portable_numbers_agree(spark):
    df = spark.range(50).select("id", rng.u32(F.lit("s"), F.col("id")).alias("u"), rng.u01(F.lit("s"), F.col("id")).alias("v"))
    for r in df.collect():
        assert r.u == rng.u32_py("s", r.id) and r.v == rng.u01_py("s", r.id) and 0 < r.v <= 1


def test_masks(spark):
    df = spark.createDataFrame([([0, 63, 64, 100], [63, 100]), ([5], [6]), ([], [])], "a array<int>, b array<int>")
    a = [c.alias(f"a{i}") for i, c in enumerate(bits.pack_array(F.col("a"), 2))]
    b = [c.alias(f"b{i}") for i, c in enumerate(bits.pack_array(F.col("b"), 2))]
    packed = df.select(*a, *b)
    own = lambda p: [F.col(f"{p}0"), F.col(f"{p}1")]
    rows = packed.select(bits.contains(own("a"), own("b")).alias("inside"), bits.size(own("a")).alias("n"), bits.overlap(own("a"), own("b")).alias("both"), bits.parity(own("a"), own("b")).alias("p")).collect()
    assert [tuple(r) for r in rows] == [(True, 4, 2, 0), (False, 1, 0, 0), (True, 0, 0, 0)]


def test_zero_weights_and_tilt():
    assert model.zero_weight(0.1) == pytest.approx(0.55) and model.zero_weight(0.5) == pytest.approx(0.75)
    assert model.tilt(0.5) == 2
    with pytest.raises(ValueError):
        model.tilt(0)


def test_order_does_not_depend_on_the_floor():
    score = np.random.default_rng(1).normal(0, 3, 200)
    orders = [np.argsort(-model.logistic(score, a)).tolist() for a in (0.01, 0.1, 0.5)]
    assert orders[0] == orders[1] == orders[2]
    assert (model.logistic(np.array([-1e9, 1e9]), 0.1) == [pytest.approx(0.1), pytest.approx(1.0)]).all()


def test_chi2_worked_value(spark):
    df = spark.createDataFrame([(30, 25), (100, 60), (0, 0)], "sup long, sup_pos long")
    got = [r.x for r in df.select(quality.chi2(100, 60).alias("x")).collect()]
    assert got[0] == pytest.approx(9.7222, abs=1e-4) and got[1] == got[2] == 0


def test_surprisingness_of_one_item_is_zero(spark):
    items = spark.createDataFrame([(0, "a", 40), (1, "b", 50)], "item_id int, item string, support long")
    ds = EncodedDataset("x", None, items, 100, 0, 0, 2, 2)
    patterns = spark.createDataFrame([("0", [0], 40), ("0,1", [0, 1], 30), ("1,0", [0, 1], 10)], "pattern string, items array<int>, sup long")
    got = {r.pattern: r.surprisingness for r in quality.with_surprisingness(patterns, ds).collect()}
    assert got["0"] == pytest.approx(0) and got["0,1"] == pytest.approx(0.1) and got["1,0"] == 0


@pytest.mark.parametrize("kind", ["cume_dist", "percent_rank"])
def test_percentiles(spark, kind):
    values = [1.0, 2.0, 2.0, 5.0, 7.0]
    df = spark.createDataFrame([(float(v),) for v in values], "phi double")
    got = sorted(r.pct for r in quality.with_percentile(df, "phi", kind).collect())
    want = [0.2, 0.6, 0.6, 0.8, 1.0] if kind == "cume_dist" else [0, 0.25, 0.25, 0.75, 1.0]
    assert got == pytest.approx(want) and math.isclose(max(got), 1)
