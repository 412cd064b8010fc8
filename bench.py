"""Headline timings: one JSON line.

Rounds of the loop are timed after the patterns are mined and the space is built, as
a session sees them; the other entries are whole queries.
"""

import json
import os
import sys
import time
from pathlib import Path

sys.path.insert(0, str(Path(__file__).parent))

from pyspark.sql import SparkSession

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
WHOLE = ["frequent_emb_len3", "percentile_rank", "xor_cell_members", "joint_entropy_fixed", "enc_order_lines"]


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from prefpat import queries as q
    from prefpat.functions import quality
    from prefpat.operators import mine
    from prefpat.plans import experiments
    from prefpat.plans.session import LoopConfig, PreferenceLoop
    from prefpat.plans.spaces import SparkSpace
    from prefpat.plans.users import QualityRanker
    from prefpat.sources.encodings import dataset

    times: dict[str, float] = {}

    def timed(name, call, per=1):
        began = time.perf_counter()
        out = call()
        times[name] = round((time.perf_counter() - began) / per, 4)
        return out

    q.QUERIES["enc_emb_sign"](spark, SF_DIR).count()  # the session's first job
    for name in WHOLE:
        timed(name, lambda: q.QUERIES[name](spark, SF_DIR).collect())  # noqa: B023
    ds = dataset(spark, SF_DIR, "emb_sign").persist()
    theta, count = timed("calibrate_min_sup", lambda: mine.calibrate_min_sup(ds, 140_000))
    prepared = timed("mine_140k_patterns", lambda: experiments.prepare(ds, theta))
    prepared.patterns.count()
    space = timed("build_matrix_space", lambda: prepared.space("surprisingness"))
    loop = PreferenceLoop(space, experiments.CHARACTERISTIC)
    timed("round_characteristic", lambda: loop.run(30, QualityRanker()), 30)
    loop = PreferenceLoop(space, LoopConfig.recommended())
    timed("round_recommended", lambda: loop.run(30, QualityRanker()), 30)
    graded = quality.with_percentile(quality.with_quality(prepared.patterns, ds, "surprisingness"))
    driven = PreferenceLoop(SparkSpace(graded, ds), experiments.CHARACTERISTIC)
    driven.step(QualityRanker())  # fills the cache
    timed("round_on_spark", lambda: driven.run(5, QualityRanker()), 5)
    rows = experiments.grid(["emb_sign"], ["surprisingness"], seeds=range(16), rounds=10)
    timed("grid_session_of_10_rounds", lambda: experiments.run_grid(spark, rows, {"emb_sign": prepared}).count(), 16)
    print(json.dumps({"metric": "seconds_per_round", "value": times["round_recommended"], "unit": "sec", "queries": times, "sf": SF_DIR.rsplit("sf", 1)[-1], "patterns": count, "min_sup": theta}))
    spark.stop()


if __name__ == "__main__":
    main()
