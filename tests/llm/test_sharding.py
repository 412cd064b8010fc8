import zlib

import numpy as np
import pytest

from prefpat.llm import sharding


def jump(key: int, shards: int) -> int:
    """One key at a time, with whole numbers."""
    shard, ahead = -1, 0
    while ahead < shards:
        shard = ahead
        key = (key * 2862933555777941757 + 1) % 2**64
        ahead = int((shard + 1) * (2.0**31 / ((key >> 33) + 1.0)))
    return shard


def shards_of(spark, rows, shards, schema="doc_id long, text string", **more):
    return sharding.assign_shards(spark.createDataFrame(rows, schema), "doc_id", "text", shards, **more).collect()


def test_keys_jump_as_defined():
    keys = np.random.default_rng(3).integers(0, 2**64, 500, dtype=np.uint64)
    for shards in (1, 2, 7, 24):
        assert sharding.jump_shards(keys, shards).tolist() == [jump(int(k), shards) for k in keys]
    with pytest.raises(ValueError):
        sharding.jump_shards(keys, 0)


def test_one_more_shard_takes_only_into_itself():
    keys = np.random.default_rng(4).integers(0, 2**64, 40_000, dtype=np.uint64)
    for shards in (1, 5, 24):
        old, new = sharding.jump_shards(keys, shards), sharding.jump_shards(keys, shards + 1)
        moved = old != new
        assert (new[moved] == shards).all() and abs(moved.mean() - 1 / (shards + 1)) < 0.01
        assert np.bincount(old, minlength=shards).min() > 0.9 * len(keys) / shards


def test_slots_sizes_and_grown_shards(spark):
    rows = [(i, "ä" * (i % 7)) for i in range(300)]
    got = shards_of(spark, rows, 5)
    grown = {r.doc_id: r.shard for r in shards_of(spark, rows, 6)}
    for shard in range(5):
        slots = sorted(r.slot for r in got if r.shard == shard)
        assert slots == list(range(len(slots))) and slots
    for r in got:
        text = dict(rows)[r.doc_id].encode()
        assert (r.size, r.text_crc32, r.law) == (len(text) + 8, zlib.crc32(text), "key")
        assert r.grown_shard == grown[r.doc_id] and r.grown_shard in (r.shard, 5)


def test_odd_rows(spark):
    rows = [(None, None, 1), (None, "x", 2), (7, "", 3), (7, "", 4), (7, "y" * 300_000, 5), (8, None, 6)]
    got = shards_of(spark, rows, 3, "doc_id long, text string, shard int")
    assert len(got) == 6 and len({r.shard for r in got if r.doc_id == 7}) == 1 and len({r.shard for r in got if r.doc_id is None}) == 1
    assert sorted(r.size for r in got) == [8, 8, 8, 8, 9, 300_008]
    for shard in range(3):
        slots = sorted(r.slot for r in got if r.shard == shard)
        assert slots == list(range(len(slots)))
    assert shards_of(spark, [], 3) == []


def test_a_key_with_a_third_of_all_rows(spark):
    got = shards_of(spark, [(0 if i % 3 == 0 else i, str(i)) for i in range(900)], 4, buckets=8)
    assert len({r.shard for r in got if r.doc_id == 0}) == 1
    for shard in range(4):
        slots = sorted(r.slot for r in got if r.shard == shard)
        assert slots == list(range(len(slots)))
