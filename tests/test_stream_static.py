"""The join of a stream of words with static ones, against all pairs."""

from __future__ import annotations

import numpy as np
import pytest

from proxjoin.functions.families import BitSampling
from proxjoin.functions.metrics import Thresholds
from proxjoin.streaming import joins

AT = Thresholds("hamming", 6, 12)


def words(n=90):
    rng = np.random.default_rng(13)
    w = rng.integers(-(1 << 62), (1 << 62) - 1, n)
    for k in range(40, 80):
        w[k] = w[k - 40] ^ sum(1 << int(b) for b in rng.choice(60, rng.integers(0, 9), replace=False))
    w[80:] = w[0]
    return [int(v) for v in w]


@pytest.mark.parametrize("static_chunk", [16, 1000])
def test_near_pairs_come_once(spark, tmp_path, monkeypatch, static_chunk):
    monkeypatch.setattr(joins, "STATIC", static_chunk)
    w = words()
    come, here = [(3 * k, v) for k, v in enumerate(w)], [(2 * k, v) for k, v in enumerate(w)]
    odd = [(1001, None), (None, w[1])]
    spark.createDataFrame(come + odd, "id long, feat long").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("id long, feat long").parquet(f"{tmp_path}/in")
    found = joins.drained(joins.stream_static_join(stream, spark.createDataFrame(here + odd, "id long, feat long"), AT, BitSampling(), 400, 12, 3))
    away = lambda a, b: ((a ^ b) & (1 << 64) - 1).bit_count()
    want = [(a, b, float(away(v, u))) for a, v in come for b, u in here if a != b and away(v, u) <= 6]
    assert sorted(map(tuple, found.collect())) == sorted(want) and len(want) > 150
    none = joins.drained(joins.stream_static_join(stream, spark.createDataFrame([], "id long, feat long"), AT, BitSampling(), 4, 12, 3))
    assert none.count() == 0


def test_only_pairs_that_share_a_key_are_found(spark, tmp_path):
    rows = [(k, v) for k, v in enumerate(words())]
    spark.createDataFrame(rows, "id long, feat long").write.parquet(f"{tmp_path}/in")
    stream = spark.readStream.schema("id long, feat long").parquet(f"{tmp_path}/in")
    static = spark.createDataFrame(rows, "id long, feat long")
    few, many = ({tuple(r) for r in joins.drained(joins.stream_static_join(stream, static, AT, BitSampling(), reps, 12, 3)).collect()} for reps in (1, 400))
    names, every = [(0, 0)], np.array([v for _, v in rows])
    batch = joins.Batch.__new__(joins.Batch)
    batch.n, batch.kind, batch.words = len(every), "bits", every.view(np.uint64)
    key = BitSampling().keys(batch, 3, names, 12)[:, 0]
    assert few == {r for r in many if key[r[0]] == key[r[1]]} and len(few) < len(many)
