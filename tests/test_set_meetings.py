"""Meetings of sets in groups of repetitions: the plain join's pairs, without its rows for keys and meetings."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import DataFrame

import __spark_entry__ as entry
from proxjoin.functions.families import MinHash
from proxjoin.functions.metrics import Thresholds
from proxjoin.operators import hashing, memory_aware, set_meetings
from proxjoin.operators.memory_aware import join_until_recall, memory_aware_join

AT = Thresholds("jaccard", 0.5, 0.1)


@pytest.fixture(scope="module")
def sets(spark):
    """Sets of many sizes, near ones, copies, empty ones and nulls."""
    rng = random.Random(5)
    tokens = [rng.getrandbits(59) - 2**58 for _ in range(400)]
    own = [rng.sample(tokens, rng.choice([1, 2, 5, 30, 90, 300])) for _ in range(90)]
    own += [s[: max(1, len(s) * rng.randrange(4, 10) // 10)] for s in own] + own[:15] * 3 + [[]] * 4
    rows = [(1000 - 3 * k, sorted(s)) for k, s in enumerate(own)] + [(1, None), (None, own[0])]
    return spark.createDataFrame(rows, "id long, feat array<long>").repartition(5)


def pairs(df: DataFrame) -> list[tuple]:
    return sorted(map(tuple, df.collect()))


def without_rows(monkeypatch):
    """From here on a row for each key or meeting is an error."""

    def refuse(*args, **more):
        raise AssertionError("a row for each key")

    for name in ("met", "exploded", "measured"):
        monkeypatch.setattr(memory_aware, name, refuse)
    monkeypatch.setattr(hashing, "exploded", refuse)


@pytest.mark.parametrize("group", [set_meetings.GROUP, 30_000, 3_000])
def test_same_pairs_as_the_plain_join(spark, sets, group, monkeypatch):
    known = sets.where("id is not null and feat is not null")
    want = pairs(memory_aware_join(known, None, AT, 40, MinHash(), rounds=2, reps=9, seed=3))
    monkeypatch.setattr(set_meetings, "GROUP", group)
    monkeypatch.setattr(set_meetings, "PASS", group)
    monkeypatch.setattr(set_meetings, "SHARE", 8)
    without_rows(monkeypatch)
    assert pairs(memory_aware_join(sets, None, AT, 40, MinHash(), n=2 * known.count(), rounds=2, reps=9, seed=3, cells=True)) == want and len(want) > 100
    assert memory_aware_join(sets.limit(0), None, AT, 40, MinHash(), cells=True).count() == 0


@pytest.mark.parametrize("far_cap", [0, 20, 10_000])
def test_capped_pairs(spark, sets, far_cap, monkeypatch):
    known = sets.where("id is not null and feat is not null")
    how = {"rounds": 2, "reps": 6, "k": 1, "cap": "round_batch", "far_cap": far_cap, "batch": 2, "seed": 3}
    want = pairs(memory_aware_join(known, None, AT, 40, MinHash(), **how))
    without_rows(monkeypatch)
    assert pairs(memory_aware_join(known, None, AT, 40, MinHash(), cells=True, **how)) == want and want


def test_until_recall(spark, sets, monkeypatch):
    known = sets.where("id is not null and feat is not null")
    want = pairs(join_until_recall(known, None, AT, 20, MinHash(), 0.99, seed=3))
    without_rows(monkeypatch)
    assert pairs(join_until_recall(known, None, AT, 20, MinHash(), 0.99, seed=3, cells=True)) == want and want


def test_repeated_ids_take_the_plain_way(spark):
    rows = [(1, [1, 2, 3]), (1, [7, 8, 9]), (2, [1, 2, 3]), (3, [7, 8, 9])]
    points = spark.createDataFrame(rows, "id long, feat array<long>")
    a, b = (pairs(memory_aware_join(points, None, AT, 2, MinHash(), rounds=3, seed=1, cells=c).distinct()) for c in (True, False))
    assert a == b == [(1, 2, 0.0), (1, 3, 0.0)]


@pytest.mark.parametrize("name", ["aware_jaccard_docs", "aware_capped_docs", "aware_until_recall_docs", "aware_shingles_docs", "aware_pages"])
def test_queries_make_no_row_for_a_key(spark, sf, name, monkeypatch):
    without_rows(monkeypatch)
    assert entry.queries()[name](spark, sf).count() > 0
