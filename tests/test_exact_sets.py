"""Exact set joins in cells of like sizes: all pairs, without a row for each shared token."""

from __future__ import annotations

import random

import pytest

import __spark_entry__ as entry
from proxjoin.functions.families import MinHash
from proxjoin.functions.metrics import Thresholds
from proxjoin.operators import exact_sets, memory_aware
from proxjoin.plans.params import plan_memory_aware

AT = Thresholds("jaccard", 0.5, 0.1)


def plan_of(df) -> str:
    return df._jdf.queryExecution().toString()


@pytest.fixture(scope="module")
def sets(spark):
    rng = random.Random(3)
    own = [set(rng.sample(range(400), rng.choice([1, 2, 3, 7, 20, 60, 190]))) for _ in range(120)]
    own += [set(rng.sample(sorted(s), max(1, len(s) * 2 // 3))) | {500} for s in own] + own[:20] + [set()] * 3
    tokens = [rng.getrandbits(59) for _ in range(501)]
    return {k: sorted(tokens[t] for t in s) for k, s in enumerate(own)}


@pytest.mark.parametrize("kind", exact_sets.FILTERS)
@pytest.mark.parametrize("chunk", [1 << 15, 16])
def test_all_pairs_are_found(spark, sets, kind, chunk, monkeypatch):
    monkeypatch.setattr(exact_sets, "SETS", chunk)
    points = spark.createDataFrame(list(sets.items()), "id long, feat array<long>")
    found = {(r.id_l, r.id_r): r.dist for r in exact_sets.exact_set_join(points, AT, kind).collect()}
    want = {}
    for a in sets:
        for b in range(a + 1, len(sets)):
            x, y = set(sets[a]), set(sets[b])
            if x and 2 * len(x & y) >= len(x | y):
                want[a, b] = round(1 - len(x & y) / len(x | y), 6)
    assert found == pytest.approx(want) and len(want) > 100


@pytest.mark.parametrize("name", ["exact_jaccard_docs", "prefix_filter_docs", "positional_filter_docs", "rank_neighbours"])
def test_exact_join_makes_no_row_for_a_shared_token(spark, sf, name):
    df = entry.queries()[name](spark, sf)
    assert "token" not in plan_of(df) and df.count() == 27


def test_emissions_of_all_near_pairs_are_those_of_the_join(spark, sets):
    points = spark.createDataFrame(list(sets.items()), "id long, feat array<long>")
    plan = plan_memory_aware(len(sets), len(sets) // 8, MinHash(), 0.5, 0.1, 2)
    rows = lambda df: sorted((r.tag, r.id_l, r.id_r, r.dist) for r in df.collect())
    values = exact_sets.near_values(points, AT, empty=True)
    want = rows(memory_aware.emissions(points, None, AT, MinHash(), plan, 7))
    assert rows(memory_aware.emissions_among(values, points, AT, MinHash(), plan, 7)) == want and want
    met = {r.tag: r.meetings for r in memory_aware.meetings_by_tag(points, MinHash(), plan, 7).collect()}
    seen = memory_aware.candidates(points, None, MinHash(), plan, 7).groupBy("tag").count().collect()
    assert {k: n for k, n in met.items() if n} == {r.tag: r["count"] for r in seen}
