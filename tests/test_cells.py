"""Joins in cells against all pairs, with chunks so small that there are many cells."""

from __future__ import annotations

import math
from collections import Counter

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from proxjoin.functions import features
from proxjoin.functions.families import Batch, BitSampling, HashFamily, Hyperplane, MinHash
from proxjoin.functions.metrics import Thresholds
from proxjoin.operators import baselines, cells, counters
from proxjoin.operators.memory_aware import candidates, memory_aware_join
from proxjoin.plans.params import plan_memory_aware
from proxjoin.workloads import WORKLOADS

L2 = Thresholds("l2", 1.1, 1.2)


def vectors(spark, n=90):
    """Unit vectors, with copies, a zero vector and a point without one."""
    rng = np.random.default_rng(5)
    v = rng.standard_normal((n, 8))
    v[60:70] = v[:10]
    v[70:80] = v[10]
    v /= np.linalg.norm(v, axis=1)[:, None]
    v[80] = 0
    rows = [(3 * k, [float(x) for x in v[k].astype("f4")]) for k in range(n)]
    return spark.createDataFrame([*rows, (1000, None), (None, rows[0][1])], "id long, feat array<float>")


@pytest.mark.parametrize("chunk", [8, 1000])
@pytest.mark.parametrize("k", [5, 70])
def test_closest_pairs(spark, monkeypatch, chunk, k):
    points = vectors(spark)
    want = baselines.exact_join(points, None, L2).orderBy("dist", "id_l", "id_r").limit(k)
    monkeypatch.setattr(cells.in_cells, "__defaults__", (chunk, None))
    assert [tuple(r) for r in cells.closest_pairs(points, L2, k).collect()] == [tuple(r) for r in want.collect()]
    assert cells.closest_pairs(points.limit(0), L2, k).count() == 0


def test_closest_pairs_makes_no_row_for_each_pair(spark, sf):
    found = entry.queries()["closest_pairs_top"](spark, sf)
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "NestedLoopJoin" not in plan
    assert found.count() == 10


def words(spark, n=120):
    rng = np.random.default_rng(6)
    w = rng.integers(-(1 << 63), (1 << 63) - 1, n)
    for k in range(40, 80):
        w[k] = w[k - 40] ^ sum(1 << int(b) for b in rng.choice(63, rng.integers(0, 9), replace=False))
    return spark.createDataFrame([*[(5 * k, int(w[k])) for k in range(n)], (1, None), (None, 3)], "id long, feat long")


@pytest.mark.parametrize("chunk", [16, 1000])
def test_memory_aware_in_cells_is_the_join_by_buckets(spark, monkeypatch, chunk):
    monkeypatch.setattr(cells, "CHUNK_BITS", chunk)
    monkeypatch.setattr(cells.in_cells, "__defaults__", (chunk, None))
    works = [(words(spark), Thresholds("hamming", 10, 20), BitSampling()), (vectors(spark), Thresholds("cosine", 0.4, 0.2), Hyperplane())]
    for points, at, family in works:
        for rounds in (1, 4):
            got, want = (sorted(map(tuple, memory_aware_join(points.where("id is not null and feat is not null"), None, at, 30, family, rounds=rounds, reps=4, k=5, seed=2, cells=c).collect())) for c in (True, False))
            assert got == want
    assert memory_aware_join(words(spark).limit(0), None, works[0][1], 30, BitSampling(), cells=True).count() == 0


@pytest.mark.parametrize("family", [BitSampling(), Hyperplane()])
def test_keys_agree_where_all_functions_do(family):
    rng = np.random.default_rng(7)
    batch = Batch.__new__(Batch)
    batch.n, batch.kind, batch.words, batch.matrix = 300, family.kind, rng.integers(0, 16, 300).astype(np.uint64), rng.standard_normal((300, 3)).round()
    for k in (1, 5, 70):
        got, want = family.keys(batch, 3, [(0, 1), (2, 5)], k), HashFamily.keys(family, batch, 3, [(0, 1), (2, 5)], k)
        assert ((got[:, None] == got[None]) == (want[:, None] == want[None])).all()


@pytest.mark.parametrize("own", [True, False])
def test_points_that_have_met_are_not_hashed_again(own):
    class Counting(Hyperplane):
        def keys(self, batch, seed, names, k):
            hashed.append(batch.n)
            return super().keys(batch, seed, names, k)

    rng, hashed, names = np.random.default_rng(11), [], [(0, j) for j in range(1000)]
    a, b = (Batch.__new__(Batch) for _ in range(2))
    for batch, n in ((a, 80), (b, 70)):
        batch.n, batch.kind, batch.matrix = n, "dense", rng.standard_normal((n, 3))
    b = a if own else b
    keys_a, keys_b = (Hyperplane().keys(m, 3, names, 9) for m in (a, b))
    x, y = np.nonzero(a.matrix @ b.matrix.T > 0)
    want = (keys_a[x] == keys_b[y]).any(axis=1)
    assert (cells.ever_met(x, y, a, b, own, Counting(), 3, names, 9) == want).all() and 0 < want.sum() < len(want)
    close = (a.matrix @ b.matrix.T > 0.99 * np.outer(np.linalg.norm(a.matrix, axis=1), np.linalg.norm(b.matrix, axis=1))) & ~(np.eye(a.n, b.n, dtype=bool) & own)
    hashed.clear()
    cells.ever_met(*np.nonzero(close), a, b, own, Counting(), 3, names, 9)
    assert sum(hashed) < 0.5 * len(names) / cells.TAGS * (a.n if own else a.n + b.n)


def groups(spark, n=60):
    """Sets of few tokens, with copies, an empty set and a point without one."""
    rng = np.random.default_rng(8)
    rows = [(7 * k, sorted(set(rng.integers(0, 9, 8).tolist()))) for k in range(n)]
    return spark.createDataFrame([*rows, (1, rows[0][1]), (2, rows[0][1]), (3, rows[1][1]), (4, []), (5, None)], "id long, feat array<long>")


@pytest.mark.parametrize("chunk", [16, 1000])
def test_links_are_those_of_the_join(spark, monkeypatch, chunk):
    monkeypatch.setattr(cells.in_cells, "__defaults__", (chunk, None))
    at, points = Thresholds("jaccard", 0.7, 0.5), groups(spark)
    names, whole = [(0, j) for j in range(40)], points.where("feat is not null")
    want = Counter()
    for a, b, _ in baselines.exact_join(whole, None, at).collect():
        want.update((a, b))
    first = {}
    for r in sorted(whole.collect()):
        first.setdefault(tuple(r.feat), r.id)
    assert sorted(map(tuple, cells.links_met(points, at, MinHash(), 7, names, 2).collect())) == sorted((r.id, first[tuple(r.feat)], want[r.id]) for r in whole.collect())


def test_brand_sets_have_a_row_for_each_customer(spark, sf):
    con = duckdb.connect()
    for name in ("orders", "lineitem", "part"):
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{sf}/{name}.parquet'")
    found = entry.queries()["aware_brand_sets"](spark, sf)
    assert found.columns == ["id", "class_id", "links"]
    assert sorted(map(tuple, found.collect())) == sorted(con.execute(entry.oracle_sql()["aware_brand_sets"]).fetchall())


@pytest.mark.parametrize("whole", [True, False])
@pytest.mark.parametrize(("chunk", "leaf"), [(16, 4), (1000, 16)])
def test_halved_l1(spark, monkeypatch, whole, chunk, leaf):
    monkeypatch.setattr(cells.in_cells, "__defaults__", (chunk, None))
    rng = np.random.default_rng(9)
    v = rng.integers(0, 9, (70, 6)) * rng.integers(1, 6, (70, 1))
    v = v if whole else v + rng.random((70, 6)).round(3)
    v[40:50] = v[:10]
    points = spark.createDataFrame([(int(3 * k), [float(x) for x in row]) for k, row in enumerate(v)], "id long, feat array<double>")
    at = Thresholds("l1", 25, 40)
    want = sorted(map(tuple, baselines.exact_join(points, None, at).collect()))
    assert sorted(map(tuple, baselines.recursive_nested_join(points, None, at, leaf).collect())) == want and len(want) > 20
    assert baselines.recursive_nested_join(points.limit(0), None, at, leaf).count() == 0


def test_halved_l1_makes_no_row_for_each_pair(spark, sf):
    plan = entry.queries()["recursive_nested_l1_docs"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plan and "HashJoin" not in plan


@pytest.mark.parametrize("chunk", [16, 1000])
def test_collision_counts(spark, monkeypatch, chunk):
    monkeypatch.setattr(cells, "CHUNK_BITS", chunk)
    at, points = Thresholds("hamming", 10, 20), words(spark)
    whole, names = points.where("id is not null and feat is not null"), [(r, j) for r in range(2) for j in range(4)]
    plan = plan_memory_aware(240, 30, BitSampling(), at.r, at.cr, 2, 4, 3)
    met = counters.collisions(candidates(whole, None, BitSampling(), plan, 7), whole, None, at).first()
    size = baselines.join_sizes(whole, None, at).first()
    assert tuple(cells.collision_counts(points, at, BitSampling(), 7, names, 3).first()) == (met.near, met.grey, met.far, size.near, size.grey)
    assert tuple(cells.collision_counts(points.limit(0), at, BitSampling(), 7, names, 3).first()) == (0, 0, 0, 0, 0)


def test_collision_bounds_count_all_rounds(spark, sf):
    work = WORKLOADS["W6"]
    points = work.points(spark, sf)[0]
    n = 2 * points.count()
    plan = plan_memory_aware(n, n // 16, work.family, work.at.r, work.at.cr)
    assert plan.rounds == math.ceil(3 * math.log2(n))
    met = counters.collisions(candidates(points, None, work.family, plan, 7), points, None, work.at).first()
    got = entry.queries()["collision_bounds"](spark, sf).first()
    assert (got.near, got.grey, got.far) == (met.near, met.grey, met.far)
    assert got.near <= got.near_bound and got.grey <= got.grey_bound and got.far <= got.far_bound


@pytest.mark.parametrize("chunk", [16, 1000])
def test_close_pairs_are_those_of_all_values(spark, monkeypatch, chunk):
    monkeypatch.setattr(cells, "CHUNK", chunk)
    at, points = Thresholds("cosine", 0.4, 0.2), vectors(spark)
    want = baselines.all_values(points, None, at).where("value >= 0.2")
    assert sorted(map(tuple, cells.close_pairs(points, at).collect())) == sorted(map(tuple, want.collect()))


def test_lateral_topk_makes_no_row_for_each_pair(spark, sf, monkeypatch):
    monkeypatch.setattr(baselines, "all_values", None)
    found = entry.queries()["lateral_topk"](spark, sf)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{sf}/embeddings.parquet'")
    assert sorted(map(tuple, found.collect())) == sorted(con.execute(entry.oracle_sql()["lateral_topk"]).fetchall())


def test_meetings_come_in_pieces(monkeypatch):
    """Points that all meet are looked at a few at a time, so a crowded bucket takes no more memory."""
    monkeypatch.setattr(cells, "MEETINGS", 100)
    keys = np.r_[np.zeros(40, np.int64), np.arange(20) << 48]
    pieces = list(cells.met_at(keys, keys[::-1].copy()))
    assert max(len(x) for x, _ in pieces) <= 160
    found = [(a, b) for x, y in pieces for a, b in zip(x.tolist(), y.tolist(), strict=True)]
    assert sorted(found) == [(a, b) for a in range(60) for b in range(60) if keys[a] == keys[59 - b]]


def test_fingerprints_in_pieces(spark):
    texts = spark.createDataFrame([(1, "a b c d e"), (2, ""), (3, "f g a"), (4, None)], "id long, text string")
    whole, pieces = (sorted(map(str, features.fingerprints64(texts, step).collect())) for step in (1 << 16, 2))
    assert whole == pieces
