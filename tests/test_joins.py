"""The joins against exact answers: every variant, both kinds of input, and the laws that runs obey."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from proxjoin.functions.families import BitSampling, MinHash
from proxjoin.functions.metrics import Thresholds
from proxjoin.operators import baselines, clusters, counters
from proxjoin.operators.emission import replication
from proxjoin.operators.hashing import exploded, hashed, met
from proxjoin.operators.memory_aware import buckets, candidates, emissions, memory_aware_join
from proxjoin.operators.memory_oblivious import meetings, memory_oblivious_join
from proxjoin.plans.params import plan_memory_aware, plan_memory_oblivious, predicted_recall
from proxjoin.sources.clusters import flipped, grey_ring_points, random_words, two_cluster_points
from proxjoin.sources.points import load_points, require_points
from proxjoin.sources.scratch import written
from proxjoin.workloads import WORKLOADS


def pairs(df):
    return {(r.id_l, r.id_r) for r in df.collect()}


@pytest.fixture(scope="module")
def words(spark, sf):
    return written(load_points(spark, sf, "doc_words"), "words")


@pytest.fixture(scope="module")
def fingers(spark, sf):
    return written(load_points(spark, sf, "doc_finger64"), "fingers")


W1, W6 = Thresholds("jaccard", 0.5, 0.1), Thresholds("hamming", 10, 20)


def test_set_joins_agree(words):
    want = pairs(baselines.exact_join(words, None, W1))
    assert len(want) == 27
    for join in (baselines.inverted_index_join, baselines.prefix_filter_join, baselines.positional_filter_join, baselines.length_filter_join):
        assert pairs(join(words, W1)) == want
    assert pairs(baselines.block_nested_join(words, None, W1, 40)) == want == pairs(baselines.recursive_nested_join(words, None, W1, 30))
    assert pairs(baselines.single_level_lsh_join(words, None, W1, MinHash())) == want


@pytest.mark.parametrize("dedup", ["distinct", "lookback", "none", "random", "random+distinct"])
def test_memory_aware(words, dedup):
    want = pairs(baselines.inverted_index_join(words, W1))
    found = memory_aware_join(words, None, W1, 64, MinHash(), rounds=3, dedup=dedup)
    rows = [(r.id_l, r.id_r) for r in found.collect()]
    assert set(rows) <= want
    if not dedup.startswith("random"):
        assert set(rows) == want
    if dedup in ("distinct", "lookback", "random+distinct"):
        assert len(rows) == len(set(rows))


def test_memory_aware_two_sides_and_tiny_chunks(spark, sf):
    work = WORKLOADS["W7"]
    left, right = work.points(spark, sf)
    want = pairs(baselines.exact_join(left, right, work.at))
    assert pairs(memory_aware_join(left, right, work.at, 8, MinHash(), rounds=4, k=1)) == want
    assert pairs(memory_oblivious_join(left, right, work.at, MinHash(), repeats=6)) == want


def test_far_cap(words, fingers):
    want = pairs(baselines.exact_join(fingers, None, W6))
    assert pairs(memory_aware_join(fingers, None, W6, 64, BitSampling(), rounds=2, cap="round_batch")) <= want
    strict = pairs(memory_aware_join(fingers, None, W6, 64, BitSampling(), rounds=1, cap="round_batch", far_cap=0, batch=1))
    assert strict <= want
    assert pairs(memory_aware_join(words, None, W1, 64, MinHash(), rounds=3, cap="round_batch")) == pairs(baselines.inverted_index_join(words, W1))


def test_lookback_reports_once_a_round(words):
    plan = plan_memory_aware(400, 64, MinHash(), 0.5, 0.1, rounds=1)
    looked = emissions(words, None, W1, MinHash(), plan, 1, lookback=True).collect()
    every = emissions(words, None, W1, MinHash(), plan, 1)
    assert len(looked) == len({(r.id_l, r.id_r) for r in looked}) == every.select("id_l", "id_r").distinct().count() < every.count()
    first = {(r.id_l, r.id_r): r.tag for r in every.groupBy("id_l", "id_r").agg(F.min("tag").alias("tag")).collect()}
    assert all(first[r.id_l, r.id_r] == r.tag for r in looked)


@pytest.mark.parametrize("options", [{}, {"strict_leaf": True}, {"heavy": False}, {"branching": "ceil"}, {"local_rows": 1000}, {"repeats": 0.999}, {"budget": 1e9}])
def test_memory_oblivious(fingers, options):
    want = pairs(baselines.exact_join(fingers, None, W6))
    found = pairs(memory_oblivious_join(fingers, None, W6, BitSampling(), **({"repeats": 5, "seed": 2} | options)))
    assert found <= want and len(found) >= 0.95 * len(want)


def test_same_seed_same_pairs(fingers):
    a = pairs(memory_aware_join(fingers, None, W6, 32, BitSampling(), rounds=1, seed=5))
    assert a == pairs(memory_aware_join(fingers.repartition(7), None, W6, 32, BitSampling(), rounds=1, seed=5))


def test_emission_is_once_in_expectation(spark):
    base = random_words(spark, 60, 3)
    near = written(base.union(flipped(base, 6, 1000)), "near")
    at = Thresholds("hamming", 6, 24)
    counts = []
    for seed in range(6):
        counts.append(memory_aware_join(near, None, at, 16, BitSampling(), rounds=1, dedup="random", seed=seed).count())
    assert 0.8 * 60 <= sum(counts) / 6 <= 1.2 * 60
    counts = [memory_oblivious_join(near, None, at, BitSampling(), dedup="random", seed=seed).count() for seed in range(4)]
    assert 0.6 * 60 <= sum(counts) / 4 <= 1.4 * 60


def test_recall_at_the_critical_distance(spark):
    base = random_words(spark, 300, 9)
    both = written(base.union(flipped(base, 8, 10_000)), "critical")
    at = Thresholds("hamming", 8, 24)
    plan = plan_memory_oblivious(1200, BitSampling(), 8, 24)
    floor = predicted_recall(plan.p1, plan.branching, plan.depth)
    # the pairs of a run share its functions, so only several runs tell the mean
    found = [memory_oblivious_join(both, None, at, BitSampling(), n=1200, strict_leaf=True, heavy=False, seed=s).count() for s in range(4)]
    assert sum(found) / 4 >= 300 * floor * 0.75


def test_adversarial_inputs(spark):
    at = Thresholds("hamming", 6, 20)
    assert memory_aware_join(grey_ring_points(spark, 6), None, at, 4, BitSampling(), rounds=2).count() == 0
    two = written(two_cluster_points(spark, 120), "two")
    want = pairs(baselines.exact_join(two, None, at))
    assert pairs(memory_oblivious_join(two, None, at, BitSampling(), strict_leaf=True, repeats=3)) == want
    far = random_words(spark, 200, 4)
    assert pairs(memory_aware_join(far, None, at, 32, BitSampling(), rounds=1)) == pairs(baselines.exact_join(far, None, at))


def test_heavy_points_leave(spark, sf):
    work = WORKLOADS["W8"]
    left, _ = work.points(spark, sf)
    plan = plan_memory_oblivious(2 * left.count(), work.family, work.at.r, work.at.cr)
    run = meetings(left, None, work.at, work.family, plan, repeats=1, heavy=True, local_rows=1, branching="random", seed=1, strict_leaf=True)
    quality = counters.heavy_quality(run, left, None, work.at).collect()
    assert all(r.share > 1 / 6 for r in quality)
    sizes = counters.level_sizes(run)
    assert sizes.where("n_l <= 0 or n_r <= 0").isEmpty()
    if run.levels > 1 and run.heavy:
        gone = run.heavy[0].select("side", "id")
        assert run.meetings.where("level > 0").join(gone.where("side = 0").withColumnRenamed("id", "id_l"), "id_l").isEmpty()


def test_collisions_stay_below_their_bounds(fingers):
    plan = plan_memory_oblivious(400, BitSampling(), 10, 20)
    run = meetings(fingers, None, W6, BitSampling(), plan, repeats=1, heavy=False, local_rows=1, branching="ceil", seed=4, strict_leaf=True)
    sizes = baselines.join_sizes(fingers, None, W6).first()
    seen = counters.collisions_by_level(run, fingers, None, W6).collect()
    total = {c: sum(r[c] for r in seen) for c in ("near", "grey", "far")}
    last = run.levels - 1
    assert total["near"] <= sizes.near * 3**last and total["grey"] <= 2 * sizes.grey
    rows = counters.replication_by_level(run).collect()
    assert all(r.rows <= 400 * 3**r.level for r in rows)
    trace = counters.oblivious_cost(run, fingers, None, W6, [200, 50, 10])
    assert [c for _, c in trace] == sorted(c for _, c in trace)


def test_chunks_tile_a_bucket_once(spark):
    rows = spark.range(50).select(F.lit(0).alias("tag"), F.lit(1).alias("key"), "id")
    found = met(rows, rows, ["tag", "key"], 8)
    assert found.count() == 2500 == found.select("id_l", "id_r").distinct().count()


def test_plans_never_compare_everything(words, fingers):
    for df in (memory_aware_join(words, None, W1, 64, MinHash(), n=400, rounds=1), baselines.prefix_filter_join(words, W1)):
        text = df._jdf.queryExecution().executedPlan().toString()
        assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    plan = plan_memory_aware(400, 64, MinHash(), 0.5, 0.1, rounds=1)
    keyed = buckets(words, MinHash(), plan, 0, range(1))
    assert keyed.columns == ["id", "tag", "key"]  # features don't travel to the buckets
    assert candidates(words, None, MinHash(), plan, 0).columns == ["tag", "key", "id_l", "id_r"]


def test_edges(spark):
    sets = spark.createDataFrame([(1, []), (2, []), (3, [5]), (4, None)], "id long, feat array<long>")
    points = require_points(sets, "jaccard")
    assert pairs(memory_aware_join(points, None, W1, 2, MinHash(), rounds=4)) == {(1, 2)} == pairs(baselines.exact_join(points, None, W1))
    zero = spark.createDataFrame([(1, [0.0, 0.0]), (2, [0.0, 0.0])], "id long, feat array<double>")
    assert baselines.exact_join(zero, None, Thresholds("cosine", 0.7, 0.2)).count() == 0
    with pytest.raises(TypeError):
        require_points(sets, "l2")
    with pytest.raises(ValueError):
        require_points(sets.union(sets.limit(1)), "jaccard", unique=True)
    with pytest.raises(ValueError):
        Thresholds("l1", 5, 5)
    none = points.limit(0)
    assert memory_aware_join(none, None, W1, 2, MinHash(), rounds=1).count() == 0
    assert memory_oblivious_join(none, points, W1, MinHash()).count() == 0


def test_measures_of_runs(words):
    plan = plan_memory_aware(400, 64, MinHash(), 0.5, 0.1, rounds=2)
    every = emissions(words, None, W1, MinHash(), plan, 1)
    r = replication(every).first()
    assert r.emissions >= r.pairs and r.replication == pytest.approx(r.emissions / r.pairs)
    truth = baselines.inverted_index_join(words, W1)
    report = counters.recall(every, truth).first()
    assert report.recall == 1 and report.precision == 1
    assert counters.observe_run(truth).rows == 27


def test_clusters(spark):
    chain = spark.createDataFrame([(k, k + 1) for k in range(1, 40)] + [(100, 101)], "id_l long, id_r long")
    got = {r.id: r.cluster for r in clusters.dup_clusters(chain).collect()}
    assert got == {k: 1 for k in range(1, 41)} | {100: 100, 101: 100}


def test_hashing_is_the_same_for_any_batching(words):
    names = [(0, j) for j in range(5)]
    a = {r.id: tuple(r["keys"]) for r in hashed(words, MinHash(), 1, names, 2).collect()}
    b = {r.id: tuple(r["keys"]) for r in hashed(words.repartition(9), MinHash(), 1, names, 2).collect()}
    assert a == b and exploded(hashed(words, MinHash(), 1, names, 2)).count() == 5 * len(a)
