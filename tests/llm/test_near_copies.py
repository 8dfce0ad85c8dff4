"""Near copies by the exact similarity of their shingles, against brute force."""

from __future__ import annotations

import numpy as np
import pytest

import corpus_pipeline
from proxjoin.llm import near_copies, simhash


def shingles(text, wide=5):
    w = (text or "").encode().lower().split()
    return {tuple(w[k : k + wide]) for k in range(max(1, len(w) - wide + 1))}


def brute(rows):
    """One row of each component: the smallest doc_id, then text key."""
    sets, group = [shingles(r[1]) for r in rows], list(range(len(rows)))
    for a in range(len(rows)):
        for b in range(a):
            if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b]):
                old, new = group[a], group[b]
                group = [new if g == old else g for g in group]
    return [[r for r, g in zip(rows, group, strict=True) if g == k] for k in sorted(set(group))]


def corpus():
    """Copies of some texts with 1 to 12 words changed: similarities of 0.4 to 0.99, several between 0.8 and 1."""
    rng = np.random.default_rng(3)
    rows, line = [], "a line that many of these documents share with each other".split()
    for k in range(12):
        base = [f"w{rng.integers(400)}" for _ in range(150 + 10 * k)]
        for j in range(10):
            w = [*base]
            for at in rng.choice(len(w), j, replace=False):
                w[at] = f"n{k}x{j}x{at}"
            rows.append((100 * j + k, " ".join(w + line)))
    return [*rows, (5000, "Short text"), (5001, "short  TEXT"), (5002, ""), (5003, None), (5004, "alone")]


@pytest.mark.parametrize(("crowd", "cell"), [(64, 2048), (3, 2048), (1, 7)])
def test_near_copies_are_all_found(spark, crowd, cell):
    rows = corpus()
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    found = {}
    for r in near_copies.near_rows(frame, crowd=crowd, cell=cell).collect():
        found.setdefault(bytes(r.label), set()).add(r.doc_id)
    assert sorted(map(sorted, found.values())) == sorted(sorted(r[0] for r in group) for group in brute(rows))


def test_stage_drops_near_copies(spark):
    rows = corpus()
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    kept = corpus_pipeline.drop_near_copies(spark, frame, "")
    assert sorted(r.doc_id for r in kept.collect()) == sorted(min(r[0] for r in group) for group in brute(rows))
    assert corpus_pipeline.drop_near_copies(spark, frame.limit(0), "").count() == 0


@pytest.mark.parametrize("dedup", [near_copies.near_dedup, simhash.near_dedup])
def test_one_row_of_each_component_stays(spark, dedup):
    text = [" ".join(f"{t}{k}" for k in range(100)) for t in "abcdefg"]
    linked = [(1, text[0]), (None, text[0].upper()), (None, text[1]), (None, text[2]), (2, text[3]), (5, text[3].upper()), (5, text[4])]
    same = [(None, text[5]), (None, text[5].upper()), (9, text[6]), (9, text[6]), (9, text[6].upper())]
    frame = spark.createDataFrame(linked + same, "doc_id long, text string")
    got = [(r.doc_id, r.text.lower()) for r in dedup(frame).collect()]
    want = [(1, text[0]), (None, text[1]), (None, text[2]), (2, text[3]), (5, text[4]), (None, text[5]), (9, text[6])]
    assert sorted(map(str, got)) == sorted(map(str, want))


def forest(n, links):
    group = list(range(n))
    for a, b in links:
        group = [group[a] if g == group[b] else g for g in group]
    return [group.index(g) for g in group]


@pytest.mark.parametrize("budget", [2, 5, 11])
@pytest.mark.parametrize("step", [1 << 18, 7])
def test_chains_link_all_fingerprints_within_the_budget(budget, step):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 64, 12, np.uint64)
    bits = np.concatenate([base, *[[b ^ np.uint64(sum(1 << int(k) for k in rng.choice(64, n, replace=False))) for n in (1, 2, 3, 5, 6, 10, 11, 12)] for b in base]])
    for part in (np.zeros(len(bits), np.int64), np.arange(len(bits)) % 2):
        got = simhash.chained(bits, budget, part, np.arange(len(bits)), step)
        near = [(a, b) for a in range(len(bits)) for b in range(a) if int(bits[a] ^ bits[b]).bit_count() <= budget and (not part.any() or part[a] != part[b])]
        assert all((max(p), min(p)) in near for p in got)
        assert forest(len(bits), got) == forest(len(bits), near) and len(got) == len(bits) - len(set(forest(len(bits), near)))


@pytest.mark.parametrize("cell", [1 << 14, 5])
def test_cells_of_fingerprints_link_like_sizes(spark, cell):
    rng = np.random.default_rng(6)
    base = rng.integers(0, 1 << 63, 20).tolist()
    rows = [(b ^ flip, int(size)) for b in base for flip, size in ((0, 100), (5, 118), (1 << 40, 300))] + [(base[0], 2000)]
    got = {(r.a, r.b) for r in simhash.cell_links(spark.createDataFrame(rows, "bits long, size long"), 2, 0.23, cell).collect()}
    assert got == {tuple(sorted((b, b ^ 5))) for b in base}


def test_stage_links_by_fingerprints_first(spark, monkeypatch):
    """Without what the exact search adds, SimHash still finds three quarters of the links, and none that is less alike."""
    monkeypatch.setattr(near_copies, "shared", lambda docs, *_: docs.sparkSession.createDataFrame([], "token long, node binary, n long"))
    rows = corpus()
    found = {}
    for r in near_copies.near_rows(spark.createDataFrame(rows, "doc_id long, text string")).collect():
        found.setdefault(bytes(r.label), set()).add(r.doc_id)
    whole = {r[0]: k for k, group in enumerate(brute(rows)) for r in group}
    assert all(len({whole[i] for i in group}) == 1 for group in found.values())
    joined = len(rows) - len(brute(rows))
    assert len(rows) - len(found) >= 0.75 * joined
