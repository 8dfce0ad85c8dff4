"""Substring dedup where rows repeat a doc_id, or have none, against brute force over rows."""

from __future__ import annotations

import collections

import numpy as np
import pytest
from pyspark.sql import functions as F

from proxjoin.llm import repeats
from proxjoin.llm.blobs import places_opened, places_packed

SCHEMA = "doc_id long, text string"


def listed(tag, n):
    return " ".join(f"{tag}{k}" for k in range(n))


def got(spark, rows, parts=1, **more):
    frame = spark.createDataFrame(rows, SCHEMA).repartition(parts)
    return collections.Counter((r.doc_id, r.n_words, r.n_removed, r.kept) for r in repeats.substring_dedup(frame, **more).collect())


def test_places_may_go_back():
    ids, starts = np.array([4, 4, 4, 4, 4, 4, 9]), np.array([3, 10, 40, 3, 10, 40, 7])
    assert [x.tolist() for x in places_opened(*places_packed(ids, starts))] == [ids.tolist(), starts.tolist()]


@pytest.mark.parametrize("parts", [1, 3])
def test_a_row_twice_keeps_its_text(spark, parts):
    text = listed("w", 200)
    assert got(spark, [(1, text), (1, text), (2, "other words")], parts) == {(1, 200, 0, text): 2, (2, 2, 0, "other words"): 1}


def row_brute(rows, window=20):
    """Windows are taken from the first row that has them; rows that share an id may come in any order."""
    first, out = {}, collections.Counter()
    for n, (doc_id, text) in enumerate(rows):
        w = (text or "").split()
        gone = set()
        for k in range(len(w) - window + 1):
            if first.setdefault(tuple(w[k : k + window]), (n, k)) != (n, k):
                gone |= {*range(k, k + window)}
        out[doc_id, len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone)] += 1
    return out


@pytest.mark.parametrize("parts", [1, 3])
@pytest.mark.parametrize("same", [None, 7])
def test_rows_without_own_id_are_told_apart(spark, parts, same):
    passage = listed("p", 30)
    rows = [(1, passage), (same, listed("a", 10)), (same, f"{listed('b', 50)} {passage} {listed('c', 20)}"), (same, listed("d", 90)), (same, None)]
    assert got(spark, rows, parts) == row_brute(rows)
    # the same start in two rows: one keeps the passage
    twins = [(same, f"{passage} {listed('e', 5)}"), (same, f"{passage} {listed('f', 9)}")]
    assert got(spark, twins, parts) in (row_brute(twins), row_brute(twins[::-1]))


def test_a_span_unlike_its_source_is_found(spark):
    passage = " ".join(f"p{k}" for k in range(40))
    docs = spark.createDataFrame([(1, f"a {passage}"), (2, f"{passage} b"), (None, passage)], "doc_id long, text string")
    found = repeats.substring_dedup(docs)
    apart = repeats.told_apart(docs)
    assert found.where("size(spans) > 0").count() == 2 and repeats.differing(found, apart, 16).count() == 0
    moved = found.withColumn("spans", F.transform("spans", lambda s: s.withField("source_start", s["source_start"] - 1)))
    assert {r.source_doc for r in repeats.differing(moved, apart, 16).collect()} == {1}
