"""Queries against their SQL on tables with texts without words, copies and repeated values."""

from __future__ import annotations

import duckdb
import numpy as np
import pytest

import __spark_entry__ as entry
from proxjoin.functions.metrics import Thresholds
from proxjoin.operators import baselines, distribution


def same(spark, folder, name):
    con = duckdb.connect()
    for path in folder.glob("*.parquet"):
        con.sql(f"CREATE VIEW {path.stem} AS SELECT * FROM '{path}/*.parquet'")
    df = entry.queries()[name](spark, str(folder))
    want = con.sql(entry.oracle_sql()[name])
    told = lambda columns, rows: sorted(tuple(str(r[columns.index(c)]) for c in sorted(columns)) for r in rows)
    return told(df.columns, [tuple(r) for r in df.collect()]), told(want.columns, want.fetchall())


@pytest.fixture(scope="module")
def wordless(spark, tmp_path_factory):
    folder = tmp_path_factory.mktemp("wordless")
    texts = ["a b c", "b c d", "", "...", None, "a b c", "x y", "!?"]
    rows = [(k, t, "en", "src1", len(t or "")) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    return folder


@pytest.mark.parametrize("name", ["array_set_ops", "minhash_buckets_md5"])
def test_texts_without_words(spark, wordless, name):
    found, want = same(spark, wordless, name)
    assert found == want and found


@pytest.mark.parametrize("metric", ["l1", "l2", "cosine"])
def test_dense_pairs_are_counted_in_cells(spark, metric):
    rng = np.random.default_rng(5)
    vectors = np.r_[rng.normal(size=(90, 8)), np.zeros((1, 8)), np.ones((2, 8))]
    points = spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(vectors)], "id long, feat array<double>")
    at = Thresholds(metric, *((0.5, 0.1) if metric == "cosine" else (3.0, 5.0)))
    edges = [0.9, 0.5, 0.0] if metric == "cosine" else [0.0, 3.0, 9.0]
    got = {r.bin: r.n for r in distribution.dense_counts(points, at, edges, chunk=20).collect()}
    value = [r.value for r in baselines.all_values(points, None, at).collect() if r.value is not None]
    holds = (lambda v, t: v >= t) if metric == "cosine" else (lambda v, t: v <= t)
    assert [sum(got[j] for j in range(1, k + 2)) for k in range(3)] == [sum(holds(v, t) for v in value) for t in edges]


def test_l2_cdf_of_the_query_counts_all_pairs(spark, tmp_path):
    spark.range(10_300).selectExpr("id as vec_id", "transform(sequence(1, 4), k -> cast(xxhash64(id, k) % 1000 / 2000.0 as float)) as embedding", "0 as label").write.parquet(f"{tmp_path}/embeddings.parquet")
    found = {r.threshold: r.pairs for r in entry.queries()["cdf_l2_emb"](spark, str(tmp_path)).collect()}
    v = np.array([r.embedding for r in spark.read.parquet(f"{tmp_path}/embeddings.parquet").collect()], float)
    want = {t: 0 for t in found}
    for k in range(len(v)):
        d = np.sqrt(((v[k + 1 :] - v[k]) ** 2).sum(axis=1))
        for t in want:
            want[t] += int((d <= t).sum())
    assert found == want


def test_stream_repetitions_grow_with_the_points():
    from proxjoin.streaming.queries import repetitions

    p = 0.75**12
    for n in (500, 10_000, 1_000_000):
        assert n * (1 - p) ** repetitions(n, p) <= 1e-6 < n * (1 - p) ** 256


@pytest.mark.parametrize("name", ["cluster_source", "cost_table", "monotone_check", "rho_table"])
def test_measures_read_a_given_table(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = entry.queries()[name](spark, sf)
    want = con.sql(entry.oracle_sql()[name])
    told = lambda columns, rows: sorted(tuple(str(r[columns.index(c)]) for c in sorted(columns)) for r in rows)
    assert told(df.columns, [tuple(r) for r in df.collect()]) == told(want.columns, want.fetchall())
    assert df.inputFiles()
