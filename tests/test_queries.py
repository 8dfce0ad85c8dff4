"""Registered queries against DuckDB on the smallest tables, and the driver's contract."""

from __future__ import annotations

import decimal
import os

import duckdb
import pytest

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = """aware_jaccard_docs lookback_dedup_docs aware_hamming_docs oblivious_brand_sets prefix_filter_docs rho_table join_sizes_docs minhash_buckets_md5 bitsample_counters_md5 replication_factor_md5
heavy_points_exact cdf_l2_emb asof_last_event price_band_range_join topk_neighbours rollup_levels clusters_listed array_set_ops sparse_map_cosine events_session udtf_shingles leaf_kernel_docs sql_near_pairs
stream_tumbling stream_static_neardup stream_state_ttl cost_table""".split()


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    con.sql("SET timezone = 'UTC'")
    for t in TABLES:
        path = f"{sf}/{t}.parquet"
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def told(value):
    if isinstance(value, float | decimal.Decimal):
        return f"{float(value):.6g}"
    return str(value)


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda k: columns[k])
    return sorted(tuple(told(r[k]) for k in order) for r in data)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, sf, duck, name):
    df = entry.queries()[name](spark, sf)
    want = duck.sql(entry.oracle_sql()[name])
    assert sorted(df.columns) == sorted(want.columns)
    assert rows(df.columns, [tuple(r) for r in df.collect()]) == rows(want.columns, want.fetchall())


def test_contract(spark):
    found = entry.entry(spark)
    assert found.columns == ["id_l", "id_r", "dist"] and found.count() == 27
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_source_and_sinks(spark, sf):
    found = entry.queries()
    assert found["pair_sink"](spark, sf).count() == 27
    assert found["cluster_source"](spark, sf).count() == 10
    assert found["random_emission_docs"](spark, sf).count() > 0
