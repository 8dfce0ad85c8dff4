"""Substring dedup of the whole documents table against SQL."""

from __future__ import annotations

import duckdb
from pyspark.sql import functions as F

from proxjoin.llm import oracles, queries

SF = "/root/testdata/sf0.001"


def test_query_equals_sql(spark):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet'")
    found = queries.op9_substring_dedup(spark, SF)
    want = con.sql(oracles.oracle_sql()["op9_substring_dedup"])
    assert found.columns == want.columns
    assert sorted(map(tuple, found.collect())) == sorted(want.fetchall())
    assert found.agg(F.sum("n_removed")).first()[0] > 0
