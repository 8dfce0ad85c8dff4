"""Parts of batches by bytes of their texts."""

from __future__ import annotations

import pyarrow as pa
import pytest

from proxjoin.llm.blobs import by_bytes

TEXTS = [None, "", "ab", "é" * 10, "x" * 50, "", "y", None]


@pytest.mark.parametrize("step", [1, 3, 20, 1000])
def test_parts_hold_every_row_once_and_stay_small(step):
    batch = pa.record_batch([pa.array(range(len(TEXTS)), pa.int64()), pa.array(TEXTS, pa.string())], names=["doc_id", "text"])
    parts = list(by_bytes(batch, step))
    assert [t for p in parts for t in p.column(1).to_pylist()] == TEXTS
    for p in parts:
        sizes = [len((t or "").encode()) for t in p.column(1).to_pylist()]
        assert sum(sizes[:-1]) < step


def test_no_rows_no_parts():
    assert list(by_bytes(pa.record_batch([pa.array([], pa.string())], names=["text"]), 10)) == []
