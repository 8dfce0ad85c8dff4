"""Social security numbers stay among the valid ones, differ where their values differ, and come back."""

from __future__ import annotations

import re

from proxjoin.llm import pseudonyms


def test_social_security_numbers_are_permuted_among_the_valid(spark):
    values = [f"{a:03d}-{g:02d}-{s:04d}" for a in range(1, 900, 3) if a != 666 for g, s in ((1, 1), (99, 9999), (45, 1268))]
    values += ["123-45-1268", "665-01-0001", "667-01-0001", "899-99-9999"]
    values = list(dict.fromkeys(values))
    frame = spark.createDataFrame(list(enumerate(values)), "doc_id long, text string")
    made = pseudonyms.pseudonymise(frame)
    out = [r.text for r in made.orderBy("doc_id").collect()]
    assert all(re.fullmatch(r"(?!000|666|9)\d{3}-(?!00)\d\d-(?!0000)\d{4}", p) for p in out)
    assert len(set(out)) == len(values)
    assert [r.text for r in pseudonyms.restore(made).orderBy("doc_id").collect()] == values


def test_invalid_numbers_stay(spark):
    values = ["000-12-3456", "666-12-3456", "900-12-3456", "123-00-3456", "123-45-0000"]
    frame = spark.createDataFrame(list(enumerate(values)), "doc_id long, text string")
    assert [r.text for r in pseudonyms.pseudonymise(frame).orderBy("doc_id").collect()] == values
