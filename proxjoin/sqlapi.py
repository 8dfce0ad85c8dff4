"""The measures and shingles as SQL functions, and SQL forms of the joins."""

from __future__ import annotations

import re

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


@F.udtf(returnType="place int, shingle string")
class Shingles:
    """The shingles of n tokens of a text."""

    def eval(self, text: str, n: int):
        tokens = re.findall("[a-z0-9]+", (text or "").lower())
        for k in range(len(tokens) - n + 1):
            yield k, " ".join(tokens[k : k + n])


def register_functions(spark: SparkSession) -> None:
    """jaccard_similarity, hamming_distance, l2_distance and cosine_of as SQL functions, which Catalyst inlines; proxjoin_shingles as a table function."""
    total = "aggregate(zip_with(a, b, (x, y) -> {}), 0D, (t, x) -> t + x)"
    dot = lambda x, y: f"aggregate(zip_with({x}, {y}, (x, y) -> double(x) * double(y)), 0D, (t, x) -> t + x)"
    bodies = {
        "jaccard_similarity(a array<bigint>, b array<bigint>)": "case when size(a) + size(b) = 0 then 1D else size(array_intersect(a, b)) / (size(a) + size(b) - size(array_intersect(a, b))) end",
        "hamming_distance(a bigint, b bigint)": "double(bit_count(a ^ b))",
        "l2_distance(a array<double>, b array<double>)": f"sqrt({total.format('(x - y) * (x - y)')})",
        "cosine_of(a array<double>, b array<double>)": f"{dot('a', 'b')} / sqrt({dot('a', 'a')} * {dot('b', 'b')})",
    }
    for head, body in bodies.items():
        spark.sql(f"create or replace temporary function {head} returns double return {body}")
    spark.udtf.register("proxjoin_shingles", Shingles)
