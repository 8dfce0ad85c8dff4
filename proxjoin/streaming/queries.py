"""The streaming queries: each drains what is there and returns a batch."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.features import sign_bits
from ..functions.metrics import Thresholds
from ..sources.points import load_points
from ..sources.scratch import shared_folder, written
from ..workloads import WORKLOADS
from . import joins


def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joins.drained(joins.tumbling(joins.event_stream(spark, sf_dir)), "complete")


def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joins.drained(joins.tumbling(joins.event_stream(spark, sf_dir), "1 hour", "30 minutes"), "complete")


def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joins.drained(joins.sessions(joins.event_stream(spark, sf_dir)), "complete")


def repetitions(n: int, p: float, missed: float = 1e-6) -> int:
    """As many as leave so many pairs at r missed in expectation, were there n of them, where one finds a pair with probability p."""
    return math.ceil(math.log(missed / max(1, n)) / math.log1p(-p))


def stream_static_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings arrive as a stream of sign words and meet the static ones; the pairs of both sides of an id pair are one."""
    work = WORKLOADS["W6b"]
    arriving = joins.event_stream(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), sign_bits(F.col("embedding")).alias("feat"))
    static, at, k = written(load_points(spark, sf_dir, "emb_sign"), "static"), Thresholds("hamming", 16, 20), 12
    reps = max(256, repetitions(static.count(), work.family.p1p2(at.r, at.cr)[0] ** k))
    found = joins.drained(joins.stream_static_join(arriving, static, at, work.family, reps, k, 3))
    return found.select(F.least("id_l", "id_r").alias("id_l"), F.greatest("id_l", "id_r").alias("id_r"), "dist").distinct()


def stream_stream_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    views = joins.event_stream(spark, sf_dir).where("event_type = 'view'")
    buys = joins.event_stream(spark, sf_dir).where("event_type = 'purchase'")
    return joins.drained(joins.stream_stream_interval(views, buys)).groupBy("user_id").agg(F.count(F.lit(1)).alias("pairs"))


def stream_late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return joins.drained(joins.late_rows(joins.event_stream(spark, sf_dir)), "complete")


def stream_dedup_watermark(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = joins.drained(joins.once(joins.event_stream(spark, sf_dir), ["user_id", "event_type"]).select("user_id", "event_type"))
    return found.distinct()


def stream_state_ttl(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = joins.event_stream(spark, sf_dir).select(F.col("user_id").alias("key"), F.col("event_id").alias("id"), "ts")
    return joins.drained(joins.remembered(rows)).groupBy("key").agg(F.count(F.lit(1)).alias("rows"), F.max("earlier").alias("most_before"))


def stream_upsert_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_folder(spark)}/proxjoin/index-{id(sf_dir)}-{spark.sparkContext.applicationId}-{len(sf_dir)}"
    import uuid

    path = f"{path}-{uuid.uuid4().hex}"
    work = WORKLOADS["W6b"]
    arriving = joins.event_stream(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), sign_bits(F.col("embedding")).alias("feat"))
    joins.upserted_index(arriving, path, work.family, 8, 8)
    return spark.read.parquet(path).groupBy("tag").agg(F.count(F.lit(1)).alias("rows"), F.countDistinct("id").alias("points"))


def queries() -> dict:
    return {f.__name__: f for f in (stream_tumbling, stream_sliding, stream_session, stream_static_neardup, stream_stream_interval, stream_late_rows, stream_dedup_watermark, stream_state_ttl, stream_upsert_index)}
