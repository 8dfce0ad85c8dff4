"""Clusters of near pairs, and what is kept of them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.scratch import written


def dup_clusters(pairs: DataFrame) -> DataFrame:
    """id, cluster: the smallest id that near pairs lead to, for all ids that have one.

    A round takes the smallest label around and then its label's label; it ends as
    a written table, and the driver sees one flag.
    """
    both = written(pairs.select(F.col("id_l").alias("id"), F.col("id_r").alias("other")).union(pairs.select("id_r", "id_l")).distinct(), "edges")
    now = written(both.groupBy("id").agg(F.least("id", F.min("other")).alias("cluster")), "labels")
    while True:
        around = both.join(now.select(F.col("id").alias("other"), "cluster"), "other").groupBy("id").agg(F.min("cluster").alias("near"))
        hooked = now.join(around, "id").select("id", F.col("cluster").alias("was"), F.least("cluster", "near").alias("cluster"))
        above = now.select(F.col("id").alias("cluster"), F.col("cluster").alias("over"))
        now = written(hooked.join(above, "cluster").select("id", F.least("cluster", "over").alias("cluster"), (F.least("cluster", "over") < F.col("was")).alias("moved")), "labels")
        ended = now.where("moved").isEmpty()
        now = now.drop("moved")
        if ended:
            return now


def keep_first(rows: DataFrame, clusters: DataFrame, key: str, best: list) -> DataFrame:
    """One row of each cluster, the first by ``best``; rows outside of clusters stay."""
    joined = rows.join(clusters.withColumnRenamed("id", key), key, "left").withColumn("cluster", F.coalesce("cluster", key))
    return joined.withColumn("place", F.row_number().over(Window.partitionBy("cluster").orderBy(*best))).where("place = 1").drop("place")
