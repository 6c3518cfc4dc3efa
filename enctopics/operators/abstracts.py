"""Abstracts: the most frequent tokens of each cluster, kept in plain at the edge."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from enctopics.functions import crypto


def build(clusters: DataFrame, stats: DataFrame, p: int = 10) -> DataFrame:
    """cluster_id, tok, f, rank: the p tokens with the largest frequency; orphans have no abstract."""
    order = Window.partitionBy("cluster_id").orderBy(F.desc("f"), "tok")
    rows = clusters.where("cluster_id >= 0").join(stats.select("tok", F.col("tf").alias("f")), "tok")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= p).select("cluster_id", "tok", "f", "rank")


def reveal(sealed: DataFrame, key: str) -> DataFrame:
    """The column sealed becomes tok; at the edge only."""
    return sealed.withColumn("tok", crypto.open_(F.col("sealed"), key)).drop("sealed")


def refresh(old: DataFrame, touched: DataFrame, clusters: DataFrame, stats: DataFrame, p: int = 10) -> DataFrame:
    """Abstracts anew for the clusters that an update has touched, as they were for the others."""
    ids = touched.select("cluster_id").distinct()
    fresh = build(clusters.join(ids, "cluster_id", "left_semi"), stats, p)
    return old.join(ids, "cluster_id", "left_anti").unionByName(fresh)
