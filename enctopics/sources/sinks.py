"""Where results go: bucketed postings, clusters as partitions, versions of a state."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def write_bucketed(postings: DataFrame, name: str, by: str = "tok", buckets: int = 64) -> None:
    """Postings in buckets of one key and sorted by it, so that joins and sums by that key need no shuffle."""
    postings.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def write_by_cluster(postings: DataFrame, clusters: DataFrame, path: str, folders: int = 4096) -> None:
    """Postings in a folder for each hash of a cluster, sorted by token within, for pruned searches."""
    rows = postings.join(clusters.select("tok", "cluster_id"), "tok").withColumn("part", F.pmod(F.hash("cluster_id"), F.lit(folders)))
    rows.repartition("part").sortWithinPartitions("part", "cluster_id", "tok").write.mode("overwrite").partitionBy("part").parquet(path)


def read_clusters(spark: SparkSession, path: str, routed: DataFrame, folders: int = 4096) -> DataFrame:
    """Postings of the clusters of routed: their folders only, and of these the rows of the clusters themselves.

    What comes to the driver are numbers of folders, at most so many as there are.
    """
    ids = routed.select("cluster_id").distinct()
    parts = [r.p for r in ids.select(F.pmod(F.hash("cluster_id"), F.lit(folders)).alias("p")).distinct().collect()]
    return spark.read.parquet(path).where(F.col("part").isin(parts)).join(ids, "cluster_id", "left_semi").drop("part")


class Versions:
    """A state whose tables are written anew under each version; the version that counts is named last."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")

    def latest(self) -> int | None:
        hadoop = self.spark._jvm.org.apache.hadoop.fs
        path = hadoop.Path(f"{self.path}/done")
        fs = path.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not fs.exists(path):
            return None
        return max((int(s.getPath().getName().split("=")[1]) for s in fs.listStatus(path) if "=" in s.getPath().getName()), default=None)

    def write(self, version: int, **tables: DataFrame) -> None:
        for name, df in tables.items():
            df.write.mode("overwrite").parquet(f"{self.path}/v={version}/{name}")
        self.spark.range(1).write.mode("overwrite").parquet(f"{self.path}/done/v={version}")

    def read(self, name: str, version: int | None = None) -> DataFrame:
        version = self.latest() if version is None else version
        return self.spark.read.parquet(f"{self.path}/v={version}/{name}")
