"""Connected components of an edge table by alternating star contractions; state stays in tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import cut


#: Edges of a partition, about: small tables would else be written as very many files in every round.
EDGES = 5_000


def _by_minimum(pairs: DataFrame, few: int) -> DataFrame:
    """Each pair (u, v) with the least v of its u; sums before the shuffle, and a join that Spark can split."""
    pairs = pairs.coalesce(few)
    return pairs.join(pairs.groupBy("u").agg(F.min("v").alias("m")), "u").coalesce(few)


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """node, label: the least node that it can reach; only nodes that have an edge to another node.

    Null ends and loops are ignored, repeated edges count once, no edges give no rows.
    """
    high, low = F.greatest(F.col(a), F.col(b)), F.least(F.col(a), F.col(b))
    now = cut(edges.where(F.col(a) != F.col(b)).select(high.alias("u"), low.alias("v")).distinct())
    seen = None
    parts = now.rdd.getNumPartitions()
    while True:
        state = now.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("u", "v") % 1_000_003), F.lit(0)), F.coalesce(F.bit_xor(F.xxhash64("u", "v")), F.lit(0))).first()
        if state == seen or state[0] == 0:
            return now.select(F.col("u").alias("node"), F.col("v").alias("label")).union(now.select("v", "v")).groupBy("node").agg(F.min("label").alias("label"))
        seen = state
        few = max(1, min(parts, -(-state[0] // EDGES)))  # no more partitions than the edges need
        both = now.union(now.select("v", "u"))
        large = _by_minimum(both, few).select("u", "v", F.least("u", "m").alias("m")).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small = _by_minimum(large, few)
        now = cut(small.select("u", F.col("m").alias("v")).union(small.where("v <> m").select("v", "m")).distinct().coalesce(few))
