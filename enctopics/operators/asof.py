"""As-of joins: for each row the last row of another table that isn't later."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def last_before(left: DataFrame, right: DataFrame, by: str, at: str, id_col: str, name: str) -> DataFrame:
    """id_col of left and, as name, that of the latest row of right with the same `by` and (at, id) not beyond.

    Both sides are sorted together once, and the last right row so far is carried along: no range join, whose rows
    grow with the square of a key's.
    """
    a = left.select(by, at, F.col(id_col).alias("_id"), F.lit(1).alias("_side"))
    b = right.select(by, at, F.col(id_col).alias("_id"), F.lit(0).alias("_side"))
    order = Window.partitionBy(by).orderBy(at, "_id", "_side").rowsBetween(Window.unboundedPreceding, 0)
    carried = F.last(F.when(F.col("_side") == 0, F.col("_id")), ignorenulls=True).over(order)
    return a.unionByName(b).withColumn(name, carried).where("_side = 1").select(F.col("_id").alias(id_col), name)
