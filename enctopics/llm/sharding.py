"""Shards of nearly equal size from sampled splitters; DataFrame functions only.

A size-weighted sample of hashed keys gives quantile boundaries. They cut the key space into many more
ranges than shards; ranges that turn out overfull (one hot key, or an unlucky sample) are subdivided by row.
Exact sizes of the ranges, summed in order, then place every row by the middle of its own extent, so a shard
differs from the mean by at most about one row. Equal texts have equal keys and lie next to each other; their group is
split where a border between two shards falls into it, and where it is overfull or has more than ROWS_A_RANGE rows,
since sizes come first.

Nulls: a null text counts as no bytes, null ids are ordinary rows. Repeated rows each get a slot of their own.
An empty table gives an empty result. Other columns of the input are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from enctopics.llm.common import cut, narrow, no_null, small

#: Fewest ranges a shard is made of, most ranges in all, rows a range should have, sampled keys a range.
RANGES_A_SHARD, MOST_RANGES, ROWS_A_RANGE, SAMPLES_A_RANGE = 32, 4096, 50_000, 8


def _below(key: Column, bounds: list[int]) -> Column:
    """How many of the sorted bounds are at most key: first over every 64th, then over the 64 in between."""
    if not bounds:
        return F.lit(0)
    coarse, fine = F.lit(bounds[63::64]), F.lit(bounds)
    blocks = F.size(F.filter(coarse, lambda b: b <= key)) * 64 if len(bounds) >= 64 else F.lit(0)
    return blocks + F.size(F.filter(F.slice(fine, blocks + 1, F.lit(64)), lambda b: b <= key))


def shard(docs: DataFrame, n_shards: int = 24, balance: str = "bytes", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard, for shards of equal bytes or equal rows."""
    if balance not in ("bytes", "rows"):
        raise ValueError(f"balance is bytes or rows, not {balance!r}")
    text = no_null(F.col("text"))
    size = (F.octet_length(text) + 8).cast("long")
    rows = cut(
        narrow(docs, doc_id=id_col, text=text_col).select(
            "doc_id",
            size.alias("size"),
            F.crc32(text.cast("binary")).cast("long").alias("text_crc32"),
            F.xxhash64(text).alias("key"),
            F.monotonically_increasing_id().alias("row"),
            (size if balance == "bytes" else F.lit(1).cast("long")).alias("weight"),
        )
    )
    n, total = rows.agg(F.count("*"), F.coalesce(F.sum("weight"), F.lit(1))).first()
    ranges = min(MOST_RANGES, max(RANGES_A_SHARD * n_shards, n // ROWS_A_RANGE))
    wanted = ranges * SAMPLES_A_RANGE
    sampled = rows.where(F.rand(17) * total < F.col("weight") * wanted).select("key").orderBy("key").collect()
    keys = [r.key for r in sampled]
    bounds = sorted({keys[i * len(keys) // ranges] for i in range(1, ranges)} if keys else set())
    placed = rows.withColumn("range", _below(F.col("key"), bounds))

    even = max(1, total // ranges)
    parts = placed.groupBy("range").agg(F.greatest(F.lit(1), F.ceil(F.sum("weight") / (2 * even)), F.ceil(F.count("*") / ROWS_A_RANGE)).alias("parts"))
    placed = placed.join(F.broadcast(parts), "range").withColumn(
        "part", F.when(F.col("parts") > 1, F.pmod(F.xxhash64("row"), F.col("parts"))).otherwise(F.lit(0))
    )

    in_order = Window.orderBy("range", "part")
    before = in_order.rowsBetween(Window.unboundedPreceding, -1)
    extents = cut(
        placed.groupBy("range", "part")
        .agg(F.sum("weight").alias("w"), F.count("*").alias("c"))
        .select("range", "part", F.coalesce(F.sum("w").over(before), F.lit(0)).alias("w0"), F.coalesce(F.sum("c").over(before), F.lit(0)).alias("c0"))
    )
    inside = Window.partitionBy("range", "part").orderBy("key", "doc_id", "row")
    mass = F.col("w0") + F.sum("weight").over(inside.rowsBetween(Window.unboundedPreceding, 0))
    dealt = cut(
        placed.join(small(extents, extents.count()), ["range", "part"])
        .withColumn("index", F.col("c0") + F.row_number().over(inside) - 1)
        .withColumn("twice", 2 * mass - F.col("weight"))
        .select("doc_id", "size", "text_crc32", "index", F.expr(f"cast(least({n_shards - 1}, twice * {n_shards} div (2 * {total})) as int)").alias("shard"))
    )
    first = dealt.groupBy("shard").agg(F.min("index").alias("first"))
    return dealt.join(F.broadcast(first), "shard").select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit(balance).alias("law"),
        "shard",
        (F.col("index") - F.col("first")).cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )
