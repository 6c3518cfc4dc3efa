"""Types of the tables between operators, and which side of the trust boundary may hold them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

POSTINGS = T.StructType([T.StructField("tok", T.StringType()), T.StructField("doc_id", T.LongType()), T.StructField("f", T.LongType())])
CLUSTERS = T.StructType([T.StructField("cluster_id", T.IntegerType()), T.StructField("tok", T.StringType()), T.StructField("is_centre", T.BooleanType())])
ABSTRACTS = T.StructType([T.StructField("cluster_id", T.IntegerType()), T.StructField("tok", T.StringType()), T.StructField("f", T.LongType()), T.StructField("rank", T.IntegerType())])

#: Columns that a table in the cloud may have: handles, ids, counts and scores, never a plain token.
CLOUD = {"handle", "sealed", "doc_id", "f", "df", "tf", "tf2", "cluster_id", "is_centre", "q", "phi", "new_docs", "seen_docs", "rank", "entries", "r"}


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df with just the columns of schema; an error at once if one is missing or of another kind."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if have.get(f.name) != f.dataType:
            raise TypeError(f"{f.name} should be {f.dataType.simpleString()}, not {have.get(f.name)}")
    return df.select(*schema.names)


def require_cloud(df: DataFrame) -> DataFrame:
    """df, if none of its columns may hold plain text."""
    if plain := [c for c in df.columns if c not in CLOUD]:
        raise ValueError(f"not for the cloud: {plain}")
    return df
