"""The index from tokens to documents: long postings, or one row a token."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.functions import crypto
from enctopics.operators import tokens


def encrypt(postings: DataFrame, key: str) -> DataFrame:
    """tok becomes its handle; distinct tokens are hashed where they stand, in generated code."""
    return postings.select(crypto.handle(F.col("tok"), key).alias("handle"), "doc_id", "f")


def build(postings: DataFrame) -> DataFrame:
    """tok, entries: its documents and frequencies, in order."""
    return postings.groupBy("tok").agg(F.sort_array(F.collect_list(F.struct("doc_id", "f"))).alias("entries"))


def flatten(grouped: DataFrame) -> DataFrame:
    return grouped.select("tok", F.inline("entries"))


def temporary(docs: DataFrame, batch_id: int, n: int = 10, min_df: int = 1) -> DataFrame:
    """Postings of one batch, with its number."""
    return tokens.keywords(docs, n, min_df=min_df).withColumn("batch_id", F.lit(batch_id))


def merge(central: DataFrame, temp: DataFrame) -> DataFrame:
    columns = ["tok", "doc_id", "f"]
    return central.select(columns).unionByName(temp.select(columns)).groupBy("tok", "doc_id").agg(F.sum("f").alias("f"))


def remove(central: DataFrame, ids: DataFrame) -> DataFrame:
    return central.join(ids.select("doc_id").distinct(), "doc_id", "left_anti")


def new_tokens(temp: DataFrame, central: DataFrame) -> DataFrame:
    return temp.select("tok").distinct().join(central.select("tok").distinct(), "tok", "left_anti")


def token_stats(postings: DataFrame) -> DataFrame:
    f = F.col("f")
    return postings.groupBy("tok").agg(F.count("*").alias("df"), F.sum(f).alias("tf"), F.sum(f * f).alias("tf2"))
