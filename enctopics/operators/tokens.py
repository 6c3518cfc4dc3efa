"""Tokens, phrases and keywords of documents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def token_array(text: Column, min_len: int = 3) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(rf"\p{{L}}{{{min_len},}}"), F.lit(0))


def tokenize(docs: DataFrame, min_len: int = 3, stop: list[str] | None = None) -> DataFrame:
    """doc_id, tok: every occurrence."""
    out = docs.select("doc_id", F.explode(token_array(F.col("text"), min_len)).alias("tok"))
    return out.where(~F.col("tok").isin(stop)) if stop else out


def phrases(docs: DataFrame, n: int = 2, min_len: int = 3) -> DataFrame:
    """doc_id, tok: every run of n tokens."""
    rows = docs.select("doc_id", token_array(F.col("text"), min_len).alias("ts"))
    runs = F.transform(F.sequence(F.lit(1), F.size("ts") - n + 1), lambda i: F.array_join(F.slice("ts", i, F.lit(n)), " "))
    return rows.where(F.size("ts") >= n).select("doc_id", F.explode(runs).alias("tok"))


def frequencies(occurrences: DataFrame) -> DataFrame:
    return occurrences.groupBy("doc_id", "tok").agg(F.count("*").alias("f"))


def tfidf() -> Column:
    """Of f, df and total."""
    return F.round(F.col("f") * F.log(F.col("total") / F.col("df")), 6)


def best(scored: DataFrame, worth: Column, n: int) -> DataFrame:
    """The n rows of each document that are worth most; ties by token."""
    order = Window.partitionBy("doc_id").orderBy(F.desc("worth"), "tok")
    return scored.withColumn("worth", worth).withColumn("rk", F.row_number().over(order)).where(F.col("rk") <= n)


def keywords(docs: DataFrame, n: int = 10, score: str = "tfidf", min_df: int = 2) -> DataFrame:
    """tok, doc_id, f: the n best tokens of each document, by tf-idf, tf, or first position; ties by token."""
    if score == "position":
        rows = docs.select("doc_id", F.posexplode(token_array(F.col("text"))).alias("at", "tok"))
        tf = rows.groupBy("doc_id", "tok").agg(F.count("*").alias("f"), F.min("at").alias("at"))
        worth = -F.col("at")
    else:
        tf = frequencies(tokenize(docs))
        worth = F.col("f").cast("double")
    df = tf.groupBy("tok").agg(F.count("*").alias("df")).where(F.col("df") >= min_df)
    scored = tf.join(df, "tok")
    if score == "tfidf":
        total = docs.agg(F.count("*").cast("double").alias("total"))
        scored = scored.crossJoin(F.broadcast(total))
        worth = tfidf()
    return best(scored, worth, n).select("tok", "doc_id", "f")
