"""Tables, and what else can be read as documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_files(spark: SparkSession, path: str) -> DataFrame:
    """One document a file; its id is a hash of its path."""
    files = spark.read.text(path, wholetext=True)
    return files.select(F.xxhash64(F.col("_metadata.file_path")).alias("doc_id"), F.col("value").alias("text"))


def json_lines(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("doc_id long, text string").json(path)


def csv(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("doc_id long, text string").csv(path, header=True, multiLine=True, escape='"')


def page_text(pages: DataFrame) -> DataFrame:
    """Pages as documents: scripts, styles and tags out, the common entities read, blanks put together."""
    text = F.regexp_replace("html", r"(?is)<(script|style)\b.*?</(script|style)>", " ")
    text = F.regexp_replace(text, r"(?s)<[^>]*>", " ")
    for entity, sign in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        text = F.replace(text, F.lit(entity), F.lit(sign))
    return pages.select(F.col("page_id").alias("doc_id"), F.trim(F.regexp_replace(text, r"\s+", " ")).alias("text"))


def conversation_docs(turns: DataFrame) -> DataFrame:
    """A document a conversation, its turns in order."""
    said = F.sort_array(F.collect_list(F.struct("turn", "text")))
    return turns.groupBy("conv_id").agg(said.alias("said")).select(F.col("conv_id").alias("doc_id"), F.array_join(F.col("said.text"), "\n").alias("text"))
