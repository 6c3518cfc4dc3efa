"""How many clusters a corpus needs: the trace of the token-to-token similarity, without that matrix.

With v a frequency over its document's largest, r = v / (sum of v of the token) and s = v / (sum of v of the
document), a token's separation is the sum of r * s over its documents. The document's largest cancels in s, and the
token's sum can be taken out: separation = sum(v * s) / sum(v). So one window over documents, which hold few
keywords, and one sum by token, combined before its shuffle, give all separations.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def trim(postings: DataFrame, how: str | int = "mean") -> DataFrame:
    """Postings of tokens in at least the mean number of documents, or in at least so many, or of all."""
    if how == "none":
        return postings
    stats = postings.groupBy("tok").agg(F.count("*").alias("df"))
    if how == "mean":
        whole = stats.agg(F.count("*").alias("m"), F.sum("df").alias("total"))
        keep = stats.crossJoin(F.broadcast(whole)).where(F.col("df") * F.col("m") >= F.col("total"))
    else:
        keep = stats.where(F.col("df") >= int(how))
    return postings.join(keep.select("tok"), "tok", "left_semi")


def frequency_matrix(postings: DataFrame) -> DataFrame:
    return postings.select("tok", "doc_id", "f")


def as_pivot(matrix: DataFrame, doc_ids: list[int]) -> DataFrame:
    """A dense picture of a small matrix."""
    return matrix.groupBy("tok").pivot("doc_id", doc_ids).agg(F.sum("f")).na.fill(0)


def normalise(matrix: DataFrame) -> DataFrame:
    """Frequencies over the largest of their document."""
    return matrix.withColumn("n", F.col("f") / F.max("f").over(Window.partitionBy("doc_id")))


def token_importance(normal: DataFrame) -> DataFrame:
    """r: a document's share of a token. Sums are joined and not windowed, as a token may be in very many documents."""
    sums = normal.groupBy("tok").agg(F.sum("n").alias("total"))
    return normal.join(sums, "tok").withColumn("r", F.col("n") / F.col("total")).drop("total")


def document_importance(matrix: DataFrame) -> DataFrame:
    """s: a token's share of a document."""
    return matrix.withColumn("s", F.col("f") / F.sum("f").over(Window.partitionBy("doc_id")))


def topic_similarity(postings: DataFrame, min_q: float = 0.0) -> DataFrame:
    """tok, other, q: the whole matrix, on request; as many rows as there are pairs inside documents."""
    r = token_importance(normalise(postings)).select("tok", "doc_id", "r")
    s = document_importance(postings).select(F.col("tok").alias("other"), "doc_id", "s")
    return r.join(s, "doc_id").groupBy("tok", "other").agg(F.sum(F.col("r") * F.col("s")).alias("q")).where(F.col("q") > min_q)


def separation(postings: DataFrame, group: list[str] | None = None) -> DataFrame:
    """tok, q, by group if one is named."""
    group = group or []
    doc = Window.partitionBy(*group, "doc_id")
    v, s = F.col("f") / F.max("f").over(doc), F.col("f") / F.sum("f").over(doc)
    return postings.select(*group, "tok", v.alias("v"), s.alias("s")).groupBy(*group, "tok").agg((F.sum(F.col("v") * F.col("s")) / F.sum("v")).alias("q"))


def shared_similarity(separations: DataFrame) -> DataFrame:
    return separations.withColumn("shared", 1 - F.col("q"))


def _ceiled(trace):
    return F.ceil(trace - 1e-9).cast("long")


def estimate_k(postings: DataFrame) -> DataFrame:
    """One row: m tokens, trace, k."""
    trace = F.coalesce(F.sum("q"), F.lit(0.0))
    return separation(postings).agg(F.count("*").alias("m"), F.round(trace, 6).alias("trace"), _ceiled(trace).alias("k"))


def estimate_k_by(postings: DataFrame, group: str) -> DataFrame:
    trace = F.sum("q")
    return separation(postings, [group]).groupBy(group).agg(F.count("*").alias("m"), F.round(trace, 6).alias("trace"), _ceiled(trace).alias("k"))


def bounds(k: int, m: int) -> bool:
    """Whether k is possible for m tokens."""
    return (m == 0 and k == 0) or 1 <= k <= m
