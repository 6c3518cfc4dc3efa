"""Queries of the experiments; what they measure is described in plans.experiments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from enctopics.config import Config
from enctopics.operators import kestimate, tokens
from enctopics.plans import experiments as x
from enctopics.queries_core import arrived, batches
from enctopics.registry import query
from enctopics.session import kept
from enctopics.sources.tables import conversation_docs, page_text, table

#: The six smallest documents by id, and of their tokens the five that are most frequent there.
_EX = r"""six AS (SELECT doc_id, text FROM documents ORDER BY doc_id LIMIT 6), o AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '\p{L}{3,}')) AS tok FROM six),
    g AS (SELECT tok, doc_id, count(*) AS f FROM o GROUP BY tok, doc_id), five AS (SELECT tok FROM g GROUP BY tok ORDER BY sum(f) DESC, tok LIMIT 5), a AS (SELECT tok, doc_id, f FROM g SEMI JOIN five USING (tok))"""


@query("worked_example", f"WITH {_EX}, n AS (SELECT tok, doc_id, f / max(f) OVER (PARTITION BY doc_id) AS n FROM a), rs AS (SELECT tok, doc_id, n / sum(n) OVER (PARTITION BY tok) AS r, n / sum(n) OVER (PARTITION BY doc_id) AS s FROM n) SELECT x.tok, y.tok AS other, round(sum(x.r * y.s), 6) AS q FROM rs x JOIN rs y USING (doc_id) GROUP BY x.tok, y.tok")
def worked_example(spark: SparkSession, d: str) -> DataFrame:
    """The matrix of the five most frequent tokens of the six documents with the least ids; the printed example is in the tests."""
    six = table(spark, d, "documents").orderBy("doc_id").limit(6)
    found = tokens.frequencies(tokens.tokenize(six))
    five = found.groupBy("tok").agg(F.sum("f").alias("n")).orderBy(F.desc("n"), "tok").limit(5)
    return kestimate.topic_similarity(found.join(five, "tok", "left_semi")).withColumn("q", F.round("q", 6))


@query("exp_k_by_corpus")
def k_by_corpus(spark: SparkSession, d: str) -> DataFrame:
    docs = table(spark, d, "documents")
    corpora = {lang: docs.where(F.col("lang") == lang) for lang in ("de", "en", "es", "fr")}
    return x.k_by_corpus({"documents": docs, **corpora, "conversations": conversation_docs(table(spark, d, "conversations")), "pages": page_text(table(spark, d, "pages"))})


@query("exp_sweep")
def sweep(spark: SparkSession, d: str) -> DataFrame:
    return x.sweep(spark, table(spark, d, "documents"))


@query("exp_coherency")
def coherency(spark: SparkSession, d: str) -> DataFrame:
    return x.coherency(spark, table(spark, d, "documents"))


@query("exp_ablations")
def ablations(spark: SparkSession, d: str) -> DataFrame:
    return x.ablations(spark, table(spark, d, "documents"))


def _corpora(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    return {"documents": table(spark, d, "documents"), "conversations": conversation_docs(table(spark, d, "conversations")), "pages": page_text(table(spark, d, "pages"))}


@query("exp_search_relevance")
def search_relevance(spark: SparkSession, d: str) -> DataFrame:
    return x.search_relevance(_corpora(spark, d), table(spark, d, "benchmark"))


@query("search_time_boxes")
def search_time_boxes(spark: SparkSession, d: str) -> DataFrame:
    return _times(spark, d, "documents")


@query("search_time_boxes_conversations")
def search_time_boxes_conversations(spark: SparkSession, d: str) -> DataFrame:
    return _times(spark, d, "conversations")


@query("search_time_boxes_pages")
def search_time_boxes_pages(spark: SparkSession, d: str) -> DataFrame:
    return _times(spark, d, "pages")


def _times(spark: SparkSession, d: str, corpus: str) -> DataFrame:
    return x.search_time(spark, {corpus: _corpora(spark, d)[corpus]}, table(spark, d, "benchmark"))


def _deal(spark: SparkSession, d: str):
    """Postings of a sampling; texts are tokenized once, and what is dealt out by each sampling is ids."""
    docs = table(spark, d, "documents")
    found = kept(tokens.frequencies(tokens.tokenize(docs)))
    return lambda seed: arrived(kept(batches(docs.select("doc_id"), seed)), found=found)


@query("exp_updates")
def updates(spark: SparkSession, d: str) -> DataFrame:
    return x.updates(spark, _deal(spark, d))


@query("coherency_ci")
def coherency_ci(spark: SparkSession, d: str) -> DataFrame:
    """Mean and interval after each batch, with re-clustering and without, over the samplings of exp_updates."""
    runs = x.updates(spark, _deal(spark, d))
    return x.interval(runs.unpivot(["batch_id"], ["with_reclustering", "without"], "scheme", "coherency"), ("batch_id", "scheme"), "coherency", Config.samplings)


@query("exp_index_growth")
def index_growth(spark: SparkSession, d: str) -> DataFrame:
    return x.index_growth(table(spark, d, "documents"))
