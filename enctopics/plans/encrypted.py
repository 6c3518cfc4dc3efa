"""The static scheme as it is meant to run: the cloud sees handles and envelopes, the edge holds the key.

The edge takes keywords from documents and sends handles with their counts, and an envelope for each handle. The cloud
clusters handles and returns the most frequent ones of each cluster; the edge opens their envelopes and keeps the
abstracts in plain. A query is routed at the edge, and leaves it as handles and clusters.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.config import Config
from enctopics.functions import crypto
from enctopics.operators import abstracts, index, search, tokens, vectors
from enctopics.plans import static
from enctopics.schemas import require_cloud
from enctopics.session import kept


@dataclass(frozen=True)
class Cloud:
    index: DataFrame  # handle, doc_id, f
    names: DataFrame  # handle, sealed


def upload(postings: DataFrame, key: str) -> Cloud:
    """What leaves the edge; both tables are checked for columns that may hold plain text."""
    rows = require_cloud(index.encrypt(postings, key))
    names = postings.select("tok").distinct().select(crypto.handle(F.col("tok"), key).alias("handle"), crypto.seal(F.col("tok"), key).alias("sealed"))
    return Cloud(kept(rows), kept(require_cloud(names)))


def cluster(cloud: Cloud, cfg: Config = Config()) -> static.Clustering:
    """The clusters of the handles, which stand where tokens stand in the operators."""
    return static.cluster_index(cloud.index.withColumnRenamed("handle", "tok"), cfg)


def revealed(made: static.Clustering, cloud: Cloud, key: str) -> DataFrame:
    """The abstracts in plain: cluster_id, tok, f, rank. Clusters times their size envelopes are opened, at the edge."""
    sealed = made.abstracts.withColumnRenamed("tok", "handle").join(cloud.names, "handle").drop("handle")
    return abstracts.reveal(sealed, key).select("cluster_id", "tok", "f", "rank")


def add(cloud: Cloud, placed: DataFrame, key: str) -> DataFrame:
    """New tokens (tok, cluster_id) that the edge has placed, as what it pushes: handle, sealed, cluster_id."""
    return require_cloud(placed.select(crypto.handle(F.col("tok"), key).alias("handle"), crypto.seal(F.col("tok"), key).alias("sealed"), "cluster_id"))


def ask(queries: DataFrame, key: str) -> DataFrame:
    """query_id, tok: the handles of a query's tokens."""
    return queries.select("query_id", crypto.handle(F.col("tok"), key).alias("tok"))


def routes(queries: DataFrame, tops: DataFrame, postings: DataFrame, cfg: Config = Config()) -> DataFrame:
    """query_id, cluster_id: decided at the edge, by what its own documents say of its plain tokens."""
    sims = vectors.doc_cosine(postings, queries, tops)
    return search.route(search.score_abstracts(queries, tops, sims), cfg.probed_clusters)


def run(docs: DataFrame, cfg: Config = Config()) -> tuple[DataFrame, Cloud, static.Clustering]:
    """The edge's postings, the cloud's tables and the clusters."""
    postings = kept(tokens.keywords(docs, cfg.keywords_per_doc))
    cloud = upload(postings, cfg.key)
    return postings, cloud, cluster(cloud, cfg)
