"""The static scheme from documents to clusters."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame

from enctopics.config import Config
from enctopics.operators import abstracts, centres, index, kestimate, relate, tokens
from enctopics.session import kept


@dataclass(frozen=True)
class Clustering:
    postings: DataFrame  # all of the index
    trimmed: DataFrame  # what was clustered
    k: int
    centres: DataFrame
    clusters: DataFrame
    abstracts: DataFrame


def cluster_index(postings: DataFrame, cfg: Config = Config(), naive: bool = False) -> Clustering:
    trimmed = kept(kestimate.trim(postings, cfg.trim))
    k = kestimate.estimate_k(trimmed).first()["k"] or 0
    stats = index.token_stats(trimmed)
    if naive:
        c = kept(centres.by_document_count(stats, k))
    else:
        c = kept(centres.choose(trimmed, k, kestimate.separation(trimmed), cfg.inclusive, cfg.zero_overlap))
    edges = relate.relatedness(trimmed, c, cfg.disparity)
    clusters = kept(relate.distribute(edges, c, trimmed, cfg.orphan))
    return Clustering(postings, trimmed, k, c, clusters, kept(abstracts.build(clusters, stats, cfg.abstract_size)))


def cluster(docs: DataFrame, cfg: Config = Config()) -> Clustering:
    return cluster_index(kept(tokens.keywords(docs, cfg.keywords_per_doc)), cfg)
