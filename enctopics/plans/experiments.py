"""The experiments: each gives a table of what was measured."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.util import inheritable_thread_target

from enctopics.config import Config
from enctopics.functions.statistics import student_quantile
from enctopics.operators import baselines, centres, index, kestimate, metrics, relate, search, tokens, vectors
from enctopics.plans import batch, static
from enctopics.session import kept
from enctopics.streaming import stream

#: Samplings, or clusterings, whose jobs are on their way at once.
AT_ONCE = 5
#: The worked example, a row a token, a column a document.
EXAMPLE = {"Book": (30, 0, 23, 4, 40, 0), "Solve": (5, 0, 0, 60, 34, 0), "Traffic": (0, 23, 0, 30, 0, 0), "Net": (52, 49, 0, 23, 0, 26), "Enter": (0, 45, 68, 0, 3, 5)}


def at_once(spark: SparkSession, run: Callable, of: Iterable) -> list:
    """run of each, in order: many small jobs that wait for nothing of each other."""
    with ThreadPoolExecutor(AT_ONCE) as pool:
        return list(pool.map(inheritable_thread_target(spark)(run), of))


def worked_example(spark: SparkSession) -> DataFrame:
    """Its postings."""
    return spark.createDataFrame([(t, i + 1, f) for t, row in EXAMPLE.items() for i, f in enumerate(row) if f], "tok string, doc_id long, f long")


def k_by_corpus(corpora: dict[str, DataFrame], cfg: Config = Config()) -> DataFrame:
    """corpus, m, trace, k."""
    out = None
    for name, docs in corpora.items():
        row = kestimate.estimate_k(kestimate.trim(tokens.keywords(docs, cfg.keywords_per_doc), cfg.trim)).select(F.lit(name).alias("corpus"), "m", "trace", "k")
        out = row if out is None else out.unionByName(row)
    return out


def labelled(clusters: DataFrame, vecs: DataFrame) -> DataFrame:
    """id, label, vec of the tokens that have a cluster and a vector."""
    return clusters.where("cluster_id >= 0").join(vecs, "tok").select(F.col("tok").alias("id"), F.col("cluster_id").alias("label"), "vec")


def one_shot(made: static.Clustering, cfg: Config = Config()) -> dict[str, DataFrame]:
    """Clusters of the schemes that have a number of clusters of their own."""
    a = made.trimmed
    return {"static": made.clusters, "prior_encrypted": relate.distribute(relate.cooccurrence(a, made.centres), made.centres, a, score="co"), "fixed_ten": baselines.fixed_k(a, cfg.fixed_k)}


def iterative(made: static.Clustering, vecs: DataFrame, words: DataFrame, k: int) -> dict[str, DataFrame]:
    """Clusters of the schemes that take any number; words: word vectors, vecs: profiles."""
    return {"vector_kmeans": baselines.vector_kmeans(words, k), "hierarchical": baselines.hierarchical(vecs, k), "taxonomy": baselines.taxonomy(made.trimmed, k)}


def measured(spark: SparkSession, found: list[tuple[str, int, DataFrame]], vecs: DataFrame) -> DataFrame:
    """scheme, k, sc, ci, di, coherency, weighted, clusters, orphans, largest for each clustering."""

    def row(one: tuple[str, int, DataFrame]) -> tuple:
        scheme, k, clusters = one[0], one[1], kept(one[2])
        v = kept(labelled(clusters, vecs))
        c, size = metrics.coherency(v).first(), metrics.cluster_sizes(clusters).first()
        return scheme, k, metrics.silhouette(v).first()[0], metrics.calinski_harabasz(v).first()[0], metrics.davies_bouldin(v).first()[0], c["coherency"], c["weighted"], size["clusters"], size["orphans"], size["largest"]

    return spark.createDataFrame(at_once(spark, row, found), "scheme string, k int, sc double, ci double, di double, coherency double, weighted double, clusters long, orphans long, largest long")


def sweep(spark: SparkSession, docs: DataFrame, grid: tuple[int, ...] = (10, 50, 100, 150, 200, 250), cfg: Config = Config()) -> DataFrame:
    """All quality measures, in the space of profiles, over numbers of clusters: iterative schemes at each, the others at their own."""
    made = static.cluster(docs, cfg)
    vecs = kept(vectors.hashed_profiles(made.trimmed))
    words = kept(vectors.word2vec(docs).join(made.trimmed.select("tok").distinct(), "tok", "left_semi"))
    found = [(n, made.k if n != "fixed_ten" else cfg.fixed_k, c) for n, c in one_shot(made, cfg).items()]
    for some in at_once(spark, lambda k: [(n, k, c) for n, c in iterative(made, vecs, words, k).items()], sorted({*grid, made.k})):
        found += some
    return measured(spark, found, vecs)


def coherency(spark: SparkSession, docs: DataFrame, cfg: Config = Config()) -> DataFrame:
    """All schemes at the estimated number of clusters, and the fixed ten at its own."""
    return sweep(spark, docs, (), cfg)


def ablations(spark: SparkSession, docs: DataFrame, cfg: Config = Config()) -> DataFrame:
    """What each part of the static scheme does: its centres, its relatedness, its treatment of uncovered tokens."""
    made = static.cluster(docs, cfg)
    a, vecs = made.trimmed, kept(vectors.hashed_profiles(made.trimmed))
    naive = kept(centres.by_document_count(index.token_stats(a), made.centres.count()))
    infinite = kept(centres.choose(a, made.k, kestimate.separation(a), cfg.inclusive, "infinite"))
    go = lambda c, how: relate.distribute(relate.relatedness(a, c, how), c, a)
    count = lambda c: relate.distribute(relate.cooccurrence(a, c), c, a, score="co")
    found = {"static": made.clusters, "infinite_centres": go(infinite, "literal"), "no_disparity": go(made.centres, "off"), "symmetric": go(made.centres, "symmetric"), "by_count": count(made.centres), "naive_centres": go(naive, "literal"), "naive_by_count": count(naive)}
    return measured(spark, [(n, made.k, c) for n, c in found.items()], vecs)


def _searches(docs: DataFrame, benchmark: DataFrame, cfg: Config = Config()):
    made = static.cluster(docs, cfg)
    stats = kept(index.token_stats(made.trimmed))
    q = kept(search.benchmark_queries(benchmark, stats))
    fixed = kept(baselines.fixed_k(made.trimmed, cfg.fixed_k))
    from enctopics.operators import abstracts

    tops = kept(abstracts.build(fixed, stats, cfg.abstract_size))
    n = docs.count()
    sims = kept(vectors.doc_cosine(made.trimmed, q, made.abstracts.unionByName(tops)))
    return q, {
        "exhaustive": lambda: search.full(q, made.trimmed, n),
        "static": lambda: search.pruned(q, made.trimmed, made.clusters, made.abstracts, n, cfg.probed_clusters, sims=sims),
        "fixed_ten": lambda: search.pruned(q, made.trimmed, fixed, tops, n, cfg.probed_clusters, sims=sims),
    }


def search_relevance(corpora: dict[str, DataFrame], benchmark: DataFrame, cfg: Config = Config()) -> DataFrame:
    """corpus, scheme, query_id, tsap, n_relevant; a corpus with no passage of an item has no rows."""
    out = None
    for corpus, docs in corpora.items():
        _, ways = _searches(docs, benchmark, cfg)
        truth = kept(search.relevance(benchmark, docs))
        for name, run in ways.items():
            row = metrics.tsap(run(), truth, cfg.tsap_n).select(F.lit(corpus).alias("corpus"), F.lit(name).alias("scheme"), "query_id", "tsap", "n_relevant")
            out = row if out is None else out.unionByName(row)
    return out


def search_time(spark: SparkSession, corpora: dict[str, DataFrame], benchmark: DataFrame, cfg: Config = Config()) -> DataFrame:
    """corpus, scheme, runs, and least, quartiles and most of the milliseconds for the whole set of queries."""
    rows = []
    for corpus, docs in corpora.items():
        for name, run in _searches(docs, benchmark, cfg)[1].items():
            for i in range(cfg.runs):
                began = time.perf_counter()
                run().write.format("noop").mode("overwrite").save()
                rows.append((corpus, name, i, 1000 * (time.perf_counter() - began)))
    t = spark.createDataFrame(rows, "corpus string, scheme string, run int, ms double")
    part = lambda p: F.percentile("ms", p)
    return t.groupBy("corpus", "scheme").agg(F.count("*").alias("runs"), F.min("ms").alias("least"), part(0.25).alias("q1"), part(0.5).alias("median"), part(0.75).alias("q3"), F.max("ms").alias("most"))


def _coherency_of(state: batch.State) -> float:
    got = metrics.profile_coherency(state.clustering.clusters, state.clustering.postings).first()["coherency"]
    return float("nan") if got is None else got


def updates(spark: SparkSession, deal, samplings: int = 10, cfg: Config = Config(unit=10.0)) -> DataFrame:
    """seed, batch_id, recluster, with_reclustering, without: coherency after each batch of each sampling.

    deal(seed) gives postings with batch_id 0 to 5. Until the clusters are first made anew, both arms are one. Samplings
    run AT_ONCE at a time.
    """

    def sampled(seed: int) -> list[tuple]:
        pb = kept(deal(seed))
        one = lambda i: kept(pb.where(F.col("batch_id") == i).select("tok", "doc_id", "f"))
        a = b = batch.start(one(0), cfg)
        rows = []
        for i in range(1, 6):
            temp, same = one(i), a is b
            after = batch.step(a, temp, cfg)
            again = bool(after.log[-1][-1])
            b = after if same and not again else batch.step(b, temp, cfg, allow_recluster=False)
            a = after
            mine = _coherency_of(a)
            rows.append((seed, i, again, mine, mine if a is b else _coherency_of(b)))
        return rows

    found = [r for rows in at_once(spark, sampled, range(samplings)) for r in rows]
    return spark.createDataFrame(found, "seed int, batch_id int, recluster boolean, with_reclustering double, without double")


def stream_replay(spark: SparkSession, docs: DataFrame, folder: str, cfg: Config = Config()) -> DataFrame:
    """version, streamed, batched, differing: documents come one a file; tokens with a cluster after each under the stream
    scheme and under the batch scheme with batches of the same documents, and rows that only one of them has. Every version is gone
    through in turn, as the scheme does: for small corpora."""
    ids = [r.doc_id for r in docs.select("doc_id").distinct().orderBy("doc_id").toLocalIterator()]
    for i in ids:
        docs.where(F.col("doc_id") == i).coalesce(1).write.mode("append").parquet(f"{folder}/in")
    versions = stream.run(spark, f"{folder}/in", f"{folder}/state", f"{folder}/marks", cfg)
    rows, state, seen = [], None, None
    for v in range(len(ids)):
        now = versions.read("postings", v)
        came = now if seen is None else now.join(seen.select("doc_id").distinct(), "doc_id", "left_anti")
        whole = docs.join(kept(came.select("doc_id").distinct()), "doc_id", "left_semi")
        temp = kept(tokens.keywords(whole, cfg.keywords_per_doc, score="tf", min_df=1))
        state = stream.first_state(temp, cfg) if state is None else batch.step(state, temp, cfg)
        a, b = versions.read("clusters", v).select("tok", "cluster_id"), state.clustering.clusters.select("tok", "cluster_id")
        rows.append((v, a.count(), b.count(), a.exceptAll(b).count() + b.exceptAll(a).count()))
        seen = now
    return spark.createDataFrame(rows, "version int, streamed long, batched long, differing long")


def interval(df: DataFrame, by: str | tuple[str, ...], value: str, n: int, confidence: float = 0.95) -> DataFrame:
    """Mean and half width of the confidence interval of n values a group."""
    t = student_quantile(n - 1, confidence) if n > 1 else math.nan
    return df.groupBy(*([by] if isinstance(by, str) else by)).agg(F.count(value).alias("n"), F.round(F.avg(value), 6).alias("mean"), F.round(F.lit(t) * F.stddev_samp(value) / F.sqrt(F.count(value)), 6).alias("half_width"))


def index_growth(docs: DataFrame, shares: tuple[float, ...] = (0.25, 0.5, 0.75, 1.0), cfg: Config = Config()) -> DataFrame:
    """share, docs, tokens, postings: the index of the first documents by a hash of their ids."""
    p = kept(tokens.keywords(docs, cfg.keywords_per_doc))
    place = F.pmod(F.xxhash64("doc_id"), F.lit(10_000)) / 10_000
    marked = p.withColumn("at", place).withColumn("share", F.explode(F.array(*map(F.lit, shares)))).where(F.col("at") < F.col("share"))
    return marked.groupBy("share").agg(F.countDistinct("doc_id").alias("docs"), F.countDistinct("tok").alias("tokens"), F.count("*").alias("postings"))
