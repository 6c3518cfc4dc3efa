"""Search over the whole index, or over the clusters whose abstracts resemble the query."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from enctopics.operators.tokens import token_array


def benchmark_queries(benchmark: DataFrame, stats: DataFrame, n: int = 3) -> DataFrame:
    """query_id, tok: the n rarest indexed tokens of each benchmark item."""
    toks = benchmark.select(F.col("item_id").alias("query_id"), F.explode(F.array_distinct(token_array(F.col("text")))).alias("tok"))
    order = Window.partitionBy("query_id").orderBy("df", "tok")
    return toks.join(stats.select("tok", "df"), "tok").withColumn("rk", F.row_number().over(order)).where(F.col("rk") <= n).select("query_id", "tok")


def _scored(queries: DataFrame, postings: DataFrame, docs: int, stats: DataFrame | None = None) -> DataFrame:
    df = postings.groupBy("tok").agg(F.count("*").alias("df")) if stats is None else stats.select("tok", "df")
    hits = queries.join(df, "tok").join(postings, "tok")
    return hits.groupBy("query_id", "doc_id").agg(F.round(F.sum(F.col("f") * F.log(F.lit(float(docs)) / F.col("df"))), 6).alias("score"), F.count("*").alias("hits"))


def top(scored: DataFrame, k: int = 10) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "doc_id")
    return scored.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "doc_id", "score", "rank")


def full(queries: DataFrame, postings: DataFrame, docs: int, k: int = 10, stats: DataFrame | None = None) -> DataFrame:
    """query_id, doc_id, score, rank over the whole index; stats (tok, df) spare the count over all of it."""
    return top(_scored(queries, postings, docs, stats), k)


def from_store(queries: DataFrame, store: DataFrame, routed: DataFrame, stats: DataFrame, docs: int, k: int = 10) -> DataFrame:
    """As pruned(), on postings stored by cluster (cluster_id, tok, doc_id, f) of which store holds the routed clusters.

    Frequencies come from stats, so that nothing but the routed clusters is read.
    """
    hits = queries.join(routed, "query_id").join(store, ["cluster_id", "tok"]).join(stats.select("tok", "df"), "tok")
    score = F.round(F.sum(F.col("f") * F.log(F.lit(float(docs)) / F.col("df"))), 6)
    return top(hits.groupBy("query_id", "doc_id").agg(score.alias("score"), F.count("*").alias("hits")), k)


def score_abstracts(queries: DataFrame, abstracts: DataFrame, sims: DataFrame | None = None) -> DataFrame:
    """query_id, cluster_id, score: the mean of each query token's best similarity to an abstract's tokens.

    sims (a, b, sim) gives similarities of query tokens and abstract tokens; equal tokens have 1.
    """
    size = queries.groupBy("query_id").agg(F.count("*").alias("n"))
    same = queries.join(abstracts, "tok").select("query_id", "cluster_id", "tok", F.lit(1.0).alias("sim"))
    if sims is not None:
        near = queries.join(sims, F.col("tok") == F.col("a")).join(abstracts.select("cluster_id", F.col("tok").alias("b")), "b")
        same = same.unionByName(near.select("query_id", "cluster_id", "tok", "sim"))
    best = same.groupBy("query_id", "cluster_id", "tok").agg(F.max("sim").alias("sim"))
    return best.groupBy("query_id", "cluster_id").agg(F.sum("sim").alias("sum")).join(size, "query_id").select("query_id", "cluster_id", (F.col("sum") / F.col("n")).alias("score"))


def jaccard_abstracts(queries: DataFrame, abstracts: DataFrame) -> DataFrame:
    """query_id, cluster_id, score: shared tokens over all tokens of the two."""
    nq, na = queries.groupBy("query_id").agg(F.count("*").alias("nq")), abstracts.groupBy("cluster_id").agg(F.count("*").alias("na"))
    both = queries.join(abstracts, "tok").groupBy("query_id", "cluster_id").agg(F.count("*").alias("both"))
    return both.join(nq, "query_id").join(na, "cluster_id").select("query_id", "cluster_id", F.round(F.col("both") / (F.col("nq") + F.col("na") - F.col("both")), 6).alias("score"))


def route(scores: DataFrame, c: int = 3) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc(F.round("score", 9)), "cluster_id")
    return scores.withColumn("rk", F.row_number().over(order)).where(F.col("rk") <= c).select("query_id", "cluster_id")


def expand(queries: DataFrame, sims: DataFrame, top_n: int = 3) -> DataFrame:
    """query_id, tok: the query's tokens and the top_n most similar tokens of each."""
    order = Window.partitionBy("a").orderBy(F.desc("sim"), "b")
    more = sims.where("a <> b").withColumn("rk", F.row_number().over(order)).where(F.col("rk") <= top_n)
    return queries.unionByName(queries.join(more, F.col("tok") == F.col("a")).select("query_id", F.col("b").alias("tok"))).distinct()


def pruned(queries: DataFrame, postings: DataFrame, clusters: DataFrame, abstracts: DataFrame, docs: int, c: int = 3, k: int = 10, sims: DataFrame | None = None, stats: DataFrame | None = None) -> DataFrame:
    """As full(), over the routed clusters of each query only."""
    routed = route(score_abstracts(queries, abstracts, sims), c)
    inside = queries.join(clusters.select("tok", "cluster_id"), "tok").join(routed, ["query_id", "cluster_id"], "left_semi").select("query_id", "tok")
    return full(inside, postings, docs, k, stats)


def cost(queries: DataFrame, postings: DataFrame, clusters: DataFrame | None = None, routed: DataFrame | None = None) -> DataFrame:
    """query_id, visited, docs_scored, share: postings that a search goes through, of the index or of the routed clusters."""
    hits = queries.join(postings, "tok")
    if routed is not None:
        hits = hits.join(clusters.select("tok", "cluster_id"), "tok").join(routed, ["query_id", "cluster_id"], "left_semi")
        visited = routed.join(clusters, "cluster_id").join(postings, "tok").groupBy("query_id").agg(F.count("*").alias("visited"))
    else:
        visited = queries.select("query_id").distinct().crossJoin(F.broadcast(postings.agg(F.count("*").alias("visited"))))
    scored = hits.groupBy("query_id").agg(F.countDistinct("doc_id").alias("docs_scored"))
    total = postings.agg(F.count("*").alias("total"))
    return visited.join(scored, "query_id", "left").crossJoin(F.broadcast(total)).select("query_id", "visited", F.coalesce("docs_scored", F.lit(0)).alias("docs_scored"), F.round(F.col("visited") / F.col("total"), 6).alias("share"))


def relevance(benchmark: DataFrame, docs: DataFrame, at: int = 20, width: int = 60) -> DataFrame:
    """query_id, doc_id: documents that hold an item's passage, the width characters from at.

    Three tokens that lie wholly inside the passage find the documents worth a look; no text is compared with all items.
    """
    items = benchmark.select(F.col("item_id").alias("query_id"), F.substring("text", at + 1, width).alias("w")).where(F.length("w") == width)
    inner = token_array(F.regexp_replace(F.regexp_replace("w", r"^\p{L}+", ""), r"\p{L}+$", ""))
    asked = items.select("query_id", "w", F.xxhash64(F.slice(inner, 1, 3)).alias("key"), F.size(inner).alias("n")).where("n >= 3").drop("n")
    toks = docs.select("doc_id", "text", token_array(F.col("text")).alias("ts"))
    keys = F.transform(F.sequence(F.lit(1), F.greatest(F.size("ts") - 2, F.lit(1))), lambda i: F.xxhash64(F.slice("ts", i, F.lit(3))))
    found = toks.select("doc_id", F.explode(F.array_distinct(keys)).alias("key")).join(F.broadcast(asked), "key").select("doc_id", "query_id", "w")
    return found.join(docs.select("doc_id", "text"), "doc_id").where(F.contains("text", "w")).select("query_id", "doc_id").distinct()
