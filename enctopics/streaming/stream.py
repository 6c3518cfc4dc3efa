"""The stream scheme: documents that arrive as files, a state version for each micro-batch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from enctopics.config import Config
from enctopics.operators import dynamic, index, kestimate, tokens, vectors
from enctopics.plans import batch
from enctopics.plans.static import Clustering
from enctopics.session import kept
from enctopics.sources.sinks import Versions


#: At a threshold of 0.1 the noise of profiles has to be far less.
COLD_DIMS = 1024


def cold_start(postings: DataFrame, theta: float = 0.1, cfg: Config = Config()) -> DataFrame:
    """tok, cluster_id, sim, founded: tokens by falling frequency join the nearest founder beyond theta, or found."""
    stats = index.token_stats(postings)
    rows = stats.join(vectors.hashed_cells(postings, COLD_DIMS), "tok").select("tok", F.col("tf").alias("f"), "at", "x")
    none = rows.select(F.lit(0).cast("long").alias("cluster_id"), "tok", "at", "x").limit(0)
    return dynamic.attach(rows, none, theta)


def first_state(postings: DataFrame, cfg: Config = Config()) -> batch.State:
    from enctopics.operators import abstracts

    placed = kept(cold_start(postings, cfg.theta_initial, cfg))
    clusters = kept(placed.select("tok", F.col("cluster_id").cast("int").alias("cluster_id"), F.col("founded").alias("is_centre")))
    stats = index.token_stats(postings)
    centres = clusters.where("is_centre").select(F.col("cluster_id").alias("rank"), "tok")
    made = Clustering(postings, kestimate.trim(postings, "none"), clusters.where("is_centre").count(), centres, clusters, kept(abstracts.build(clusters, stats, cfg.abstract_size)))
    return batch.State(made, 0, stats.count())


def run(spark: SparkSession, source: str, state: str, checkpoint: str, cfg: Config = Config(), files_per_trigger: int = 1) -> Versions:
    """Reads Parquet files of documents as they come, until none is left; a version is written again if its batch is."""
    versions = Versions(spark, state)
    docs = spark.readStream.schema("doc_id long, text string").option("maxFilesPerTrigger", files_per_trigger).parquet(source)

    def arrived(df: DataFrame, batch_id: int) -> None:
        temp = kept(tokens.keywords(df, cfg.keywords_per_doc, score="tf", min_df=1))
        last = batch_id - 1 if batch_id else None
        if last is None:
            now = first_state(temp, cfg)
        else:
            c = Clustering(versions.read("postings", last), versions.read("postings", last), 0, versions.read("clusters", last).where("is_centre").select(F.col("cluster_id").alias("rank"), "tok"), versions.read("clusters", last), versions.read("abstracts", last))
            row = versions.read("counters", last).first()
            now = batch.step(batch.State(c, row["accumulated"], row["clustered"]), temp, cfg)
        made = now.clustering
        counters = spark.createDataFrame([(now.accumulated, now.clustered)], "accumulated long, clustered long")
        versions.write(batch_id, postings=made.postings, clusters=made.clusters.select("tok", "cluster_id", "is_centre"), abstracts=made.abstracts, counters=counters)

    docs.writeStream.foreachBatch(arrived).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    return versions


def token_stats(stream: DataFrame) -> DataFrame:
    """Running frequencies of the tokens of a stream of documents, for the update or complete mode."""
    return stream.select(F.explode(tokens.token_array(F.col("text"))).alias("tok")).groupBy("tok").agg(F.count("*").alias("tf"))


def token_totals(stream: DataFrame) -> DataFrame:
    """The same with a state of its own: occurrences so far of each token that has just arrived."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def add(key: tuple, batches, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"tok": [key[0]], "tf": [n]})

    rows = stream.select(F.explode(tokens.token_array(F.col("text"))).alias("tok"))
    return rows.groupBy("tok").applyInPandasWithState(add, "tok string, tf long", "tf long", "update", GroupStateTimeout.NoTimeout)
