"""Centre tokens: a walk from widespread to rare tokens that keeps those with more uncovered than covered documents.

The walk is sequential by its definition: a kept token covers its documents. It is computed exactly in two parts.
The head, the most widespread tokens up to HEAD postings, is replayed by one task. Then come rounds over all other
tokens at once: covered documents only become more, so a token that has failed stays failed; and a token none of
whose uncovered documents holds an earlier undecided token can't be changed by any, so it is kept now. All of these
are kept together, their documents covered, and the next round looks at what is left.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from enctopics.operators import index
from enctopics.session import kept

HEAD = 2_000_000


def ranked(stats: DataFrame) -> DataFrame:
    """tok, df, rank by most documents, then token: numbers from sorted partitions and their sizes, no single task."""
    ordered = stats.select("tok", "df").repartitionByRange(F.desc("df"), F.asc("tok")).sortWithinPartitions(F.desc("df"), F.asc("tok"))
    rows = kept(ordered.withColumn("part", F.spark_partition_id()))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = rows.groupBy("part").count().select("part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))
    inside = Window.partitionBy("part").orderBy(F.desc("df"), F.asc("tok"))
    return rows.join(F.broadcast(starts), "part").select("tok", "df", (F.col("start") + F.row_number().over(inside)).alias("rank"))


def uniqueness(postings: DataFrame, covered: DataFrame) -> DataFrame:
    """tok, new_docs, seen_docs against a table of covered doc_id."""
    marks = covered.select("doc_id").distinct().withColumn("covered", F.lit(1))
    rows = postings.join(marks, "doc_id", "left")
    return rows.groupBy("tok").agg(F.count_if(F.col("covered").isNull()).alias("new_docs"), F.count("covered").alias("seen_docs"))


def _walk(rows: pd.DataFrame, inclusive: bool) -> pd.DataFrame:
    covered: set[int] = set()
    out = []
    for (rank, tok), docs in rows.sort_values("rank").groupby(["rank", "tok"], sort=True)["doc_id"]:
        mine = set(docs)
        seen = len(mine & covered)
        new = len(mine) - seen
        if new > seen or inclusive and new == seen:
            covered |= mine
            out.append((tok, new, seen, rank))
    return pd.DataFrame(out, columns=["tok", "new_docs", "seen_docs", "rank"])


def eligible(postings: DataFrame, inclusive: bool = False, head: int = HEAD) -> DataFrame:
    """tok, new_docs, seen_docs, rank of the tokens that the walk keeps."""
    tokens = kept(ranked(index.token_stats(postings)))
    classes = tokens.groupBy("df").count().orderBy(F.desc("df")).toLocalIterator()
    least, mass = 1 << 62, 0
    for c in classes:  # whole classes of equal df, as many as fit the head
        mass += c["df"] * c["count"]
        if mass > head:
            break
        least = c["df"]
    rows = kept(postings.select("tok", "doc_id").join(tokens, "tok"))
    schema = "tok string, new_docs long, seen_docs long, rank long"
    done = kept(rows.where(F.col("df") >= least).withColumn("all", F.lit(1)).groupBy("all").applyInPandas(lambda pdf: _walk(pdf, inclusive), schema))
    if mass <= head:
        return done
    left = rows.where(F.col("df") < least).select("tok", "doc_id", "rank")
    covered = kept(rows.join(done.select("tok"), "tok", "left_semi").select("doc_id").distinct())
    while True:
        counts = uniqueness(left, covered)
        good = counts.where(F.col("new_docs") >= F.col("seen_docs") if inclusive else F.col("new_docs") > F.col("seen_docs"))
        left = kept(left.join(good, "tok"))
        if left.isEmpty():
            return done
        fresh = left.join(covered, "doc_id", "left_anti")
        first = fresh.groupBy("doc_id").agg(F.min("rank").alias("first"))
        late = fresh.join(first, "doc_id").where(F.col("rank") > F.col("first")).select("tok").distinct()
        ready = kept(left.join(late, "tok", "left_anti"))
        done = kept(done.union(ready.select("tok", "new_docs", "seen_docs", "rank").distinct()))
        covered = kept(covered.union(ready.select("doc_id")).distinct())
        left = left.join(ready.select("tok").distinct(), "tok", "left_anti").select("tok", "doc_id", "rank")


def centrality(kept_tokens: DataFrame, separations: DataFrame, zero_overlap: str = "unit") -> DataFrame:
    """phi = uniqueness * separation * (1 - separation); without covered documents the divisor is 1, or phi infinite."""
    ratio = F.col("new_docs") / F.greatest(F.col("seen_docs"), F.lit(1))
    if zero_overlap == "infinite":
        ratio = F.when(F.col("seen_docs") == 0, F.lit(float("inf"))).otherwise(ratio)
    phi = ratio * F.col("q") * (1 - F.col("q"))
    return kept_tokens.join(separations, "tok").withColumn("phi", F.when(F.isnan(phi), 0.0).otherwise(phi))


def choose(postings: DataFrame, k: int, separations: DataFrame, inclusive: bool = False, zero_overlap: str = "unit") -> DataFrame:
    """At most k centres: rank (1 is best), tok, new_docs, seen_docs, phi. Fewer if fewer are eligible."""
    scored = centrality(eligible(postings, inclusive), separations, zero_overlap)
    best = scored.orderBy(F.desc(F.round("phi", 9)), F.desc("new_docs"), "tok").limit(k)
    order = Window.orderBy(F.desc(F.round("phi", 9)), F.desc("new_docs"), "tok")  # of k rows at most
    return best.select(F.row_number().over(order).alias("rank"), "tok", "new_docs", "seen_docs", "phi")


def by_document_count(stats: DataFrame, k: int) -> DataFrame:
    """The k most widespread tokens: the simple way, with overlapping topics."""
    best = stats.orderBy(F.desc("df"), "tok").limit(k)
    return best.select(F.row_number().over(Window.orderBy(F.desc("df"), "tok")).alias("rank"), "tok", "df")


def overlap(centres: DataFrame, postings: DataFrame) -> DataFrame:
    """How much a set of centres shares: documents, documents with several centres, pairs that meet."""
    rows = postings.join(F.broadcast(centres.select("tok")), "tok", "left_semi")
    c = F.col("c")
    return rows.groupBy("doc_id").agg(F.count("*").alias("c")).agg(F.count("*").alias("docs"), F.count_if(c > 1).alias("shared_docs"), F.coalesce(F.sum(c * (c - 1) / 2), F.lit(0)).cast("long").alias("pairs"))
