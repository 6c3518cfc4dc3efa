"""How related a token is to a centre, and which centre it goes to.

For token t let T and W be the sums of f and of f * f. Over the documents it shares with centre c let a be its own
sum of f, b the centre's, w its sum of f * f, and g the sum of f * f * (the centre's f). Summing relative
co-occurrence, weighted by the token's profile, over all documents of either then gives

    r = (g / (a * b) - (W - w) / (T - a)) / T

without the second term where the token has no other document, and -W / T**2 where they never meet. So only
documents that hold both are ever joined.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.operators import index

#: Parts into which the documents of a centre are dealt; blocks of tokens that meet them, and tasks for these.
CHUNKS, BLOCKS, DEALT = 64, 32, 128


def _sides(postings: DataFrame, centres: DataFrame) -> DataFrame:
    """centre, tok, doc_id, fc, f where both stand. Centres are few, their postings may not be: no hint for these."""
    mine = postings.join(F.broadcast(centres.select("tok")), "tok", "left_semi").select(F.col("tok").alias("centre"), "doc_id", F.col("f").alias("fc"))
    others = postings.join(F.broadcast(centres.select("tok")), "tok", "left_anti")
    return mine.join(others, "doc_id")


def cooccurrence(postings: DataFrame, centres: DataFrame) -> DataFrame:
    return _sides(postings, centres).groupBy("centre", "tok").agg(F.count("*").alias("co"))


def disparity(postings: DataFrame, centres: DataFrame) -> DataFrame:
    """centre, tok, co, dis: documents of both, and of one of them only."""
    df = postings.groupBy("tok").agg(F.count("*").alias("df"))
    co = cooccurrence(postings, centres).join(df, "tok").join(df.select(F.col("tok").alias("centre"), F.col("df").alias("dfc")), "centre")
    return co.select("centre", "tok", "co", (F.col("df") + F.col("dfc") - 2 * F.col("co")).alias("dis"))


def value_by_document(postings: DataFrame, centres: DataFrame) -> DataFrame:
    """centre, tok, doc_id, u: how much they co-occur in a document, of all that both are in."""
    rows = _sides(postings, centres)
    sums = rows.groupBy("centre", "tok").agg(F.sum("fc").alias("b"), F.sum("f").alias("a"))
    return rows.join(sums, ["centre", "tok"]).select("centre", "tok", "doc_id", (F.col("f") / F.col("a") * F.col("fc") / F.col("b")).alias("u"))


def disparity_by_document(postings: DataFrame, centres: DataFrame) -> DataFrame:
    """centre, tok, doc_id, phi over the documents of just one of a pair that meets somewhere; for explanations.

    Sums come from totals less what is in documents of both, so the many rows are neither sorted nor grouped. Nor are they shuffled:
    what is dealt out is postings, the documents that a pair shares, and BLOCKS copies of a centre's documents; rows are made after that."""
    tops = F.broadcast(centres.select("tok"))
    c = postings.join(tops, "tok", "left_semi").select(F.col("tok").alias("centre"), F.col("doc_id").alias("at"), F.col("f").alias("fc"))
    chunk = lambda doc: F.pmod(F.xxhash64(doc), F.lit(CHUNKS)).cast("int")
    parts = _sides(postings, centres).groupBy("centre", "tok", chunk("doc_id").alias("chunk")).agg(F.sum("f").alias("f"), F.sum("fc").alias("fc"), F.collect_list("doc_id").alias("docs"))
    sums = parts.groupBy("centre", "tok").agg(F.sum("f").alias("f_met"), F.sum("fc").alias("fc_met"), F.map_from_entries(F.collect_list(F.struct("chunk", "docs"))).alias("met"))
    totals = postings.groupBy("tok").agg(F.sum("f").alias("whole"))
    pairs = sums.join(totals, "tok").join(F.broadcast(totals.join(tops, "tok", "left_semi").select(F.col("tok").alias("centre"), F.col("whole").alias("its"))), "centre")
    mine = pairs.select("centre", "tok", (F.col("whole") - F.col("f_met")).alias("a"))
    here = c.groupBy(F.col("at").alias("doc_id")).agg(F.collect_list("centre").alias("here"))
    own = postings.join(here, "doc_id", "left").join(mine, "tok").where(~F.coalesce(F.array_contains("here", F.col("centre")), F.lit(False)))
    # a centre's documents in chunks, in each block of tokens: a pair meets whole chunks, less the documents that it shares
    lists = c.groupBy("centre", chunk("at").alias("chunk")).agg(F.collect_list(F.struct("at", "fc")).alias("docs"))
    lists = lists.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(BLOCKS - 1)))).repartition(DEALT, "centre", "block")
    its = pairs.select("centre", "tok", (F.col("its") - F.col("fc_met")).alias("b"), "met", F.pmod(F.xxhash64("tok"), F.lit(BLOCKS)).cast("int").alias("block"))
    cells = its.repartition(DEALT, "centre", "block").join(lists, ["centre", "block"]).withColumn("met", F.try_element_at("met", F.col("chunk")))
    rest = F.filter("docs", lambda d: ~F.coalesce(F.array_contains(F.col("met"), d["at"]), F.lit(False)))
    theirs = cells.select("centre", "tok", "b", F.inline(F.when(F.col("met").isNull(), F.col("docs")).otherwise(rest)))
    return own.select("centre", "tok", "doc_id", (F.col("f") / F.col("a")).alias("phi")).unionByName(theirs.select("centre", "tok", F.col("at").alias("doc_id"), (F.col("fc") / F.col("b")).alias("phi")))


def relative_by_document(postings: DataFrame, centres: DataFrame) -> DataFrame:
    """centre, tok, doc_id, rho: co-occurrence where both are, less disparity where one is."""
    u = value_by_document(postings, centres).select("centre", "tok", "doc_id", F.col("u").alias("rho"))
    return u.unionByName(disparity_by_document(postings, centres).select("centre", "tok", "doc_id", (-F.col("phi")).alias("rho")))


def relatedness(postings: DataFrame, centres: DataFrame, disparity: str = "literal") -> DataFrame:
    """centre, tok, r for pairs that meet. disparity: literal, off, or symmetric (the centre's own documents count too)."""
    f, fc = F.col("f"), F.col("fc")
    met = _sides(postings, centres).groupBy("centre", "tok").agg(F.sum(f).alias("a"), F.sum(fc).alias("b"), F.sum(f * f).alias("a2"), F.sum(f * f * fc).alias("g"), F.sum(fc * fc).alias("b2"))
    totals = index.token_stats(postings)
    both = met.join(totals.select("tok", F.col("tf").alias("own"), F.col("tf2").alias("own2")), "tok")
    r = F.col("g") / (F.col("a") * F.col("b"))
    if disparity != "off":
        r = r - F.when(F.col("own") > F.col("a"), (F.col("own2") - F.col("a2")) / (F.col("own") - F.col("a"))).otherwise(0.0)
    r = r / F.col("own")
    if disparity == "symmetric":
        both = both.join(totals.select(F.col("tok").alias("centre"), F.col("tf").alias("its"), F.col("tf2").alias("its2")), "centre")
        r = r - F.when(F.col("its") > F.col("b"), (F.col("its2") - F.col("b2")) / (F.col("its") - F.col("b"))).otherwise(0.0) / F.col("its")
    return both.select("centre", "tok", r.alias("r"))


def distribute(edges: DataFrame, centres: DataFrame, postings: DataFrame | None = None, orphan: str = "cooccurring_only", score: str = "r") -> DataFrame:
    """tok, cluster_id, is_centre: the centre with the largest score, the better centre where they tie.

    Orphans, the tokens of postings that meet no centre: cluster -1, or with `literal` what the formula says, where a
    centre that is never met has the constant -W / T**2 and may win over one that is met.
    """
    c = centres.select(F.col("tok").alias("centre"), F.col("rank").alias("cluster_id"))
    rows = edges.join(F.broadcast(c), "centre")
    best = rows.groupBy("tok").agg(F.max_by("cluster_id", F.struct(F.round(score, 12), -F.col("cluster_id"))).alias("cluster_id"), F.max(score).alias("best"), F.collect_set("cluster_id").alias("met"))
    out = best.select("tok", "cluster_id")
    if postings is not None:
        stats = index.token_stats(postings).join(F.broadcast(centres.select("tok")), "tok", "left_anti")
        full = stats.join(best, "tok", "left")
        if orphan == "literal":
            n = centres.count()
            unmet = F.array_min(F.array_except(F.sequence(F.lit(1), F.lit(n)), F.coalesce("met", F.array().cast("array<int>"))))
            constant = -F.col("tf2") / (F.col("tf") * F.col("tf"))
            chosen = F.when(F.col("best").isNull() | (unmet.isNotNull() & (constant > F.col("best"))), unmet).otherwise(F.col("cluster_id"))
        else:
            chosen = F.coalesce("cluster_id", F.lit(-1))
        out = full.select("tok", chosen.alias("cluster_id"))
    own = centres.select("tok", F.col("rank").alias("cluster_id"), F.lit(True).alias("is_centre"))
    return out.withColumn("is_centre", F.lit(False)).unionByName(own)
