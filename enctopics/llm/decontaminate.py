"""Benchmark passages inside documents: SimHash over item-sized windows, then exact similarity; no Python.

Texts become lower-case runs of letters and digits; shingles are five words (all words, if fewer). Similarity is
the weighted Jaccard of two shingle multisets, and a window of an item's own number of words counts at 0.8 or more.
A document with fewer words than an item is its own only window for it. Items of under five words are one shingle, and
meet the runs of as many words of each document.

1. A window that similar shares a shingle with its item. So all windows of an item's size that hold any shingle of an
   item of that size are looked at; each gets a 64-bit SimHash of its shingles.
2. Windows and items of one size meet in a multi-index: the bits are cut into RADIUS + 1 blocks, and two fingerprints
   within RADIUS agree in one block at least.
3. Pairs within RADIUS are verified exactly.

Windows at 0.8 lie about 10 bits from their item, 3 bits as a standard deviation; RADIUS is more than three
deviations beyond. The tests measure that on random edits. The windows of a document are no more than its words for
each size of an item, also where texts repeat themselves.

Nulls: null texts and texts or items without a word match nothing. Repeated documents or items each match.
Empty tables give no rows. Other columns of the inputs are ignored.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import cut, let, narrow, no_null, small, without

WORDS, SIMILARITY, RADIUS = 5, 0.8, 20


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(no_null(text)), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def shingles(ws: Column, k: int | Column = WORDS) -> Column:
    """Hashes of all runs of k words; of the whole sequence, if it is shorter; none of no words."""

    k = F.lit(k) if isinstance(k, int) else k

    def of(w: Column) -> Column:
        runs = F.transform(F.sequence(F.lit(1), F.size(w) - k + 1), lambda i: F.xxhash64(F.slice(w, i, k)))
        return F.when(F.size(w) >= k, runs).when(F.size(w) > 0, F.array(F.xxhash64(w))).otherwise(F.array().cast("array<bigint>"))

    return let(ws, of)


def fingerprint(hashes: Column) -> Column:
    """64 bits; a bit is set if it is set in over half of the hashes.

    Four bits are counted at once, in the four 16-bit lanes of a long; where so many hashes could overflow a lane,
    each bit is counted alone.
    """
    lanes = F.expr("281479271743489L")  # 1 in each lane
    half = (F.lit(16383) - F.floor(F.size(hashes) / 2)).cast("bigint")

    def four(j: int) -> Column:
        n = F.aggregate(hashes, F.lit(0).cast("bigint"), lambda n, h: n + F.shiftrightunsigned(h, j).bitwiseAND(lanes))
        return F.shiftleft(F.shiftrightunsigned(n + half * lanes, 14).bitwiseAND(lanes), j)

    ones = F.transform(F.sequence(F.lit(0), F.lit(63)), lambda b: F.aggregate(hashes, F.lit(0), lambda n, h: n + F.getbit(h, b).cast("int")) * 2 > F.size(hashes))
    alone = F.aggregate(F.transform(ones, lambda one, b: F.when(one, F.call_function("shiftleft", F.expr("1L"), b)).otherwise(F.expr("0L"))), F.lit(0).cast("bigint"), lambda acc, bit: acc.bitwiseOR(bit))
    return F.when(F.size(hashes) < 32768, reduce(lambda x, y: x.bitwiseOR(y), map(four, range(16)))).otherwise(alone)


def block_edges(radius: int = RADIUS) -> list[tuple[int, int]]:
    """First bit and width of each of radius + 1 blocks of a fingerprint."""
    cuts = [64 * i // (radius + 1) for i in range(radius + 2)]
    return [(a, b - a) for a, b in zip(cuts, cuts[1:])]


def blocks(fp: Column, radius: int = RADIUS) -> Column:
    return F.array(*[F.shiftrightunsigned(fp, a).bitwiseAND(F.lit((1 << w) - 1).cast("bigint")) for a, w in block_edges(radius)])


def overlap(a: Column, b: Column) -> Column:
    """Size of the intersection of two multisets; a is gone through once for each different element of b."""
    count = lambda hs, h: F.size(F.filter(hs, lambda x: x == h))
    return F.aggregate(F.array_distinct(b), F.lit(0), lambda n, h: n + F.least(count(a, h), count(b, h)))


def contamination(docs: DataFrame, benchmark: DataFrame, similarity: float = SIMILARITY, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """doc_id, item_id, start_word, n_words, hamming, similarity: the best window of each pair."""
    items = cut(
        narrow(benchmark, item_id=item_col, text=item_text_col)
        .select("item_id", words(F.col("text")).alias("ws"))
        .select("item_id", F.size("ws").alias("n_words"), shingles(F.col("ws")).alias("item_hashes"))
        .where("n_words > 0")
        .withColumn("item", F.monotonically_increasing_id())
        .withColumn("item_fp", fingerprint(F.col("item_hashes")))
    )
    width = F.least("n_words", F.lit(WORDS))
    n_items, n_shingles, widths = items.agg(F.count("*"), F.coalesce(F.sum(F.size("item_hashes")), F.lit(0)), F.collect_set(width)).first()
    wanted = small(items.select("n_words", F.size("item_hashes").alias("total"), F.explode("item_hashes").alias("h")).distinct(), n_shingles)

    texts = narrow(docs, doc_id=id_col, text=text_col).withColumn("row", F.xxhash64("doc_id", "text"))
    # _outer: a plain explode makes Spark test the array's size first, and so compute it twice
    at_width = lambda k: texts.select("row", shingles(words(F.col("text")), k).alias("hashes")).select("row", F.posexplode_outer("hashes").alias("at", "h"))
    hits = reduce(DataFrame.union, map(at_width, sorted(widths) or [WORDS])).join(wanted, "h")
    held = hits.groupBy("row", "n_words", "total").agg(F.array_sort(F.collect_set("at")).alias("ats"))
    asked = cut(held.groupBy("row", width.alias("k")).agg(F.collect_list(F.struct("n_words", "total", "ats")).alias("asked")))

    full = texts.join(small(asked, asked.count()), "row").select("doc_id", "asked", "k", words(F.col("text")).alias("ws")).select("doc_id", "asked", F.size("ws").alias("size"), shingles(F.col("ws"), F.col("k")).alias("hashes"))

    def starts(a: Column) -> Column:
        """Of the windows over a hit, those that don't hold the hit before: each window once, in order."""
        last = F.greatest(F.size("hashes") - a["total"], F.lit(0))
        before = lambda i: F.when(i > 0, F.element_at(a["ats"], F.greatest(i, F.lit(1))) + 1).otherwise(0)
        first = lambda p, i: F.greatest(p - a["total"] + 1, before(i), F.lit(0))
        spans = F.transform(a["ats"], lambda p, i: F.when(first(p, i) <= F.least(p, last), F.sequence(first(p, i), F.least(p, last))).otherwise(F.array().cast("array<int>")))
        return F.flatten(spans)

    each = full.select("doc_id", "size", "hashes", F.explode_outer("asked").alias("a")).select("doc_id", "size", "hashes", "a.n_words", "a.total", F.explode_outer(starts(F.col("a"))).alias("start")).where("start IS NOT NULL")
    windows = each.select("doc_id", "n_words", F.least("n_words", "size").alias("held_words"), "start", F.slice("hashes", F.col("start") + 1, F.col("total")).alias("window")).withColumn("fp", F.coalesce(fingerprint(F.col("window")), F.lit(0).cast("bigint")))  # never null, so no filter computes it again
    probes = windows.select("*", F.posexplode_outer(blocks(F.col("fp"), radius)).alias("block", "value"))
    index = items.select("item", "item_id", F.col("n_words").alias("size"), "item_hashes", "item_fp", F.posexplode(blocks(F.col("item_fp"), radius)).alias("b", "v"))
    hamming = F.bit_count(F.col("fp").bitwiseXOR(F.col("item_fp")))
    met = (F.col("block") == F.col("b")) & (F.col("value") == F.col("v")) & (F.col("n_words") == F.col("size"))
    agree = F.array_position(F.zip_with(blocks(F.col("fp"), radius), blocks(F.col("item_fp"), radius), lambda x, y: x == y), F.lit(True)) - 1
    found = (
        probes.join(small(index, n_items * (radius + 1)), met)
        .where((hamming <= radius) & (agree == F.col("block")))  # once a pair: where its first equal block meets
        .withColumn("similarity", let(overlap(F.col("window"), F.col("item_hashes")), lambda n: n / (F.size("window") + F.size("item_hashes") - n)))
        .where(F.col("similarity") >= similarity)
    )
    best = F.min_by(F.struct("start", F.col("held_words").alias("n_words"), hamming.alias("hamming"), "similarity"), F.struct(-F.col("similarity"), F.col("start")))
    return found.groupBy("doc_id", "item_id").agg(best.alias("best")).select("doc_id", "item_id", F.col("best.start").cast("long").alias("start_word"), "best.n_words", "best.hamming", F.round("best.similarity", 6).alias("similarity"))


def clean(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without those that hold a passage of benchmark; rows without an id stay."""
    found = contamination(docs, benchmark, id_col=id_col, text_col=text_col).select("doc_id").distinct()
    return without(docs, cut(found), id_col)
