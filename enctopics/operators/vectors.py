"""Vectors of tokens, for similarities: word vectors, document profiles, or a given table. All have length 1."""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from enctopics.operators.tokens import token_array


def norm(v: Column) -> Column:
    return F.sqrt(F.aggregate(v, F.lit(0.0), lambda s, x: s + x * x))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """Vectors of one length as the rows of a matrix."""
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    parts = [c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1) for c in chunks if len(c)]
    return np.concatenate(parts) if parts else np.zeros((0, 0))


def unit(df: DataFrame, column: str = "vec") -> DataFrame:
    """Rows whose vector isn't zero, at length 1; the length is a variable of the expression, or it would be taken anew for each number."""
    length = norm(F.transform(column, lambda x: x.cast("double")))
    scaled = F.transform(F.array(length), lambda n: F.transform(column, lambda x: x.cast("double") / n))
    return df.where(length > 0).withColumn(column, F.get(scaled, 0))


#: Tokens that are trained on at once; of the words of a first such block, so many start all others from one place.
BLOCK, COMMON = 2_000_000, 50_000
#: Words on either side; centres of a step; noise words of a step and how many of them a pair counts as; first step length;
#: pairs of a word in a step that are added up in full; how far a word goes in a step at most.
WINDOW, STEP, NOISE, NEGATIVES, RATE, FULL, FAR = 5, 256, 128, 5, 0.1, 64, 0.5


def _first(words: list[str], size: int, seed: int) -> np.ndarray:
    """Small vectors that word and seed determine, the same in every task."""
    h = np.fromiter((zlib.crc32(w.encode(), seed) for w in words), np.uint64, len(words))[:, None] + np.arange(size, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return (((h >> np.uint64(40)).astype(np.float32) / (1 << 24)) - 0.5) / size


def _add(to: np.ndarray, at: np.ndarray, by: np.ndarray, pairs: np.ndarray) -> None:
    """to[at] += by with repeated places; of a word with more than FULL pairs the sum is scaled down, as all start from one state, and none goes beyond FAR."""
    order = np.argsort(at, kind="stable")
    own, starts = np.unique(at[order], return_index=True)
    n = np.add.reduceat(pairs[order], starts)
    way = np.add.reduceat(by[order], starts) * (FULL / np.maximum(n, FULL)).astype(np.float32)[:, None]
    to[own] += way * (FAR / np.maximum(np.linalg.norm(way, axis=1, keepdims=True), FAR))


def _skip_gram(ids: np.ndarray, doc: np.ndarray, inner: np.ndarray, outer: np.ndarray, seed: int) -> None:
    """One pass over ids (words by their row; doc: their document) that moves inner and outer in place, with noise words shared by a step."""
    draw = np.random.default_rng(seed)
    chance = np.cumsum(np.bincount(ids, minlength=len(inner)) ** 0.75)
    sigmoid = lambda x: 1 / (1 + np.exp(-np.clip(x, -30, 30)))
    ids, doc = np.pad(ids, WINDOW), np.pad(doc, WINDOW, constant_values=-1)
    for i in range(WINDOW, len(ids) - WINDOW, STEP):
        j = min(i + STEP, len(ids) - WINDOW)
        rate = np.float32(RATE * max(1 - (i - WINDOW) / len(ids), 1e-4))
        around = slice(i - WINDOW, j + WINDOW)
        v, u = inner[ids[i:j]], outer[ids[around]]
        dv, du, pairs, met_by = np.zeros_like(v), np.zeros_like(u), np.zeros(j - i, np.float32), np.zeros(len(u), np.float32)
        reach = draw.integers(1, WINDOW + 1, j - i)
        for d in [*range(-WINDOW, 0), *range(1, WINDOW + 1)]:
            met = (doc[i + d : j + d] == doc[i:j]) & (reach >= abs(d))
            there = slice(WINDOW + d, WINDOW + d + j - i)
            g = (met * (1 - sigmoid(np.einsum("ij,ij->i", v, u[there])))).astype(np.float32)[:, None] * rate
            dv += g * u[there]
            du[there] += g * v
            pairs += met
            met_by[there] += met
        noise = np.minimum(np.searchsorted(chance, draw.random(NOISE) * chance[-1], "right"), len(inner) - 1)
        un = outer[noise]
        g = -sigmoid(v @ un.T) * (rate * np.float32(NEGATIVES / NOISE) * pairs)[:, None]
        dv += g @ un
        _add(outer, np.r_[ids[around], noise], np.concatenate([du, g.T @ v]), np.r_[met_by, np.full(NOISE, pairs.sum() * NEGATIVES / NOISE)])
        _add(inner, ids[i:j], dv, pairs * (1 + NEGATIVES))


def _trained(size: int, seed: int, start: tuple[dict[str, int], np.ndarray, np.ndarray] | None) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def block(lists: list[pa.Array]) -> Iterator[pa.RecordBatch]:
        coded = pa.concat_arrays([x.flatten() for x in lists]).dictionary_encode()
        words, ids = coded.dictionary.to_pylist(), coded.indices.to_numpy().astype(np.int64)
        doc = np.concatenate([x.value_lengths().to_numpy() for x in lists])
        inner, outer = _first(words, size, seed), np.zeros((len(words), size), np.float32)
        if start:
            known = np.fromiter((start[0].get(w, -1) for w in words), np.int64, len(words))
            inner[known >= 0], outer[known >= 0] = start[1][known[known >= 0]], start[2][known[known >= 0]]
        _skip_gram(ids, np.repeat(np.arange(len(doc)), doc), inner, outer, seed)
        n = np.bincount(ids, minlength=len(words))
        for i in range(0, len(words), 10_000):
            sides = [pa.FixedSizeListArray.from_arrays(pa.array(x[i : i + 10_000].ravel()), size).cast(pa.list_(pa.float32())) for x in (inner, outer)]
            yield pa.record_batch([coded.dictionary[i : i + 10_000], pa.array(n[i : i + 10_000]), *(sides if start is None else sides[:1])], ["tok", "n", "vec", "outer"][: 3 + (start is None)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists, n = [], 0
        for batch in batches:
            if batch.num_rows:
                lists.append(batch.column(0))
                n += len(batch.column(0).flatten())
            if start and n >= BLOCK:
                yield from block(lists)
                lists, n = [], 0
        if lists:
            yield from block(lists)

    return run


def word2vec(docs: DataFrame, size: int = 32, min_count: int = 2, seed: int = 42) -> DataFrame:
    """tok, vec by skip-grams with negative sampling, one pass over the token sequences.

    Blocks of documents are trained on in tasks, each with the words that occur in it; a word's vector is the mean of its
    blocks', by its occurrences there. All blocks go on from one that is chosen by a hash of ids and texts, so their spaces agree.
    Corpora of a block or less are trained on in one task. The driver holds the COMMON most frequent words of the first block, never the vocabulary.
    Words under min_count stand in windows, but get no row. Nulls and texts without a word count for nothing.
    """
    rows = docs.where("text IS NOT NULL").select("doc_id", "text")
    words = lambda df: df.select(token_array(F.col("text")).alias("words"))
    total = rows.agg(F.sum(F.length("text"))).first()[0] or 0
    share = BLOCK * 6 / max(total, 1)  # of characters, a word's six or more
    chosen = rows if share >= 1 else rows.where(F.shiftrightunsigned(F.xxhash64("doc_id", "text", F.lit(seed)), 11).cast("double") < share * float(1 << 53))
    one = words(chosen.repartition(1).sortWithinPartitions("doc_id", "text"))
    first = one.mapInArrow(_trained(size, seed, None), "tok string, n long, vec array<float>, outer array<float>")
    if share >= 1:
        found = first.drop("outer")
    else:
        top = first.orderBy(F.desc("n"), "tok").limit(COMMON).toArrow()
        start = {w: i for i, w in enumerate(top["tok"].to_pylist())}, matrix(top["vec"]).reshape(-1, size), matrix(top["outer"]).reshape(-1, size)
        found = words(rows).mapInArrow(_trained(size, seed, start), "tok string, n long, vec array<float>")
    n, sums = F.sum("n").alias("n"), [F.sum(F.col("vec")[i].cast("double") * F.col("n")).alias(f"v{i}") for i in range(size)]
    mean = F.array(*[F.round(F.col(f"v{i}") / F.col("n"), 9) for i in range(size)])
    return unit(found.groupBy("tok").agg(n, *sums).where(F.col("n") >= min_count).select("tok", mean.alias("vec")))


def table(df: DataFrame, tok: str, vec: str) -> DataFrame:
    return unit(df.select(F.col(tok).cast("string").alias("tok"), F.col(vec).alias("vec")))


def sparse(df: DataFrame) -> DataFrame:
    """at and x, the places and values of vec that aren't zero, in its stead; as it is if it has them already."""
    if "vec" not in df.columns:
        return df
    places = F.filter(F.sequence(F.lit(0), F.greatest(F.size("vec") - 1, F.lit(0))), lambda i: F.get("vec", i) != 0)
    return df.withColumns({"at": places, "x": F.transform(F.filter("vec", lambda v: v != 0), lambda v: v.cast("double"))}).drop("vec")


def hashed_cells(postings: DataFrame, dims: int = 64) -> DataFrame:
    """tok, at, x: signed sums of a token's frequencies over hashed documents, of length 1, without those that are zero."""
    at, sign = F.pmod(F.xxhash64("doc_id"), F.lit(dims)).cast("int"), 1 - 2 * F.pmod(F.xxhash64("doc_id", F.lit("sign")), F.lit(2))
    cells = postings.groupBy("tok", at.alias("at")).agg(F.sum(F.col("f") * sign).cast("double").alias("x"))
    x = F.col("x")
    m = cells.where("x <> 0").groupBy("tok").agg(F.sort_array(F.collect_list(F.struct("at", "x"))).alias("m"), F.sqrt(F.sum(x * x)).alias("len"))
    return m.select("tok", F.col("m.at").alias("at"), F.transform("m.x", lambda v: v / F.col("len")).alias("x"))


def hashed_profiles(postings: DataFrame, dims: int = 64) -> DataFrame:
    """tok, vec: signed sums of a token's frequencies over hashed documents, a dense stand-in for its profile.

    Cosines are those of the profiles but for noise of 1 / sqrt(dims).
    """
    m = hashed_cells(postings, dims).select("tok", F.map_from_arrays("at", "x").alias("m"))
    return m.select("tok", F.transform(F.sequence(F.lit(0), F.lit(dims - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0))).alias("vec"))


def profile(postings: DataFrame) -> DataFrame:
    """tok, doc_id, x: a token's frequencies as a sparse vector of length 1."""
    sums = postings.groupBy("tok").agg(F.sqrt(F.sum(F.col("f") * F.col("f"))).alias("len"))
    return postings.join(sums, "tok").select("tok", "doc_id", (F.col("f") / F.col("len")).alias("x"))


def doc_cosine(postings: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """a, b, sim for tokens of left and of right that share a document."""
    p = profile(postings)
    a = p.join(left.select("tok").distinct(), "tok", "left_semi").select(F.col("tok").alias("a"), "doc_id", F.col("x").alias("xa"))
    b = p.join(right.select("tok").distinct(), "tok", "left_semi").select(F.col("tok").alias("b"), "doc_id", F.col("x").alias("xb"))
    return a.join(b, "doc_id").groupBy("a", "b").agg(F.sum(F.col("xa") * F.col("xb")).alias("sim"))


def within(rows: DataFrame) -> DataFrame:
    """a, b, sim for the pairs of tokens of one cluster, from cluster_id, tok, vec; abstracts are short."""
    a = rows.select("cluster_id", F.col("tok").alias("a"), F.col("vec").alias("va"))
    b = rows.select("cluster_id", F.col("tok").alias("b"), F.col("vec").alias("vb"))
    return a.join(b, "cluster_id").where("a < b").select("a", "b", dot(F.col("va"), F.col("vb")).alias("sim"))
