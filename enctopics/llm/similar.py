"""SimHash near-duplicates at a similarity of 0.8: rare shingles, pigeonring over fingerprints, verified Jaccard.

A text becomes the set of its five-word shingles (all its words, if fewer); words are what white space parts, in
lower case. Two texts are linked at a Jaccard similarity of 0.8 or more. Their SimHashes may then differ in some 20
of 64 bits, too many for equal blocks of bits to be keys that tell much. So texts meet as follows:

1. All sets are put into one order, frequent shingles last. Of n shingles, two similar texts share one among the
   first n - ceil(0.8 n) + 1 of each, so these are the keys under which texts meet. How frequent a shingle is comes
   from a sketch of all texts; it decides how many texts meet, never which links are found.
2. Pairs that meet must have fitting sizes and fingerprints within RADIUS: chains of consecutive 16-bit segments
   have to keep their cumulative differences within proportional budgets, then the whole distance counts. Sets of under
   LEAST shingles, whose fingerprints are coarse, are not judged by them.
3. What is left is verified by the exact similarity. Neighbours by size under a key come first, then each text with
   the pivot of its key, the text that meets most others. What they connect needs no further comparison. As long as many
   pairs are left and pivots help, another text of the largest part that is connected under a key is its next pivot. Then
   all pairs that meet under a key and aren't connected yet are compared, each under one of its keys: under none for which
   both texts have a lesser one among their OWN least. From the second step on, the parities of 512 cells of
   either set, of which each unequal shingle turns one, prove most pairs apart, those of 2,048 cells all but few of
   the rest before their sets are fetched. Of all keys under which the same texts meet, one is kept.

Texts of one set are one node, so copies cost nothing. Nulls: texts without a word, null ones too, are copies of
each other. An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from enctopics.llm.common import BROADCAST_ROWS, cut, first_copies, narrow, save, small, trimmed
from enctopics.llm.components import components

WORDS, SIMILARITY, SEED, RADIUS, LEAST = 5, 0.8, 42, 26, 32
#: Cells of a set's parities, and of the wider ones that sets of at least LONG shingles have besides.
CELLS, WIDE, LONG = 512, 2048, 128
#: Cells of the sketch, in how many slices; keys of texts that a worker knows it has sent already; bytes that are split into words at once.
BUCKETS, SLICES, KNOWN, CHUNK = 1 << 21, 64, 100_000, 1 << 18
#: Rounds of pivots at most; pairs a row from which another round may be worth it; least keys of a text that its rows carry.
PIVOTS, MANY, OWN = 4, 4, 16
_ODD, _TURN = np.uint64(0x9E3779B97F4A7C15), np.uint64(29)


def _pieces(text: bytes) -> Iterator[bytes]:
    """A text in pieces of about CHUNK bytes, cut at white space."""
    at = 0
    while at < len(text):
        end = at + CHUNK
        while end < len(text) and text[end] not in b" \t\n\r\x0b\x0c":
            end += 1
        yield text[at:end]
        at = end


def shingles(text: bytes, k: int = WORDS) -> np.ndarray:
    """Hashes of the different runs of k words, in rising order."""
    parts = [np.array([xxhash.xxh64_intdigest(w, SEED) for w in piece.lower().split()], np.uint64) for piece in _pieces(text)]
    hashes = np.concatenate(parts) if parts else np.zeros(0, np.uint64)
    n = len(hashes) - k + 1
    if n < 1:
        words = text.lower().split()
        return np.array([xxhash.xxh64_intdigest(b" ".join(words), SEED)] if words else [], np.uint64)
    out = np.zeros(n, np.uint64)
    for i in range(k):
        out = (out ^ hashes[i : i + n]) * _ODD
        out ^= out >> _TURN
    return np.unique(out)


def _key(hashes: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(hashes.tobytes(), SEED) - (1 << 63)


def _needed(n: int | Column, similarity: float):
    """Least whole number that is at least similarity * n."""
    return F.ceil(n * F.lit(similarity) - 1e-9) if isinstance(n, Column) else int(np.ceil(n * similarity - 1e-9))


def _fingerprint(hashes: np.ndarray) -> int:
    """64 bits, each set if it is set in over half of the hashes, as a signed number."""
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        ones += np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.int64)[0])


def _parity(hashes: np.ndarray, cells: int = CELLS) -> np.ndarray:
    """A bit a cell: whether an odd number of hashes falls into it. Each hash that only one of two sets has changes one bit at most."""
    odd = np.bincount((hashes >> np.uint64(40)).astype(np.int64) & (cells - 1), minlength=cells) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def _mapped(docs: DataFrame, of: Callable[[int, np.ndarray], tuple], schema: str) -> DataFrame:
    """The columns of `of` for the key and the shingles of each different text, as far as a worker knows: lists, one a column."""
    names = [c.split()[0] for c in schema.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: set[int] = set()
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                made = []
                for t in batch.column(0)[at : at + 64]:
                    hashes = shingles(t.as_buffer().to_pybytes() if t.is_valid else b"")
                    if (key := _key(hashes)) not in seen:
                        if len(seen) >= KNOWN:
                            seen.clear()
                        seen.add(key)
                        made.append(of(key, hashes))
                if made:
                    yield pa.record_batch([pa.concat_arrays([m[i] for m in made]) for i in range(len(names))], names)

    return docs.select("text").mapInArrow(trimmed(run), schema)


def _surveyed(docs: DataFrame) -> DataFrame:
    """doc_id, key, size, parity and wide parity (null for few shingles) of each text's set, counts null; and slices (as key) of how many shingles fall into each cell."""
    kind = dict(docs.dtypes)["doc_id"]
    names, longs = ["doc_id", "key", "n", "parity", "wide", "counts"], pa.list_(pa.int64())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = np.zeros(BUCKETS, np.uint32)
        ids = None
        for batch in batches:
            ids, keys, sizes, odd, wide = batch.column(0).type, [], [], [], []
            for t in batch.column(1):
                hashes = shingles(t.as_buffer().to_pybytes() if t.is_valid else b"")
                odd.append(_parity(hashes))
                wide.append(_parity(hashes, WIDE) if len(hashes) >= LONG else None)
                np.add.at(held, (hashes % np.uint64(BUCKETS)).astype(np.int64), 1)
                keys.append(_key(hashes))
                sizes.append(len(hashes))
            yield pa.record_batch([batch.column(0), pa.array(keys, pa.int64()), pa.array(sizes, pa.int64()), pa.array(odd, longs), pa.array(wide, longs), pa.nulls(len(keys), pa.binary())], names)
        if ids is not None:
            slices = [zlib.compress(x.tobytes(), 1) for x in held.reshape(SLICES, -1)]
            yield pa.record_batch([pa.nulls(SLICES, ids), pa.array(range(SLICES), pa.int64()), pa.nulls(SLICES, pa.int64()), pa.nulls(SLICES, longs), pa.nulls(SLICES, longs), pa.array(slices, pa.binary())], names)

    return docs.mapInArrow(trimmed(run), f"doc_id {kind}, key long, n long, parity array<long>, wide array<long>, counts binary")


def _crowd(slices: DataFrame) -> np.ndarray:
    """How many binary digits the count of each cell has, over all partitions."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for key, raw in zip(batch.column(0).to_pylist(), batch.column(1)):
                part = np.frombuffer(zlib.decompress(raw.as_buffer()), np.uint32).astype(np.uint64)
                sums[key] = sums[key] + part if key in sums else part
        digits = [zlib.compress(np.ceil(np.log2(x + 1.0)).astype(np.uint8).tobytes(), 1) for x in sums.values()]
        yield pa.record_batch([pa.array(sums.keys(), pa.int64()), pa.array(digits, pa.binary())], ["key", "digits"])

    crowd = np.zeros((SLICES, BUCKETS // SLICES), np.uint8)
    for r in slices.repartition("key").mapInArrow(add, "key long, digits binary").collect():
        crowd[r["key"]] = np.frombuffer(zlib.decompress(r["digits"]), np.uint8)
    return crowd.reshape(-1)


def _chained(a: str, b: str, radius: int = RADIUS) -> Column:
    """Whether two fingerprints keep to the budgets from some segment on around the ring, and to radius as a whole."""
    gap = F.col(a).bitwiseXOR(F.col(b))
    d = [F.bit_count(F.shiftrightunsigned(gap, 16 * i).bitwiseAND(F.lit(0xFFFF))) for i in range(4)]
    chain = lambda i: reduce(lambda x, y: x & y, [4 * sum((d[(i + j) % 4] for j in range(1, n)), d[i]) <= n * radius for n in (1, 2, 3)])
    return reduce(lambda x, y: x | y, map(chain, range(4))) & (F.bit_count(gap) <= radius)


def _unequal(a: str, b: str, longs: int) -> Column:
    """Bits in which two parities differ: no more than the shingles that only one of the two sets has."""
    return reduce(lambda x, y: x + y, (F.bit_count(F.col(a)[i].bitwiseXOR(F.col(b)[i])) for i in range(longs)))


def _most(n: Column, similarity: float) -> Column:
    """How many shingles only one of two similar sets may have; n of both together."""
    return n - 2 * F.ceil(n * F.lit(similarity / (1 + similarity)) - 1e-9)


def _asked(pairs: DataFrame) -> tuple[DataFrame, int]:
    """key of the texts of pairs, each once, and how many they are."""
    keys = cut(pairs.select(F.explode(F.array("a", "b")).alias("key")).distinct())
    return keys, keys.count()


def _with_texts(docs: DataFrame, found: DataFrame, keys: DataFrame, n: int) -> DataFrame:
    """Documents that hold the texts of keys, and few others, if these are few enough to be told apart by a broadcast; rows without an id stay."""
    if n > BROADCAST_ROWS:
        return docs
    ids = found.join(F.broadcast(keys), "key", "left_semi").groupBy("key").agg(F.min("doc_id").alias("doc_id")).select("doc_id", F.lit(True).alias("asked")).distinct()
    return docs.join(F.broadcast(ids), "doc_id", "left").where("asked OR doc_id IS NULL").select(*docs.columns)


def _alike(pairs: DataFrame, docs: DataFrame, found: DataFrame, parities: DataFrame, similarity: float) -> DataFrame:
    """The pairs a, b whose sets are similar. Wide parities come first; the sets are made anew for the texts that are still asked for."""

    def whole(key: int, hashes: np.ndarray) -> tuple:
        return pa.array([key]), pa.array([hashes.view(np.int64)], pa.list_(pa.int64()))

    def of(keys: DataFrame, n: int, rows: DataFrame, *columns: str) -> DataFrame:
        """rows of keys, each once."""
        return rows.join(small(keys, n), "key", "left_semi").groupBy("key").agg(*[F.first(c).alias(c) for c in columns])

    def both(pairs: DataFrame, rows: DataFrame) -> DataFrame:
        sides = [rows.select(*[F.col(c).alias(side if c == "key" else f"{c}_{side}") for c in rows.columns]) for side in "ab"]
        return pairs.join(sides[0], "a").join(sides[1], "b")

    unequal, most = _unequal("wide_a", "wide_b", WIDE // 64), _most(F.col("n_a") + F.col("n_b"), similarity)
    pairs = cut(both(pairs, save(of(*_asked(pairs), parities, "n", "wide"))).where(F.col("wide_a").isNull() | F.col("wide_b").isNull() | (unequal <= most)).select("a", "b"))
    asked = _asked(pairs)
    sets = save(of(*asked, _mapped(_with_texts(docs, found, *asked), whole, "key long, hashes array<long>"), "hashes"))
    shared = both(pairs, sets).select("a", "b", (F.size("hashes_a") + F.size("hashes_b")).alias("n"), F.size(F.array_intersect("hashes_a", "hashes_b")).alias("shared"))
    return shared.where(F.col("shared") >= _needed(F.col("n") - F.col("shared"), similarity)).select("a", "b")


def _once(met: DataFrame) -> DataFrame:
    """The rows of one key h of all that the same texts meet under: x and y stand for these texts, first marks one row a key."""
    one = met.where("first").groupBy("x", "y").agg(F.min("h").alias("h"))
    return save(met.join(one, ["h", "x", "y"], "left_semi").drop("first", "x", "y"))


def _pivots(now: DataFrame, turn: int) -> DataFrame:
    """One row of each key h: first that of the text that meets most others, later any of the component with most rows under h."""
    if turn:
        ranked = now.join(now.groupBy("h", "label").agg(F.count("*").alias("degree")), ["h", "label"]).withColumn("order", F.xxhash64("key", F.lit(turn)))
    else:
        degree = now.join(now.groupBy("h").agg(F.count("*").alias("size")), "h").groupBy("key").agg(F.sum("size").alias("degree"))
        ranked = now.join(degree, "key").withColumn("order", F.col("key"))
    return ranked.groupBy("h").agg(F.max_by(F.struct("key", "n", "fp", "parity", "label"), F.struct("degree", "order")).alias("p")).select("h", "p.*")


def _open_pairs(now: DataFrame) -> tuple[int, float]:
    """Rows, and pairs of rows under one key that aren't connected."""
    size = now.groupBy("h", "label").agg(F.count("*").cast("double").alias("c")).groupBy("h").agg(F.sum("c").alias("c"), F.sum(F.col("c") * F.col("c")).alias("own"))
    rows, pairs = size.agg(F.sum("c"), F.sum((F.col("c") * F.col("c") - F.col("own")) / 2)).first()
    return int(rows or 0), pairs or 0.0


def _met(one: DataFrame, other: DataFrame, similarity: float, *more: Column) -> DataFrame:
    """Pairs a, b of rows under one key that aren't connected, can't be told apart yet and keep to more: a row a key."""
    left, right = (df.select("h", *[F.col(c).alias(f"{c}{side}") for c in df.columns if c != "h"]) for df, side in ((one, "_a"), (other, "_b")))
    small_n, large_n = F.least("n_a", "n_b"), F.greatest("n_a", "n_b")
    judged = (_unequal("parity_a", "parity_b", CELLS // 64) <= _most(small_n + large_n, similarity)) & ((small_n < LEAST) | _chained("fp_a", "fp_b"))
    met = left.join(right, "h").where(reduce(lambda x, y: x & y, [F.col("label_a") != F.col("label_b"), small_n >= _needed(large_n, similarity), judged, *more]))
    return met.select(F.least("key_a", "key_b").alias("a"), F.greatest("key_a", "key_b").alias("b"))


def _linked(docs: DataFrame, found: DataFrame, crowd: np.ndarray, parities: DataFrame, similarity: float) -> DataFrame:
    """node, label of the sets that are linked to another; found: doc_id, key, parities: key, n, parity, wide of every text's set."""

    def first(key: int, hashes: np.ndarray) -> tuple:
        n = len(hashes)
        order = np.lexsort((hashes, crowd[(hashes % np.uint64(BUCKETS)).astype(np.int64)]))
        chosen = hashes[order[: n - _needed(n, similarity) + 1]] if n else hashes
        same = lambda x: pa.array(np.full(len(chosen), x))
        return pa.array(chosen.view(np.int64)), same(key), same(n), same(_fingerprint(hashes))

    near = lambda less, more: F.col(less) >= _needed(F.col(more), similarity)
    fits = lambda n, m, f, g: near(n, m) & ((F.col(n) < LEAST) | (F.col(m) < LEAST) | _chained(f, g))
    order, whole = Window.partitionBy("h").orderBy("n", "key"), Window.partitionBy("h")
    met = _mapped(docs, first, "h long, key long, n long, fp long").repartition("h")
    met = met.withColumns({"before": F.lag("key").over(order), "after": F.lead("key").over(order), "n_before": F.lag("n").over(order), "fp_before": F.lag("fp").over(order)})
    met = met.where(~F.col("before").eqNullSafe(F.col("key")) & (F.col("before").isNotNull() | F.col("after").isNotNull()))
    met = met.withColumns({"x": F.bit_xor(F.xxhash64("key")).over(whole), "y": F.bit_xor(F.xxhash64("key", F.lit("y"))).over(whole)})
    met = met.select("h", "key", "n", "fp", F.col("before").isNull().alias("first"), F.when(fits("n_before", "n", "fp_before", "fp"), F.col("before")).alias("before"), "x", "y")
    met = _once(save(met))
    close = cut(met.where(F.col("before").isNotNull()).select(F.col("before").alias("a"), F.col("key").alias("b")).distinct())
    links = cut(_alike(close, docs, found, parities, similarity))

    def still_open(rows: DataFrame, labels: DataFrame) -> DataFrame:
        """rows with the label of their component, of the keys under which several components meet."""
        labelled = rows.join(labels.withColumnRenamed("node", "key"), "key", "left").withColumn("label", F.coalesce("label", "key"))
        several = labelled.groupBy("h").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("h")
        return labelled.join(several, "h", "left_semi").select("h", "key", "n", "fp", "label", *(["parity"] if "parity" in rows.columns else []))

    def apart(one: DataFrame, other: DataFrame, known: DataFrame, *more: Column) -> DataFrame:
        """What _met has, each pair once, of the pairs that haven't been compared."""
        return cut(_met(one, other, similarity, *more).distinct().join(known, ["a", "b"], "left_anti"))

    known = close.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    odd = parities.groupBy("key").agg(F.first("parity").alias("parity"))
    now, labels = cut(still_open(met, components(links)).join(odd, "key")), None
    _, before = _open_pairs(now)
    for turn in range(PIVOTS):
        pairs = apart(now, _pivots(now, turn), known)
        links = cut(links.union(_alike(pairs, docs, found, parities, similarity)).distinct())
        known, labels = known.union(pairs), cut(components(links))
        now = cut(still_open(now.drop("label"), labels))
        rows, left = _open_pairs(now)
        if left <= MANY * rows or left > before / 2:
            break
        before = left
    if not left:
        return labels
    own = now.groupBy("key").agg(F.slice(F.sort_array(F.collect_set("h")), 1, OWN).alias("own"))
    rest = cut(now.join(own, "key"))
    once = (F.col("key_a") < F.col("key_b")) & (F.coalesce(F.array_min(F.array_intersect("own_a", "own_b")), F.col("h")) >= F.col("h"))
    rest = apart(rest, rest, known, once)
    return labels if rest.isEmpty() else components(links.union(_alike(rest, docs, found, parities, similarity)))


def near_duplicates(docs: DataFrame, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, component_id: the least doc_id that links reach."""
    rows = narrow(docs, doc_id=id_col, text=text_col)
    surveyed = save(_surveyed(rows))
    crowd = _crowd(surveyed.where("counts IS NOT NULL").select("key", "counts"))
    found = surveyed.where("counts IS NULL").select("doc_id", "key")
    parities = surveyed.where("counts IS NULL").select("key", "n", "parity", "wide")
    labels = _linked(rows, found, crowd, parities, similarity)
    known = found.groupBy("key").agg(F.min("doc_id").alias("least")).join(labels.withColumnRenamed("node", "key"), "key", "left").select("key", "least", F.coalesce("label", "key").alias("label"))
    owned = known.join(known.groupBy("label").agg(F.min("least").alias("component_id")), "label").select("key", "component_id")
    return found.join(owned, "key").select("doc_id", "component_id")


def one_of_each(docs: DataFrame, similarity: float = SIMILARITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The document with the least id of each component, with all columns; rows without an id stay."""
    least = near_duplicates(docs, similarity, id_col, text_col).where("doc_id = component_id").select("doc_id")
    return first_copies(docs, least, id_col, text_col)
