"""Near-duplicates by SimHash: pigeonring candidates, Hamming links, connected components.

A fingerprint's 64 bits form a ring of four 16-bit segments. If two fingerprints differ in at most 3 bits, there
is a segment from which the differences, added up along the ring, stay within 0, 1, 2 and 3: chains that keep to
the proportional budget. So the first segment of such a chain is equal and the second differs in one bit at most,
which leaves one of its halves equal: eight 24-bit keys a fingerprint, and every link shares one of them.
Inside a key the rest of the chain is tested before the whole distance. Keys with more than HOT fingerprints get
longer: the budget of the third and fourth segment leaves one of three, and one of four, parts equal.

Only distinct fingerprints are compared, so copies cost nothing; in large groups a fingerprint is compared only
with those it isn't linked to yet, so a dense group gives a spanning tree of its links and not all of them.

Nulls: a null text has no words, so fingerprint zero, linked like any other. Repeated rows each get a row; the
component of documents without ids has a null id. An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import cut, first_copies, narrow, small
from enctopics.llm.components import components

RADIUS, SHINGLE, SEED, HOT = 3, 3, 42, 20_000
#: Shingles that are counted at once, and group size from which links are searched one fingerprint at a time.
CHUNK, LARGE = 1 << 16, 64


def fingerprint(text: bytes, k: int = SHINGLE) -> int:
    """SimHash over k-word shingles of a text, as an unsigned number."""
    words = text.lower().split()
    n = max(len(words) - k + 1, 1)
    if not words:
        return 0
    ones = np.zeros(64, np.int64)
    for at in range(0, n, CHUNK):
        part = words[at : at + CHUNK + k - 1]
        runs = zip(*(part[i:] for i in range(k))) if len(part) >= k else [part]
        hashes = np.array([xxhash.xxh64_intdigest(b" ".join(run), SEED) for run in runs], np.uint64)
        ones += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fp (the 64 bits as a long)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t.as_buffer().to_pybytes() if t.is_valid else b"") for t in batch.column(1)], np.uint64)
            yield pa.record_batch([batch.column(0), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    rows = narrow(docs, doc_id=id_col, text=text_col)
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, fp long")


def _chained(a: np.ndarray, b: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Which pairs keep to the budgets 0, 1, 2, 3 along the ring from segment start."""
    d = a ^ b
    turn = (start * 16).astype(np.uint64)
    d = (d >> turn) | (d << ((np.uint64(64) - turn) & np.uint64(63)))
    ok = np.bitwise_count(d & np.uint64(0xFFFFFFFF)) <= 1
    return ok & (np.bitwise_count(d & np.uint64(0xFFFFFFFFFFFF)) <= 2) & (np.bitwise_count(d) <= RADIUS)


def _dense(fps: np.ndarray, start: int) -> tuple[list, list]:
    """Links that connect a large group as all its links would."""
    label, left, right = np.arange(len(fps)), [], []
    for r in range(len(fps) - 1):
        rest = np.flatnonzero(label[r + 1 :] != label[r]) + r + 1
        hit = rest[_chained(fps[rest], fps[r], np.full(1, start))]
        if len(hit):
            names, first = np.unique(label[hit], return_index=True)
            label[np.isin(label, names)] = label[r]
            left += [fps[r]] * len(names)
            right += list(fps[hit[first]])
    return left, right


def _links(keys: np.ndarray, fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Links inside groups of equal key; keys are sorted, their lowest two bits name the first segment."""
    start = (keys & 3).astype(np.int64)
    edge = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1], True])
    size = np.diff(edge)
    left, right = [], []
    for g in np.flatnonzero(size > LARGE):
        a, b = _dense(fps[edge[g] : edge[g + 1]], int(start[edge[g]]))
        left.append(np.array(a, np.uint64))
        right.append(np.array(b, np.uint64))
    behind = np.repeat(edge[1:], size) - np.arange(len(keys)) - 1
    behind[np.repeat(size > LARGE, size)] = 0
    at, lag = np.flatnonzero(behind > 0), 1
    while len(at):
        ok = at[_chained(fps[at], fps[at + lag], start[at])]
        left.append(fps[ok])
        right.append(fps[ok + lag])
        lag += 1
        at = at[behind[at] >= lag]
    none = np.zeros(0, np.uint64)
    return np.concatenate([none, *left]), np.concatenate([none, *right])


def _search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links of a partition that is sorted by key; the last key of a batch waits for the next batch."""
    keys, fps = [], []

    def out(k: np.ndarray, f: np.ndarray) -> pa.RecordBatch:
        a, b = _links(k, f)
        return pa.record_batch([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], ["a", "b"])

    for batch in batches:
        k, f = (batch.column(i).to_numpy(zero_copy_only=False) for i in (0, 1))
        if not len(k):
            continue
        cut_at = int(np.searchsorted(k, k[-1])) if k[0] != k[-1] else 0
        if cut_at or (keys and keys[-1][-1] != k[0]):
            done_k, done_f = np.concatenate([*keys, k[:cut_at]]), np.concatenate([*fps, f[:cut_at]])
            yield out(done_k, done_f.view(np.uint64))
            keys, fps = [], []
        keys.append(k[cut_at:])
        fps.append(f[cut_at:])
    if keys:
        yield out(np.concatenate(keys), np.concatenate(fps).view(np.uint64))


def _segment(i: int, at: int, width: int):
    """width bits of the fingerprint from bit at of segment i, around the ring."""
    return F.shiftrightunsigned(F.col("fp"), (i % 4) * 16 + at).bitwiseAND(F.lit((1 << width) - 1))


def links(fps: DataFrame) -> DataFrame:
    """a, b: links between the distinct values of fp, enough to connect whatever all links connect."""
    keys = [(_segment(i, 0, 16) * 512 + half * 256 + _segment(i + 1, 8 * half, 8)) * 4 + i for i in range(4) for half in (0, 1)]
    rows = cut(fps.select("fp").distinct().select("fp", F.explode(F.array(*keys)).alias("key")))
    hot = rows.groupBy("key").count().where(F.col("count") > HOT).select("key", F.lit(True).alias("hot"))
    n_hot = hot.count()
    if n_hot:
        longer = []
        for i in range(4):
            parts = [(a, _segment(i + 2, lo, w), b, _segment(i + 3, 4 * b, 4)) for a, (lo, w) in enumerate([(0, 5), (5, 5), (10, 6)]) for b in range(4)]
            longer.append(F.array(*[F.col("key") + F.shiftleft((F.lit(a * 4 + b + 1).cast("long") * 64 + x) * 16 + y, 28) for a, x, b, y in parts]))
        chosen = F.when(F.col("hot"), F.element_at(F.array(*longer), (F.col("key") % 4 + 1).cast("int"))).otherwise(F.array("key"))
        rows = rows.join(small(hot, n_hot), "key", "left").select(F.explode(chosen).alias("key"), "fp")
    return rows.select("key", "fp").repartition("key").sortWithinPartitions("key").mapInArrow(_search, "a long, b long").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, fingerprint (hex), component_id: the least doc_id that links reach."""
    found = cut(fingerprints(docs, id_col, text_col))
    known = found.groupBy("fp").agg(F.min("doc_id").alias("least"))
    labels = components(links(known))
    known = known.join(labels, known.fp == labels.node, "left").select("fp", "least", F.coalesce("label", "fp").alias("label"))
    least = known.groupBy("label").agg(F.min("least").alias("component_id"))
    owned = known.join(least, "label").select("fp", "component_id")
    return found.join(owned, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The document with the least id of each component, with all columns; rows without an id stay."""
    least = near_duplicates(docs, id_col, text_col).where("doc_id = component_id").select("doc_id")
    return first_copies(docs, least, id_col, text_col)
