"""Language by nearest centroid: TF-IDF vectors of character n-grams, several centroids a language, cosine.

Letters in lower case, everything else as one space, give bigrams and trigrams, hashed to DIMS places. Document
frequencies come from every document that may be learned from; spherical k-means of each language works on a
sample: of each language as many documents as its part of SAMPLE, give or take what chance does, chosen by a hash of
id and text over the whole language. Equal rows count once in the sample. The prediction is the language of the
nearest centroid. A text is rejected if its cosine is under REJECT times what all but QUANTILE of its language's
sample reach, or if it has no letter; texts with fewer than LEAST n-grams tell too little to be rejected by distance.

Nulls: a null text, or one without a letter, is `und` with score 0; a null language is not learned. Repeated rows
each get a row, and count as often in learning. With nothing to learn from, all is `und`. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import give_back, narrow, trimmed

DIMS, CENTROIDS, SAMPLE, ROUNDS = 1 << 13, 6, 4000, 12
REJECT, QUANTILE, LEAST = 0.5, 0.01, 60
#: Texts that are compared with the centroids at once; characters that are hashed at once.
BLOCK, CHUNK = 64, 1 << 18


@cache
def _letters() -> np.ndarray:
    return np.fromiter((chr(i).isalpha() for i in range(0x110000)), bool, 0x110000)


def counts(text: str) -> np.ndarray | None:
    """How often each place is hit; None without a letter. Long texts are taken in pieces that overlap."""
    total = None
    for at in range(0, len(text), CHUNK):
        c = np.frombuffer(text[max(at - 2, 0) : at + CHUNK].lower().encode("utf-32-le", "replace"), np.uint32)
        letter = _letters()[c]
        if not letter.any():
            continue
        c = np.where(letter, c, 32)
        c = c[letter | np.r_[True, letter[:-1]]]  # one space for many
        c = np.concatenate([[32], c, [32]]).astype(np.uint32)
        two = c[:-1] * np.uint32(0x9E3779B1) + c[1:] * np.uint32(0x85EBCA77)
        three = (two[:-1] ^ (two[:-1] >> np.uint32(15))) * np.uint32(0xC2B2AE3D) + c[2:] * np.uint32(0x27D4EB2F)
        places = np.concatenate([two >> np.uint32(19), ((three ^ (three >> np.uint32(13))) * np.uint32(0x165667B1)) >> np.uint32(19)])
        got = np.bincount(places, minlength=DIMS)
        total = got if total is None else total + got
    return total


def _weighted(tf: np.ndarray, idf: np.ndarray) -> np.ndarray:
    v = np.log1p(tf).astype(np.float32) * idf
    return v / np.maximum(np.linalg.norm(v, axis=-1, keepdims=True), 1e-9)


def _frequencies(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    df, n = np.zeros(DIMS, np.int64), 0
    for batch in batches:
        for t in batch.column(0):
            if t.is_valid and (c := counts(t.as_py())) is not None:
                df += c > 0
                n += 1
    yield pa.record_batch([pa.array(np.r_[-1, np.arange(DIMS)]), pa.array(np.r_[n, df])], ["place", "n"])


def _vectors(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        langs, keys, places, hits = [], [], [], []
        for lang, key, t in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
            if (c := counts(t.as_py())) is not None:
                langs.append(lang)
                keys.append(key)
                places.append(at := np.flatnonzero(c).astype(np.int32))
                hits.append(c[at].astype(np.int32))
        lists = [pa.array(x, pa.list_(pa.int32())) for x in (places, hits)]
        yield pa.record_batch([pa.array(langs, pa.string()), pa.array(keys, pa.int64()), *lists], ["lang", "key", "places", "hits"])


def _k_means(x: np.ndarray, k: int) -> np.ndarray:
    """Centroids on the sphere; each next seed is the vector farthest from those so far."""
    seeds = [0]
    near = x @ x[0]
    while len(seeds) < min(k, len(x)):
        seeds.append(int(near.argmin()))
        near = np.maximum(near, x @ x[seeds[-1]])
    c = x[seeds]
    for _ in range(ROUNDS):
        own = (x @ c.T).argmax(axis=1)
        sums = np.stack([x[own == j].sum(axis=0) if (own == j).any() else c[j] for j in range(len(c))])
        c = sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-9)
    return c.astype(np.float32)


class Model:
    """langs, idf, centroids (rows), owner (a language's place for each row), floor (a cosine for each language)."""

    def __init__(self, langs: list[str], idf: np.ndarray, centroids: np.ndarray, owner: np.ndarray, floor: np.ndarray):
        self.langs, self.idf, self.centroids, self.owner, self.floor = langs, idf, centroids, owner, floor


def learn(labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> Model:
    rows = narrow(labelled, doc_id=id_col, text=text_col, lang=lang_col).where("lang IS NOT NULL AND text IS NOT NULL")
    size = {r["lang"]: r["count"] for r in rows.groupBy("lang").count().collect()}
    df = np.zeros(DIMS + 1, np.int64)
    for r in rows.select("text").mapInArrow(trimmed(_frequencies), "place long, n long").groupBy("place").agg(F.sum("n").alias("n")).collect():
        df[r["place"]] = r["n"]
    idf = (np.log((1 + df[-1]) / (1 + df[:DIMS])) + 1).astype(np.float32)
    a_lang = max(SAMPLE // max(len(size), 1), 1)
    share = F.lit(0.0)
    for lang, n in size.items():
        share = F.when(F.col("lang") == lang, F.lit(min(1.0, a_lang / n))).otherwise(share)
    key = F.xxhash64("doc_id", "text", F.lit("sample"))
    chosen = rows.withColumn("key", key).where(F.shiftrightunsigned("key", 11).cast("double") < share * float(1 << 53))
    chosen = chosen.groupBy("lang", "key").agg(F.first("text").alias("text")).select("lang", "key", "text")
    got: dict[str, list] = {}
    for r in chosen.mapInArrow(trimmed(_vectors), "lang string, key long, places array<int>, hits array<int>").toLocalIterator():
        got.setdefault(r["lang"], []).append((r["key"], np.array(r["places"], np.int32), np.array(r["hits"], np.int32)))
    langs, centroids, floor = sorted(got), [], []
    for lang in langs:
        sample = sorted(got.pop(lang), key=lambda v: v[0])  # in one order, so that a run again learns the same
        x = np.zeros((len(sample), DIMS), np.float32)
        for row, (_, places, hits) in zip(x, sample):
            row[places] = hits
            row[:] = _weighted(row, idf)
        centroids.append(_k_means(x, CENTROIDS))
        floor.append(REJECT * np.quantile((x @ centroids[-1].T).max(axis=1), QUANTILE))
        del x
    give_back()
    owner = np.repeat(np.arange(len(langs)), [len(c) for c in centroids]) if langs else np.zeros(0, int)
    return Model(langs, idf, np.concatenate(centroids) if langs else np.zeros((0, DIMS), np.float32), owner, np.array(floor))


def _judge(texts: pa.Array, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Language, cosine and rejection of each text."""
    n = len(texts)
    lang, score, rejected = np.full(n, "und", object), np.zeros(n), np.ones(n, bool)
    at, tf = [], []

    def flush() -> None:
        if at and len(model.langs):
            cos = _weighted(np.stack(tf), model.idf) @ model.centroids.T
            best = cos.argmax(axis=1)
            own = model.owner[best]
            lang[at] = np.array(model.langs, object)[own]
            score[at] = np.clip(cos[np.arange(len(at)), best], 0, 1)
            rejected[at] = (score[at] < model.floor[own]) & (np.sum(tf, axis=1) >= LEAST)
        at.clear()
        tf.clear()

    for i, t in enumerate(texts):
        if t.is_valid and (c := counts(t.as_py())) is not None:
            at.append(i)
            tf.append(c)
            if len(at) == BLOCK:
                flush()
    flush()
    return lang, score, rejected


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, lang_pred, score (the cosine), rejected."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lang, score, rejected = _judge(batch.column(1), model)
            yield pa.record_batch([batch.column(0), pa.array(lang, pa.string()), pa.array(score), pa.array(rejected)], ["doc_id", "lang_pred", "score", "rejected"])

    rows = narrow(docs, doc_id=id_col, text=text_col)
    return rows.mapInArrow(trimmed(run), f"doc_id {dict(rows.dtypes)['doc_id']}, lang_pred string, score double, rejected boolean")


def accepted(docs: DataFrame, model: Model, text_col: str = "text") -> DataFrame:
    """The rows of docs that aren't rejected, with all their columns."""
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield batch.filter(pa.array(~_judge(batch.column(at), model)[2]))

    return docs.mapInArrow(trimmed(run), docs.schema)
