"""Toxicity of texts after undoing obfuscation: a noisy channel decoded by Viterbi, then a learned lexicon.

1. Character trigrams of every document, over 64 symbols, make a language model.
2. Words that mix letters with look-alike characters, letters spelled out with gaps, and letters repeated three
   times or more become lattices: a character may stand for itself or for what it looks like, a repeated letter for
   one, two or all of them. Viterbi takes the path that the model finds likeliest, less a cost for each change. Letters
   that are spelled out are read twice: as one word, and with breaks at gaps where the model favours them.
3. Words of restored texts, and their beginnings, are counted once a document by label, copies of a text once.
   A feature's weight is the lower bound of the share of toxic documents among those that have it.
4. A document's score is the chance that at least one of its different words is toxic, by its best feature.

Labels are learned from at most LABELLED rows, chosen by a hash of their ids where there are more; the language
model and the scores cover all documents. Every reliable feature is kept: their number is bounded by what that many
labelled texts hold. Words and runs of any length are read.

Nulls: a null or empty text has the base rate; null labels are not learned. Repeated rows each get a score.
With nothing to learn from, every score is the base rate, 0 then. Other columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Callable, Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import BROADCAST_ROWS, narrow, small

LABELLED, LEAST, RELIABLE, STARTS = BROADCAST_ROWS, 3, 0.42, (4, 5, 6)
SYMBOLS, CHANGE, BREAK, KEPT, Z = 64, 1.5, 1.0, 500_000, 2.0
#: What look-alike characters may stand for.
LOOKS = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "€": "e"}
_MARKS = re.escape("".join(LOOKS))
_MIXED = rf"[^\W_]*(?:[^\W\d_][{_MARKS}]+[^\W\d_]|[{_MARKS}][^\W\d_])[{_MARKS}\w]*"
_SPACED = r"(?<!\w)\w(?:[ .\-_*]\w){3,}(?!\w)"
_REPEATED = r"[^\W_]*([^\W\d_])\1\1[^\W_]*"
_SUSPECT = re.compile(f"{_SPACED}|{_MIXED}|{_REPEATED}")
_SPELLED, _GAPS = re.compile(_SPACED), re.compile(r"[ .\-_*]\w[ .\-_*]\w[ .\-_*]")  # every spelled-out word holds such gaps
_WORD = re.compile(r"[^\W\d_]+")


@cache
def _symbol() -> np.ndarray:
    """0 for what isn't a letter, 1 to 26 for a to z, 27 to 63 for other letters."""
    table = np.fromiter(((27 + i % 37) if chr(i).isalpha() else 0 for i in range(0x110000)), np.int64, 0x110000)
    table[ord("a") : ord("z") + 1] = np.arange(1, 27)
    return table


def symbols(text: str) -> np.ndarray:
    return _symbol()[np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)]


def _trigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    n = np.zeros(SYMBOLS**3, np.int64)
    for batch in batches:
        for t in batch.column(0):
            text = (t.as_py() or "").lower()
            for at in range(0, len(text), 1 << 20):
                s = np.concatenate([[0], symbols(text[at : at + (1 << 20)]), [0]])
                n += np.bincount((s[:-2] * SYMBOLS + s[1:-1]) * SYMBOLS + s[2:], minlength=len(n))
    at = np.flatnonzero(n)
    yield pa.record_batch([pa.array(at), pa.array(n[at])], ["gram", "n"])


def language_model(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """Log probabilities of a symbol after two others, from all documents."""
    n = np.zeros(SYMBOLS**3)
    for r in narrow(docs, text=text_col).mapInArrow(_trigrams, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")).collect():
        n[r["gram"]] = r["n"]
    n = n.reshape(SYMBOLS, SYMBOLS, SYMBOLS)
    two = n.sum(axis=0)  # the last two symbols
    back = (two + 0.5) / (two.sum(axis=1, keepdims=True) + 0.5 * SYMBOLS)
    return np.log((n + 8 * back[None]) / (n.sum(axis=2, keepdims=True) + 8)).astype(np.float32)


def lattice(token: str, breaks: bool = False) -> list[list[tuple[str, float]]]:
    """For each place of a token: what it may stand for, and at what cost. Gaps between single letters are nothing, or
    with breaks what may end a word."""
    spelled = bool(_SPELLED.fullmatch(token))
    if spelled:
        token = token[::2]
    places, at = [], 0
    while at < len(token):
        c, end = token[at], at + 1
        while end < len(token) and token[end] == c and not (spelled and breaks):
            end += 1
        ways = [c, *LOOKS.get(c, "")] if not c.isalpha() else [c]
        n = end - at
        times = {n: 0.0, 1: CHANGE, 2: CHANGE} if n > 2 else {n: 0.0}
        if spelled and breaks and places:
            places.append([("", 0.0), (" ", BREAK)])
        places.append([(w * k, cost + CHANGE * (w != c)) for w in ways for k, cost in times.items()])
        at = end
    return places


def decode(token: str, model: np.ndarray, breaks: bool = False) -> str:
    """The likeliest reading of a token, between blanks; paths are kept as links, so the work grows with the length."""
    table = _symbol()
    best: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
    for ways in [*lattice(token, breaks), [(" ", 0.0)]]:
        after: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        for (a, b), (score, said) in best.items():
            for way, cost in ways:
                x, y, now = a, b, score - cost
                for c in way if len(way) < 4 else way[:3]:  # letters that go on as they are change the state no more
                    z = int(table[ord(c)])
                    now += float(model[x, y, z]) - 2.0 * (z == 0 and c != " ")
                    x, y = y, z
                if len(way) > 3:
                    now += (len(way) - 3) * (float(model[x, y, z]) - 2.0 * (z == 0 and c != " "))
                if (x, y) not in after or after[x, y][0] < now:
                    after[x, y] = (now, (said, way))
        best = after
    said, ways = max(best.values(), key=lambda v: v[0])[1], []
    while said:
        said, way = said
        ways.append(way)
    return "".join(reversed(ways)).strip()


class Reader:
    """What `of` makes of the words of a text's different tokens and spelled-out words, restored; tokens are read once."""

    def __init__(self, model: np.ndarray, of: Callable[[list[str]], Iterable]):
        self.model, self.of, self.read = model, of, {}

    def restore(self, match: re.Match) -> str:
        apart = f" {decode(match[0], self.model, True)}" if _SPELLED.fullmatch(match[0]) else ""
        return f"{decode(match[0], self.model)}{apart} {match[0]}"

    def token(self, token: str) -> tuple:
        if len(self.read) >= KEPT:
            self.read.clear()
        got = self.read[token] = tuple(self.of(sorted(set(_WORD.findall(_SUSPECT.sub(self.restore, token))))))
        return got

    def __call__(self, text: str) -> set:
        text = text.lower()
        found: set = set()
        different = set(text.split())
        if _GAPS.search(text):
            different.update(m[0] for m in _SPELLED.finditer(text))
        known = self.read.get
        for t in different:
            if (got := known(t)) is None:
                got = self.token(t)
            if got:
                found.update(got)
        return found


def features(word: str) -> list[int]:
    """A word and its beginnings, as numbers."""
    names = [f"={word}", *(f"^{word[:k]}" for k in STARTS if len(word) >= k)]
    return [xxhash.xxh64_intdigest(n) - (1 << 63) for n in names]


class Lexicon:
    """weight: a feature's share of toxic documents, at least; base: the share among all."""

    def __init__(self, weight: dict[int, float], base: float, model: np.ndarray):
        self.weight, self.base, self.model = weight, base, model


def learn(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic") -> Lexicon:
    """docs: for the language model; labels: what may be learned from."""
    model = language_model(docs, text_col)
    known = narrow(labels, doc_id=id_col, toxic=label_col).where("doc_id IS NOT NULL AND toxic IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    n = known.count()
    share = min(1.0, 0.95 * LABELLED / max(n, 1))
    known = known.where(F.pmod(F.xxhash64("doc_id", F.lit("label")), F.lit(1_000_000)) < share * 1_000_000)
    texts = narrow(docs, doc_id=id_col, text=text_col).join(F.broadcast(known), "doc_id")  # LABELLED rows at most
    once = texts.groupBy(F.xxhash64("text").alias("copy")).agg(F.min("doc_id").alias("doc_id")).select("doc_id").distinct()
    texts = texts.join(small(once, min(n, LABELLED)), "doc_id", "left_semi")
    total, toxic = texts.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(model, lambda words: {f for w in words for f in features(w)})
        for batch in batches:
            n: tuple[Counter, Counter] = (Counter(), Counter())
            for text, label in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                n[int(label > 0)].update(reader(text or ""))
            every = np.fromiter(set(n[0]) | set(n[1]), np.int64)
            yield pa.record_batch([pa.array(every), *[pa.array([n[k][f] for f in every.tolist()], pa.int64()) for k in (1, 0)]], ["feature", "toxic", "other"])

    sums = texts.select("text", "toxic").mapInArrow(count, "feature long, toxic long, other long").groupBy("feature").agg(F.sum("toxic").alias("toxic"), F.sum("other").alias("other"))
    n_, p = F.col("toxic") + F.col("other"), F.col("toxic") / (F.col("toxic") + F.col("other"))
    low = (p + Z * Z / (2 * n_) - Z * F.sqrt(p * (1 - p) / n_ + Z * Z / (4 * n_ * n_))) / (1 + Z * Z / n_)
    base = toxic / total if total else 0.0
    kept = sums.where(F.col("toxic") >= LEAST).withColumn("weight", low).where(F.col("weight") >= max(RELIABLE, 2 * base))
    return Lexicon({r["feature"]: r["weight"] for r in kept.select("feature", "weight").collect()}, base, model)


def score(docs: DataFrame, lexicon: Lexicon, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, score, n_toxic_words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def toxic(words: list[str]) -> list[tuple[str, float]]:
            weighed = ((w, max(lexicon.weight.get(f, 0.0) for f in features(w))) for w in words)
            return [x for x in weighed if x[1]]

        reader = Reader(lexicon.model, toxic)
        for batch in batches:
            scores, hits = [], []
            for t in batch.column(1):
                left, n = 1 - lexicon.base, 0
                for _, p in sorted(reader(t.as_py() or "")):
                    left, n = left * (1 - p), n + 1
                scores.append(1 - left)
                hits.append(n)
            yield pa.record_batch([batch.column(0), pa.array(scores, pa.float64()), pa.array(hits, pa.int64())], ["doc_id", "score", "n_toxic_words"])

    rows = narrow(docs, doc_id=id_col, text=text_col)
    return rows.mapInArrow(run, f"doc_id {dict(rows.dtypes)['doc_id']}, score double, n_toxic_words long")
