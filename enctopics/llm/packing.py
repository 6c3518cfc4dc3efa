"""Best-fit packing of token sequences with large-item matching, on the histogram of their lengths.

Texts are tokenized once, plain ones many at a time, so that each different part of a word is looked up once for all of them; longer ones are cut into pieces of the capacity. The plan is made from how many pieces
have each length, at most CAPACITY numbers: lengths above a third of the capacity are matched greedily, the longest
with the longest that still fits, at most two a bin; the smaller ones, longest first, go where they leave least.
A step of the plan fills many equal bins at once, so its size depends on the capacity and not on the documents.
Pieces find their bin by their rank within their length; ranks are counted in parallel, popular lengths in as many
parts as their pieces ask for. A text that spells a special token of the tokenizer gets that token's id, as the tokenizer has it.

Nulls: a null text is empty, and an empty text is the end token alone; null ids are ordinary rows. Repeated rows
are packed each. An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

import re
import struct
import zlib
from bisect import bisect_left, insort
from collections.abc import Iterable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from enctopics.llm.common import cut, narrow, trimmed

CAPACITY, END = 4096, 1
#: Pieces of one length that are ranked together, at least, and parts of all lengths, at most, besides one a length; words and parts of words kept by a worker.
PART, PARTS, KEPT = 1_000, 100_000, 200_000
#: Words of these characters alone are split as the tokenizer does by the pattern below; others go to the tokenizer.
_PLAIN = re.compile(r"[!-~À-ÖØ-öø-ſ¡«»¿]+")
#: Texts of these characters alone are split many at a time, about CHUNK characters; each of them is as long in lower case.
_PLAIN_TEXT, CHUNK = re.compile(r"[!-~À-ÖØ-öø-įı-ſ¡«»¿ \t\n\r\x0b\x0c]*"), 1 << 21
_PARTS = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|\d|(?:[^\s\w]|_)+")
#: White space for Python that isn't for the tokenizer.
_ODD = re.compile("[\x1c-\x1f]")
_SPACE = re.compile(r"\s")
#: What a byte of such texts belongs to: white space, letters, digits, others; the second byte of a character to what the first does.
_BLANK, _LETTER, _DIGIT, _OTHER, _SECOND = range(5)
_KINDS = np.full(256, _OTHER, np.uint8)
_KINDS[list(b" \t\n\r\x0b\x0c")], _KINDS[ord("a") : ord("z") + 1], _KINDS[ord("0") : ord("9") + 1], _KINDS[0xC3:0xC6], _KINDS[0x80:0xC0] = _BLANK, _LETTER, _DIGIT, _LETTER, _SECOND


def _starts(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which bytes of plain lower-case text begin a part, as _PARTS has them, and which aren't white space; blanks have to be around it."""
    kind = _KINDS[data]
    second = np.flatnonzero(kind == _SECOND)
    kind[second] = kind[second - 1]
    begins = np.zeros(len(data), bool)
    begins[1:] = (kind[1:] != kind[:-1]) | (kind[1:] == _DIGIT)
    begins[second] = False
    at = np.flatnonzero((data[1:-3] == ord("'")) & (kind[:-4] != _OTHER)) + 1  # 's and its like, where a run of others begins
    one, two = data[at + 1], data[at + 2]
    length = np.where(np.isin(one, list(b"stmd")), 2, 0) + np.where(((one == ord("r")) | (one == ord("v"))) & (two == ord("e")) | (one == ord("l")) & (two == ord("l")), 3, 0)
    at, length = at[length > 0], length[length > 0]
    begins[at + 1] = False
    begins[at + length] = True
    return begins, kind != _BLANK


@cache
def _bytes() -> dict[int, str]:
    """The visible character that byte-level vocabularies have for each byte."""
    visible = [*range(33, 127), *range(161, 173), *range(174, 256)]
    return {b: chr(b) for b in visible} | {b: chr(256 + i) for i, b in enumerate(sorted({*range(256)} - {*visible}))}


class Encoder:
    """Ids of a text as little-endian 32-bit bytes, equal to the tokenizer's; words are encoded once, as far as they are kept."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        added = [re.escape(t.content) for t in self.tokenizer.get_added_tokens_decoder().values()]
        self.added = re.compile("|".join(added) or r"(?!)", re.IGNORECASE)  # texts with one of these go to the tokenizer whole
        self.model = self.tokenizer.model  # asking for it anew costs as much as a part
        self.words: dict[str, bytes] = {}
        self.parts: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def part(self, part: str) -> bytes:
        if (got := self.parts.get(part)) is None:
            if len(self.parts) >= KEPT // 2:
                self.older, self.parts = self.parts, {}
            if (got := self.older.get(part)) is None:
                seen = part if part.isascii() else part.encode().decode("latin-1").translate(_bytes())
                ids = [t.id for t in self.model.tokenize(seen)]
                got = struct.pack(f"<{len(ids)}I", *ids)
            self.parts[part] = got
        return got

    def word(self, word: str) -> bytes:
        if len(self.words) >= KEPT:
            self.words.clear()
        got = self.words[word] = b"".join(map(self.part, _PARTS.findall(word.lower()))) if _PLAIN.fullmatch(word) else self.whole(word)
        return got

    def forget(self) -> None:
        self.words.clear()
        self.parts, self.older = {}, {}

    def __call__(self, text: str) -> bytes:
        if _ODD.search(text) or self.added.search(text):
            return self.whole(text)
        known = self.words.get
        return b"".join([known(w) or self.word(w) for w in text.split()])

    def _plain(self, texts: list[str]) -> list[bytes]:
        """Ids of plain texts: each different part is looked up once."""
        raw = [t.lower().encode() for t in texts]
        data = np.frombuffer(b" " + b" ".join(raw) + b"    ", np.uint8)
        begins, solid = _starts(data)
        begins &= solid
        first = np.flatnonzero(begins)
        packed, at = data[solid], np.flatnonzero(begins[solid]).astype(np.int32)
        offsets = np.append(at, np.int32(len(packed)))
        found = pa.Array.from_buffers(pa.string(), len(at), [None, pa.py_buffer(offsets), pa.py_buffer(packed)]).dictionary_encode()
        known, codes = self.parts.get, found.indices.to_numpy()
        ids = [known(p) or self.part(p) for p in found.dictionary.to_pylist()]
        sizes = np.fromiter(map(len, ids), np.int64, len(ids)) // 4
        counts, begin = sizes[codes], np.cumsum(sizes) - sizes
        ends = np.cumsum(counts)
        gathered = np.frombuffer(b"".join(ids), "<u4")[np.repeat(begin[codes] - ends + counts, counts) + np.arange(counts.sum())]
        past = np.cumsum([len(r) + 1 for r in raw]) + 1  # where each text ends, the blank behind it included
        cuts = np.append(0, ends)[np.searchsorted(first, past)].tolist()
        return [gathered[a:z].tobytes() for a, z in zip([0, *cuts], cuts)]

    def many(self, texts: Iterable[str]) -> list[bytes]:
        """Ids of each text."""
        out: list[list[bytes]] = []
        held: list[tuple[int, str]] = []
        size = 0

        def flush() -> None:
            for (row, _), ids in zip(held, self._plain([t for _, t in held])):
                out[row].append(ids)
            held.clear()

        for row, text in enumerate(texts):
            out.append([])
            if self.added.search(text) or not _PLAIN_TEXT.fullmatch(text):
                out[row].append(self(text))
                continue
            at = 0
            while at < len(text):
                end = m.start() if (m := _SPACE.search(text, at + CHUNK)) else len(text)
                held.append((row, text[at:end]))
                size, at = size + end - at, end
                if size >= CHUNK:
                    flush()
                    size = 0
        flush()
        return [b"".join(parts) for parts in out]


@cache
def encoder(path: str) -> Encoder:
    return Encoder(path)


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: the tokens of each text, its end token included."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, end = encoder(tokenizer), np.array([END], "<u4").tobytes()
        for batch in batches:
            out = []
            for row, ids in enumerate(encode.many(t.as_py() or "" for t in batch.column(1))):
                ids += end
                out += [(row, k, at // 4, min(4 * capacity, len(ids) - at) // 4, zlib.crc32(ids[at : at + 4 * capacity])) for k, at in enumerate(range(0, len(ids), 4 * capacity))]
            cols = list(zip(*out)) if out else [()] * 5
            ids_of = batch.column(0).take(pa.array(cols[0], pa.int64()))
            yield pa.record_batch([ids_of, pa.array(cols[1], pa.int32()), *[pa.array(c, pa.int64()) for c in cols[2:]]], ["doc_id", "piece", "start", "length", "ids_crc32"])
        encode.forget()  # the worker goes on to other stages

    rows = narrow(docs, doc_id=id_col, text=text_col)
    return rows.mapInArrow(trimmed(run), f"doc_id {dict(rows.dtypes)['doc_id']}, piece int, start long, length long, ids_crc32 long")


class Plan:
    """Steps (length, first rank, bins, a bin, first bin, offset): ranks from the first one on, a bin after the other."""

    def __init__(self, histogram: dict[int, int], capacity: int = CAPACITY):
        self.capacity, self.left, self.steps, self.bins = capacity, dict(histogram), [], 0
        self.rank = dict.fromkeys(histogram, 0)
        self.open: dict[int, list[tuple[int, int]]] = {}  # by free space: first bin and number of bins
        self.spaces: list[int] = []
        large = sorted((x for x in histogram if 3 * x > capacity), reverse=True)
        self._match(large)
        for x in sorted((x for x in histogram if 3 * x <= capacity), reverse=True):
            self._best_fit(x)

    def _put(self, length: int, bins: int, each: int, first: int, used: int) -> None:
        self.steps.append((length, self.rank[length], bins, each, first, used))
        self.rank[length] += bins * each
        self.left[length] -= bins * each

    def _free(self, space: int, first: int, bins: int) -> None:
        if space > 0 and bins:
            if space not in self.open:
                self.open[space] = []
                insort(self.spaces, space)
            self.open[space].append((first, bins))

    def _new(self, bins: int) -> int:
        self.bins += bins
        return self.bins - bins

    def _match(self, large: list[int]) -> None:
        rising = large[::-1]
        for x in large:
            while self.left[x]:
                at = bisect_left(rising, self.capacity - x + 1) - 1
                while at >= 0 and (not self.left[rising[at]] or rising[at] == x and self.left[x] < 2):
                    if not self.left[rising[at]]:
                        rising.pop(at)
                    at -= 1
                if at < 0:
                    n = self.left[x]
                    first = self._new(n)
                    self._put(x, n, 1, first, 0)
                    self._free(self.capacity - x, first, n)
                    break
                y = rising[at]
                n = self.left[x] // 2 if x == y else min(self.left[x], self.left[y])
                first = self._new(n)
                self._put(x, n, 1, first, 0)
                self._put(y, n, 1, first, x)
                self._free(self.capacity - x - y, first, n)

    def _best_fit(self, x: int) -> None:
        while self.left[x]:
            at = bisect_left(self.spaces, x)
            if at == len(self.spaces):
                each = self.capacity // x
                n = max(self.left[x] // each, 1)
                self._free(self.capacity, self._new(n), n)
                continue
            space = self.spaces[at]
            first, bins = self.open[space].pop()
            if not self.open[space]:
                del self.open[space]
                self.spaces.pop(at)
            each = min(space // x, self.left[x])
            n = min(bins, self.left[x] // each)
            self._put(x, n, each, first, self.capacity - space)
            self._free(space - each * x, first, n)
            self._free(space, first + n, bins - n)


def pack(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    found = cut(pieces(docs, tokenizer, capacity, id_col, text_col).withColumn("row", F.monotonically_increasing_id()))
    histogram = {r["length"]: r["count"] for r in found.groupBy("length").count().collect()}
    steps = sorted(Plan(histogram, capacity).steps)
    spark = docs.sparkSession
    part = max(PART, sum(histogram.values()) // PARTS)
    parts = spark.createDataFrame([(x, -(-n // part)) for x, n in histogram.items()], "length long, parts int")
    dealt = found.join(F.broadcast(parts), "length").withColumn("part", F.pmod(F.xxhash64("row"), F.col("parts")))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    bases = dealt.groupBy("length", "part").count().select("length", "part", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("base"))  # PARTS rows and one a length at most
    inside = Window.partitionBy("length", "part").orderBy("doc_id", "piece", "row")
    ranked = dealt.withColumn("n", F.row_number().over(inside)).join(F.broadcast(bases), ["length", "part"]).select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("base") + F.col("n") - 1).alias("rank"))
    table = np.array(steps, np.int64).reshape(-1, 6)
    key = (table[:, 0] << 44) + table[:, 1]

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            length, rank = (batch.column(i).to_numpy(zero_copy_only=False) for i in (3, 5))
            step = table[np.searchsorted(key, (length << 44) + rank, "right") - 1]
            past, each = rank - step[:, 1], step[:, 3]
            out = [pa.array(step[:, 4] + past // each), pa.array(step[:, 5] + past % each * length)]
            yield pa.record_batch([*batch.columns[:5], *out], ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"])

    return ranked.mapInArrow(place, f"doc_id {dict(ranked.dtypes)['doc_id']}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
