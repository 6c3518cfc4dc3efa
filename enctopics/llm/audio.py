"""Chroma fingerprints of recordings, and alignment of recordings by them.

Samples become overlapping frames, their spectra 12 pitch classes. Sixteen rectangle filters over the integral image
of these, each as wide as its place in WIDTHS says, compare the logarithms of two areas; two bits of each make one 32-bit
integer a frame. Recordings share integers where they sound alike: for two recordings, a histogram of the
differences of places finds their offset, and the share of unequal bits over the overlap decides. Only offsets count at
which OVERLAP frames, or all of the shorter recording, lie over each other: fewer frames agree by chance. Of under SURE
frames fewer bits may be wrong, so that chance brings an overlap no more easily than SURE frames with ERROR of their bits wrong.

Recordings of one fingerprint form a class, and are compared once. Integers meet in an index where one
of three blocks of their bits is equal: cuts between two frames and noise leave few integers as they were, while blocks
survive up to the accepted error. So short keys meet often, and queries and recordings are gone through list by list,
each two lists in one task: the work grows with queries times recordings. A null or empty recording, or one too short for a filter, has an empty fingerprint and matches nothing.
Repeated rows each get a row. An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

import io
import wave
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import cut, narrow, small

RATE, FRAME, HOP, SPAN = 4000, 1024, 256, 12
WIDTHS, EDGES = (2, 4, 8, 12), (-0.25, 0.0, 0.25)
ERROR, VOTES, OVERLAP, SURE = 0.25, 2, 16, 40
#: First bit and width of the blocks under which integers meet; cells of a histogram that is kept whole.
BLOCKS, DENSE = ((0, 11), (11, 11), (22, 10)), 1 << 22


@cache
def _filters() -> list[tuple[int, int, int, int]]:
    """Kind, first pitch class, height and width of each filter."""
    return [(i % 4, (5 * i) % 9, 1 + i % 3, WIDTHS[i // 4]) for i in range(16)]


@cache
def _classes(rate: int) -> np.ndarray:
    """Pitch class of each place of a spectrum, as rows of 12 weights; from two octaves under to three over 440 Hz."""
    f = np.fft.rfftfreq(FRAME, 1 / rate)
    heard = (f >= 110) & (f <= 3520)
    at = np.mod(np.rint(12 * np.log2(np.where(heard, f, 440) / 440)), 12).astype(int)
    return (np.eye(12)[at] * heard[:, None]).astype(np.float32)


def chroma(samples: np.ndarray, rate: int = RATE) -> np.ndarray:
    """A row of 12 energies, of length 1, for each frame."""
    n = (len(samples) - FRAME) // HOP + 1
    if n < 1:
        return np.zeros((0, 12), np.float32)
    frames = np.lib.stride_tricks.sliding_window_view(samples.astype(np.float32), FRAME)[::HOP][:n]
    energy = np.abs(np.fft.rfft(frames * np.hanning(FRAME).astype(np.float32), axis=1)).astype(np.float32) ** 2 @ _classes(rate)
    return energy / np.maximum(np.linalg.norm(energy, axis=1, keepdims=True), 1e-9)


def fingerprint(samples: np.ndarray, rate: int = RATE) -> np.ndarray:
    """One unsigned 32-bit integer a frame, as far as the widest filter reaches."""
    c = chroma(samples, rate)
    n = len(c) - SPAN + 1
    if n < 1:
        return np.zeros(0, np.uint32)
    image = np.zeros((len(c) + 1, 13))
    image[1:, 1:] = c.cumsum(axis=0).cumsum(axis=1)
    t = np.arange(n)
    area = lambda x0, x1, y0, y1: image[t + x1, y1] - image[t + x0, y1] - image[t + x1, y0] + image[t + x0, y0]
    out = np.zeros(n, np.uint32)
    for kind, y, height, width in _filters():
        top, half, middle = y + height, width // 2, y + (height + 1) // 2
        if kind == 0:  # an area and what it leaves of all classes
            a, b = area(0, width, y, top), (area(0, width, 0, 12) - area(0, width, y, top)) * height / (12 - height)
        elif kind == 1:  # earlier and later
            a, b = area(0, half, y, top), area(half, width, y, top)
        elif kind == 2:  # lower and upper pitch classes
            a, b = area(0, width, y, middle), area(0, width, middle, top + 1) * (middle - y) / (top + 1 - middle)
        else:  # crosswise
            a, b = area(0, half, y, middle) + area(half, width, middle, top + 1), area(half, width, y, middle) + area(0, half, middle, top + 1)
        level = np.searchsorted(EDGES, np.log((a + 0.05) / (b + 0.05))).astype(np.uint32)
        out = (out << np.uint32(2)) | (level ^ (level >> np.uint32(1)))  # neighbouring levels differ in one bit
    return out


def read_wav(cell: bytes) -> tuple[np.ndarray, int]:
    """Samples, mixed to one channel, and rate of 8-, 16- or 32-bit WAV data; of anything else, or damaged data, none."""
    try:
        with wave.open(io.BytesIO(cell)) as w:
            kind = {1: "u1", 2: "<i2", 4: "<i4"}[w.getsampwidth()]
            raw = w.readframes(w.getnframes())
            wide = w.getsampwidth() * w.getnchannels()
            x = np.frombuffer(raw[: len(raw) // wide * wide], kind).astype(np.float64).reshape(-1, w.getnchannels())
            return (x - 128 if kind == "u1" else x).mean(axis=1), max(w.getframerate(), 1)
    except (wave.Error, EOFError, KeyError, ValueError, RuntimeError):
        return np.zeros(0), RATE


def melody(cell: list[float]) -> tuple[np.ndarray, int]:
    """A recording of a vector: a note for each of its numbers, a sixteenth of a second long."""
    v = np.asarray(cell, np.float64)
    step = RATE // 16
    pitch = 220 * 2 ** (np.mod(np.floor(v * 96), 24) / 12)
    phase = 2 * np.pi * np.cumsum(np.repeat(pitch, step)) / RATE
    return np.sin(phase) * np.repeat(0.5 + np.minimum(np.abs(v), 0.5), step), RATE


def fingerprints(media: DataFrame, id_col: str, media_col: str, read: Callable = read_wav) -> DataFrame:
    """id, frames: the fingerprint of each cell that read turns into samples and their rate."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for cell in batch.column(1):
                value = cell.as_py()
                out.append(fingerprint(*read(value)).view(np.int32) if value else np.zeros(0, np.int32))
            yield pa.record_batch([batch.column(0), pa.array(out, pa.list_(pa.int32()))], ["id", "frames"])

    rows = narrow(media, id=id_col, media=media_col)
    return rows.mapInArrow(run, f"id {dict(rows.dtypes)['id']}, frames array<int>")


def classes(prints: DataFrame) -> DataFrame:
    """class_id, frames, copies: recordings with the very same fingerprint, named by their least id."""
    found = prints.where(F.size("frames") > 0).groupBy(F.xxhash64("frames").alias("key"), F.hash("frames").alias("key2"))
    return found.agg(F.min("id").alias("class_id"), F.min("frames").alias("frames"), F.count("*").alias("copies")).drop("key", "key2")


def class_of(prints: DataFrame) -> DataFrame:
    """id, class_id, copies of each recording that has a fingerprint."""
    keyed = prints.where(F.size("frames") > 0).select("id", F.xxhash64("frames").alias("key"), F.hash("frames").alias("key2"))
    return keyed.join(keyed.groupBy("key", "key2").agg(F.min("id").alias("class_id"), F.count("*").alias("copies")), ["key", "key2"]).drop("key", "key2")


def _keys(frames: np.ndarray) -> list[np.ndarray]:
    """The blocks of each integer, as one array a block."""
    return [(frames >> np.uint32(at)) & np.uint32((1 << width) - 1) for at, width in BLOCKS]


class _Index:
    """Recordings, one after the other in an array, with their sorted keys."""

    def __init__(self, recordings: list[np.ndarray]):
        self.size = np.array([len(r) for r in recordings])
        self.frames = np.concatenate(recordings)
        self.first = np.cumsum(self.size) - self.size
        self.owner = np.repeat(np.arange(len(recordings)), self.size)
        self.place = np.arange(len(self.frames)) - self.first[self.owner]
        orders = [np.argsort(k, kind="stable") for k in _keys(self.frames)]
        self.masks: dict[int, np.ndarray] = {}  # cells of the histogram with enough overlap, for queries of one length
        self.sorted = [(k[o], o) for k, o in zip(_keys(self.frames), orders)]

    def over(self, n_query: int, owner: np.ndarray, offset: np.ndarray) -> np.ndarray:
        """Frames of a query that lie over frames of each owner at its offset."""
        return np.minimum(n_query - np.maximum(-offset, 0), self.size[owner] - np.maximum(offset, 0))

    def enough(self, n_query: int, owner: np.ndarray, offset: np.ndarray) -> np.ndarray:
        return self.over(n_query, owner, offset) >= np.minimum(OVERLAP, np.minimum(n_query, self.size[owner]))

    def best(self, query: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Recordings that share a key with the query, the offset with most votes (then the least), its votes."""
        hits, froms = [], []
        for key, (known, order) in zip(_keys(query), self.sorted):
            lo, n = np.searchsorted(known, key), np.searchsorted(known, key, "right")
            n -= lo
            skip = np.repeat(lo - np.cumsum(n) + n, n)
            hits.append(order[skip + np.arange(len(skip))])
            froms.append(np.repeat(np.arange(len(query)), n))
        hit, start = np.concatenate(hits), np.concatenate(froms)
        wide = len(query) + int(self.size.max())
        code = self.owner[hit] * wide + self.place[hit] - start + len(query)
        if len(self.size) * wide <= DENSE:
            votes = np.bincount(code, minlength=len(self.size) * wide).reshape(-1, wide)
            if len(query) not in self.masks:
                self.masks = {len(query): self.enough(len(query), np.arange(len(self.size))[:, None], np.arange(wide) - len(query))}
            votes *= self.masks[len(query)]
            at = votes.argmax(axis=1)
            most = votes[np.arange(len(at)), at]
            owner = np.flatnonzero(most)
            return owner, at[owner] - len(query), most[owner]
        code, votes = np.unique(code, return_counts=True)
        far = self.enough(len(query), code // wide, code % wide - len(query))
        code, votes = code[far], votes[far]
        code, votes = (x[np.lexsort((code, -votes, code // wide))] for x in (code, votes))
        owner, at = np.unique(code // wide, return_index=True)
        return owner, code[at] % wide - len(query), votes[at]

    def wrong(self, query: np.ndarray, owner: np.ndarray, offset: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Unequal bits, and frames, of the overlap of the query with each owner at its offset."""
        n = self.over(len(query), owner, offset)
        bits = np.zeros(len(owner), np.int64)
        start = self.first[owner] + np.maximum(offset, 0)
        run = max(1, DENSE // max(1, int(n.max(initial=1))))
        for at in range(0, len(owner), run):
            m = n[at : at + run]
            inside = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m)
            mine = query[np.repeat(np.maximum(-offset[at : at + run], 0), m) + inside]
            unequal = np.bitwise_count(mine ^ self.frames[np.repeat(start[at : at + run], m) + inside])
            bits[at : at + run] = np.add.reduceat(unequal.astype(np.int64), np.cumsum(m) - m)
        return bits, n


def allowed(n: np.ndarray, error: float = ERROR) -> np.ndarray:
    """The share of wrong bits up to which n frames count: chance has half of them wrong, give or take 1 / sqrt(n)."""
    return np.clip(0.5 - (0.5 - error) * np.sqrt(SURE / n), 0.0, error)


def _blocks(rows: DataFrame, name: str, frames: int) -> tuple[DataFrame, int]:
    """Recordings of like length as lists of about so many frames, and at most how many lists."""
    length = F.floor(F.log2(F.size("frames"))).cast("int")
    parts = {r["length"]: -(-r["n"] // max(1, frames >> r["length"])) for r in rows.groupBy(length.alias("length")).agg(F.count("*").alias("n")).collect()}
    many = F.element_at(F.create_map(*[F.lit(x) for kv in parts.items() for x in kv]), length) if parts else F.lit(1)
    block = F.struct(length, F.pmod(F.xxhash64("class_id"), many))
    return rows.groupBy(block.alias("block")).agg(F.collect_list(F.struct("class_id", "frames")).alias(name)).select(name), sum(parts.values())


def align(prints: DataFrame, queries: DataFrame, error: float = ERROR, votes: int = VOTES) -> DataFrame:
    """query_id (a class), class_id, copies, offset, votes, bit_error, n_frames: classes that sound like the query's.

    Queries and recordings meet in blocks, the stated queries against all rows.

    Of each two the offset with most votes, then the least offset, counts; the query's own class isn't listed.
    """
    every = cut(classes(prints))
    asked = cut(queries.join(every.select("class_id", "frames"), "class_id").distinct())
    (left, n_left), (right, n_right) = _blocks(asked, "asked", 1 << 12), _blocks(every.select("class_id", "frames"), "known", 1 << 16)
    kind = pa.list_(pa.int32())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                (q_ids, q), (ids, r) = ((x.field(0), x.field(1).cast(kind)) for x in (batch.column(i)[row].values for i in (0, 1)))
                index = _Index([x.values.to_numpy(zero_copy_only=False).view(np.uint32) for x in r])
                for at, x in enumerate(q):
                    query = x.values.to_numpy(zero_copy_only=False).view(np.uint32)
                    owner, offset, most = index.best(query)
                    enough = most >= votes
                    owner, offset, most = owner[enough], offset[enough], most[enough]
                    bits, n = index.wrong(query, owner, offset)
                    near = np.flatnonzero(np.round(bits / (32 * n), 6) <= allowed(n, error))
                    found = [owner[near], offset[near].astype(np.int32), most[near], bits[near] / (32 * n[near]), n[near].astype(np.int32)]
                    yield pa.record_batch([q_ids.take(pa.array(np.full(len(near), at))), ids.take(pa.array(found[0])), *map(pa.array, found[1:])], ["query_id", "class_id", "offset", "votes", "bit_error", "n_frames"])

    name = dict(every.dtypes)["class_id"]
    tasks = max(1, min(n_left * n_right, 4 * prints.sparkSession.sparkContext.defaultParallelism))
    met = right.crossJoin(small(left, n_left)).select("asked", "known").repartition(tasks)
    found = met.mapInArrow(run, f"query_id {name}, class_id {name}, offset int, votes long, bit_error double, n_frames int").where("query_id <> class_id")
    return found.join(every.select("class_id", "copies"), "class_id").select("query_id", "class_id", "copies", "offset", "votes", F.round("bit_error", 6).alias("bit_error"), "n_frames")
