"""Exact removal of repeated byte strings: sparse anchors bring equal strings together, bucket-pointer refinement sorts them.

A byte goes if a LENGTH-byte string over it also starts in a document with a smaller id.

1. Every LENGTH-byte string has one anchor: the leftmost least hash among its GRAM-byte grams. Consecutive strings
   of one anchor form a run, LENGTH to LENGTH + span - 1 bytes; equal strings lie in runs whose anchors have equal
   grams. Per run there is one row: the gram's hash g, the run's hash c, the document and the place.
2. Rows meet by g, sorted. Runs with equal (g, c) are equal: all but the least document's go. Copies among SETTLED
   bytes of documents are settled before the shuffle, so a hot copy sends a row for as many bytes.
3. A gram with several different runs leaves open which strings of the least document's runs repeat. Only those
   runs are fetched as bytes and sorted by bucket-pointer refinement: buckets by 8 bytes are refined by the bucket ids
   at the offset where they end, and these updated ids refine the next time, at 16, then 32 bytes, until what shares a
   bucket is equal over LENGTH bytes. A place that is alone in its bucket is sorted no more.
4. A gram with more than HOT open runs is dealt over many tasks: strings that begin early in their run share the bytes
   before the gram, the others those after it, so each half goes by the gram and the bytes on that side.
5. Places return to their documents, where they are merged.

Hashes g and c have 64 bits each and must both agree: 128 bits for equal runs, bytes for all else. Memory is bounded
by these constants, a batch of documents and the different open runs of one gram and its neighbouring bytes.

Nulls: a null text is empty; a null id counts as larger than all others. Rows that share an id never match each
other; 26 bits of a hash tell their texts apart. Empty texts and tables are kept as they are. The operator keeps all columns of its input, whatever their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import cut, free_name, no_null, save, small, trimmed

LENGTH, GRAM = 50, 16
#: Bytes of text that are hashed at once and that are settled before the shuffle, bytes of runs that are sorted at once, runs that are fetched at once, open runs of a gram that one task may sort.
CHUNK, SETTLED, SORTED, FETCHED, HOT = 1 << 19, 1 << 22, 1 << 19, 5_000, 500
NO_ID, TAG = (1 << 63) - 1, (1 << 26) - 1  # for a null id; what is kept of the hash of a text
_BASE = 0x9E3779B97F4A7C15
_TABLE = np.random.default_rng(7).integers(1, 1 << 63, 256, np.uint64) * np.uint64(2) + np.uint64(1)
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd base and of its inverse modulo 2**64."""
    size = 1 << max(n - 1, 1).bit_length()
    if size not in _POWERS:
        _POWERS.clear()
        _POWERS[size] = tuple(np.concatenate([[np.uint64(1)], np.cumprod(np.full(size, b, np.uint64))]) for b in (_BASE, pow(_BASE, -1, 1 << 64)))
    return _POWERS[size]


def _grams(text: bytes, gram: int) -> np.ndarray:
    """A hash for each place of a text where a gram starts."""
    word = np.ndarray((len(text) - 7,), "<u8", text, strides=(1,))
    h = word[: len(text) - gram + 1] * np.uint64(0xC2B2AE3D27D4EB4F) ^ (word[gram - 8 :] * np.uint64(0x165667B19E3779F9) >> np.uint64(29))
    return (h ^ (h >> np.uint64(32))) * np.uint64(_BASE)


def runs(text: bytes, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """g, c, start and number of strings of each run of a text."""
    n = len(text)
    if n < length:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    h = _grams(text, gram)
    least, at, width = (h >> np.uint64(33)).astype(np.int32), np.arange(len(h), dtype=np.int32 if n < 1 << 31 else np.int64), 1
    span = length - gram + 1

    def merged(step: int, size: int) -> tuple[np.ndarray, np.ndarray]:
        left = least[:size] <= least[step : step + size]
        return np.where(left, least[:size], least[step : step + size]), np.where(left, at[:size], at[step : step + size])

    while 2 * width <= span:
        least, at = merged(width, len(least) - width)
        width *= 2
    if width < span:
        least, at = merged(span - width, len(h) - span + 1)
    first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
    many = np.diff(np.r_[first, len(at)])
    up, down = _powers(n + 1)
    total = np.concatenate([[np.uint64(0)], np.cumsum(_TABLE[np.frombuffer(text, np.uint8)] * up[:n])])
    c = (total[first + many + length - 1] - total[first]) * down[first]
    return h[at[first]], (c ^ (c >> np.uint64(31))) * np.uint64(0xD6E8FEB86659FD93), first, many


def _pieces(text: bytes, length: int) -> Iterator[tuple[int, bytes]]:
    """A text in pieces that share length - 1 bytes, so that each string lies in one of them.

    A run at a seam may be split in two; its strings stay with the gram that is their anchor.
    """
    for at in range(0, max(len(text) - length + 1, 0), CHUNK):
        yield at, text[at : at + CHUNK + length - 1]


def _place(start: np.ndarray, many: np.ndarray, tag: np.ndarray | int) -> np.ndarray:
    """Start, number of strings and tag as one number: 31, 6 and 26 bits."""
    return (start << 32) | (many << 26) | tag


def _placed(place: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    return place >> 32, (place >> 26) & 63, place & TAG


def _joined(doc: np.ndarray, tag: np.ndarray, start: np.ndarray, end: np.ndarray) -> tuple:
    """Places of the same document that touch, made one; in order of document and start."""
    order = np.lexsort((start, tag, doc))
    doc, tag, start, end = doc[order], tag[order], start[order], end[order]
    if not len(doc):
        return doc, tag, start, end
    new = np.r_[True, (doc[1:] != doc[:-1]) | (tag[1:] != tag[:-1])]
    group = np.cumsum(new) - 1
    top = int(end.max()) + 1
    reach = np.maximum.accumulate(end + group * top) - group * top  # farthest end so far within the document
    fresh = np.flatnonzero(new | np.r_[True, start[1:] > reach[:-1]])
    return doc[fresh], tag[fresh], start[fresh], reach[np.r_[fresh[1:], len(doc)] - 1]


def _rows(batches: Iterator[pa.RecordBatch], length: int, gram: int) -> Iterator[pa.RecordBatch]:
    """Runs of some documents at a time; no strings in a place marks one that is already known to go, up to c."""
    cols: list[list[np.ndarray]] = [[] for _ in range(4)]
    held = 0

    def settled() -> pa.RecordBatch:
        g, c, doc, place = (np.concatenate(col) for col in cols)
        for col in cols:
            col.clear()
        order = np.lexsort((doc, c, g))
        g2, c2, doc2 = g[order], c[order], doc[order]
        first = np.flatnonzero(np.r_[True, (g2[1:] != g2[:-1]) | (c2[1:] != c2[:-1])])
        known = np.empty(len(g), bool)
        known[order] = doc2 > np.repeat(doc2[first], np.diff(np.r_[first, len(g)]))  # rows stay in document order, which packs better
        start, many, tag = _placed(place[known])
        d, t, s, e = _joined(doc[known], tag, start, start + many + length - 1)
        mix = (d * 0x9E3779B1 ^ s * 0x85EBCA77).astype(np.int64) * 0x9E3779B1
        out = [np.concatenate(x) for x in ((g[~known], mix), (c[~known], e), (doc[~known], d), (place[~known], _place(s, 0 * s, t)))]
        return pa.record_batch([pa.array(x) for x in out], ["g", "c", "doc", "place"])

    for batch in batches:
        for i in range(len(batch)):
            doc, raw, tag = batch.column(0)[i].as_py(), batch.column(1)[i].as_buffer().to_pybytes(), batch.column(2)[i].as_py()
            for at, piece in _pieces(raw, length):
                g, c, start, many = runs(piece, length, gram)
                for col, x in zip(cols, (g.view(np.int64), c.view(np.int64), np.full(len(g), doc), _place(start + at, many, tag))):
                    col.append(x)
                held += len(piece)
                if held > SETTLED:
                    yield settled()
                    held = 0
    if cols[0]:
        yield settled()


def _meet(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """From rows sorted by g, c, doc: places to remove (open = 0), and runs with open strings (open = how many)."""
    last_g = last_c = last_doc = None
    waiting: list[tuple] = []  # the first class of the last gram, in case another follows
    several = False

    def batch_of(parts: list[tuple]) -> pa.RecordBatch:
        cols = [np.concatenate(x) for x in zip(*parts)]
        return pa.record_batch([pa.array(x.astype(np.int64)) for x in cols], ["g", "doc", "tag", "start", "end", "open"])

    for batch in batches:
        g, c, doc, place = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(4))
        start, many, tag = _placed(place)
        if not len(g):
            continue
        parts = []
        done = many == 0
        parts.append((0 * g[done], doc[done], tag[done], start[done], c[done], many[done]))
        g, c, doc, tag, start, many = (x[~done] for x in (g, c, doc, tag, start, many))
        if len(g):
            new_g = np.r_[g[0] != last_g, g[1:] != g[:-1]]
            new_c = new_g | np.r_[c[0] != last_c, c[1:] != c[:-1]]
            if not new_g[0] and not several and new_c.any() and (not new_g.any() or np.argmax(new_c) < np.argmax(new_g)):
                parts += waiting
            if new_g[0] or new_c[np.cumsum(new_g) == 0].any():
                waiting = []
            at = np.flatnonzero(new_c)
            which = np.cumsum(new_c) - 1
            least = np.where(which >= 0, doc[at][which] if len(at) else 0, last_doc if last_doc is not None else 0)
            goes = doc > least
            parts.append((0 * g[goes], doc[goes], tag[goes], start[goes], start[goes] + many[goes] + length - 1, 0 * g[goes]))
            gram_no = np.cumsum(new_g)  # 0: goes on from the last batch
            classes = np.bincount(gram_no, weights=new_c, minlength=gram_no[-1] + 1)
            classes[0] += (2 if several else 1) if last_g is not None and not new_g[0] else 0
            opens = ~goes & (classes[gram_no] > 1)
            row = lambda m: (g[m], doc[m], tag[m], start[m], start[m] + many[m] + length - 1, many[m])
            parts.append(row(opens))
            last = gram_no == gram_no[-1]
            several = bool(classes[gram_no[-1]] > 1)
            if gram_no[-1] > 0:
                waiting = []
            if not several:
                waiting = [*waiting, row(last & ~goes)]
            last_g, last_c, last_doc = g[-1], c[-1], least[-1]
        if sum(len(p[0]) for p in parts):
            yield batch_of(parts)


def refine(data: np.ndarray, starts: np.ndarray, group: np.ndarray, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray]:
    """Which of the strings at starts share their group and bucket with another, and the bucket of each of these.

    Bucket-pointer refinement of all places of data: a bucket holds the places with equal bytes over some width; the pair
    of bucket ids at a place and one width later refines it, so ids that one round has updated are what the next sorts by.
    """
    n, width = len(data), 8
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    ids = np.unique(np.ndarray((n,), "<u8", padded.tobytes(), strides=(1,)), return_inverse=True)[1].astype(np.int64)
    while width < length:
        step = min(width, length - width)
        later = np.concatenate([ids[step:] + 1, np.zeros(min(step, n), np.int64)])
        top = int(ids.max(initial=0)) + 2
        shared = np.flatnonzero(np.bincount(ids, minlength=1)[ids] > 1)
        ids[shared] = top + np.unique(ids[shared] * top + later[shared], return_inverse=True)[1]
        width += step
    named = group.astype(np.int64) * (int(ids.max(initial=0)) + 1) + ids[starts]
    bucket, size = np.unique(named, return_inverse=True, return_counts=True)[1:]
    shared = size[bucket] > 1
    return np.flatnonzero(shared), bucket[shared].astype(np.int64)


def _sort(batches: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """From open runs sorted by g: the places of their strings that also start in a smaller document."""

    def settled(part: list[tuple]) -> pa.RecordBatch:
        g, doc, tag, start, many, raw = (np.concatenate(x) if not isinstance(x[0], list) else sum(x, []) for x in zip(*part))
        data = np.frombuffer(b"".join(raw), np.uint8)
        base = np.cumsum([0, *map(len, raw)])[:-1]
        run = np.repeat(np.arange(len(g)), many)
        inside = np.arange(len(run)) - np.repeat(np.cumsum(many) - many, many)
        left, bucket = refine(data, base[run] + inside, np.unique(g, return_inverse=True)[1][run], length)
        run, inside = run[left], inside[left]
        least = np.full(int(bucket.max(initial=-1)) + 1, NO_ID)
        np.minimum.at(least, bucket, doc[run])
        hit = doc[run] > least[bucket]
        at = start[run[hit]] + inside[hit]
        d, t, s, e = _joined(doc[run[hit]], tag[run[hit]], at, at + length)
        return pa.record_batch([pa.array(x.astype(np.int64)) for x in (d, t, s, e)], ["doc", "tag", "start", "end"])

    part: list[tuple] = []
    held = 0
    for batch in batches:
        if not len(batch):
            continue
        g, doc, tag, start, many = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(5))
        raw = batch.column(5).to_pylist()
        cut_at = int(np.flatnonzero(g == g[-1])[0])
        if held > SORTED and (cut_at or part[-1][0][-1] != g[0]):
            part.append((g[:cut_at], doc[:cut_at], tag[:cut_at], start[:cut_at], many[:cut_at], raw[:cut_at]))
            yield settled(part)
            part, held = [], 0
            g, doc, tag, start, many, raw = (x[cut_at:] for x in (g, doc, tag, start, many, raw))
        part.append((g, doc, tag, start, many, raw))
        held += sum(map(len, raw))
    if part:
        yield settled(part)


def _halves(a: dict, raw: bytes, length: int, gram: int) -> Iterator[tuple[int, int, int, bytes]]:
    """Key, start, strings and bytes of the two halves of a run: those with much after the gram, those with much before it."""
    held = (length - gram) // 2  # bytes that all strings of a half share on its side, at least
    at = a["open"] - 1 + int(np.flatnonzero(_grams(raw, gram)[a["open"] - 1 :].view(np.int64) == a["g"])[0])
    early = min(max(at - held, 0), a["open"])  # strings that start so far before the gram
    key = lambda side, context: xxhash.xxh64_intdigest(context, (2 * a["g"] + side) & (1 << 64) - 1) - (1 << 63)
    if early:
        yield key(0, raw[at - held : at]), a["start"], early, raw[: early + length - 1]
    if early < a["open"]:
        yield key(1, raw[at + gram : at + gram + held]), a["start"] + early, a["open"] - early, raw[early:]


def _fetch(batches: Iterator[pa.RecordBatch], length: int, gram: int) -> Iterator[pa.RecordBatch]:
    """The bytes of the runs that are asked for, some thousands at a time."""
    out: list[tuple] = []

    def some() -> pa.RecordBatch:
        cols = list(zip(*out))
        out.clear()
        return pa.record_batch([pa.array(x, pa.int64()) for x in cols[:5]] + [pa.array(cols[5], pa.binary())], ["g", "doc", "tag", "start", "many", "raw"])

    for batch in batches:
        for i in range(len(batch)):
            doc, tag, raw = batch.column(0)[i].as_py(), batch.column(1)[i].as_py(), batch.column(2)[i].as_buffer().to_pybytes()
            for a in batch.column(3)[i].values.to_pylist():
                run = raw[a["start"] : a["end"]]
                for g, start, many, part in _halves(a, run, length, gram) if a["hot"] else ((a["g"], a["start"], a["open"], run),):
                    out.append((g, doc, tag, start, many, part))
                if len(out) >= FETCHED:
                    yield some()
    if out:
        yield some()


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH, gram: int = GRAM, name: str = "__removed") -> DataFrame:
    """The columns of docs and, under name, start and end of what is to go, in bytes, in order and apart from each other."""
    if not 32 <= length <= 64 or not 8 <= gram <= 16:
        raise ValueError("strings have 32 to 64 bytes, grams 8 to 16")
    doc = F.coalesce(docs[id_col].cast("long"), F.lit(NO_ID))
    text = no_null(docs[text_col])
    tag = F.xxhash64(text).bitwiseAND(F.lit(TAG))  # tells rows with one id but different texts apart
    own = [f"__c{i}" for i in range(len(docs.columns))]  # no name of docs can clash with ours
    body = own[docs.columns.index(text_col)]
    keyed = docs.select(doc.alias("__doc"), tag.alias("__tag"), *[docs[c].alias(o) for o, c in zip(own, docs.columns)])
    rows = docs.select(doc.alias("doc"), text.alias("text"), tag.alias("tag")).where(F.octet_length("text") >= length)
    every = rows.mapInArrow(trimmed(lambda b: _rows(b, length, gram)), "g long, c long, doc long, place long")
    met = save(every.repartition("g").sortWithinPartitions("g", "c", "doc").mapInArrow(trimmed(lambda b: _meet(b, length)), "g long, doc long, tag long, start long, end long, open long"))
    opened = met.where("open > 0")
    hot = cut(opened.groupBy("g").agg(F.count("*").alias("n")).where(F.col("n") > HOT).select("g", F.lit(True).alias("hot")))
    opened = opened.join(small(hot, hot.count()), "g", "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
    asked = opened.groupBy("doc", "tag").agg(F.collect_list(F.struct("g", "start", "end", "open", "hot")).alias("asked"))
    at = (F.col("__doc") == F.col("doc")) & (F.col("__tag") == F.col("tag"))
    # all columns go along, so that both joins with keyed read one and the same exchange of the texts
    wanted = keyed.join(asked, at).select("doc", "tag", F.col(body).alias("text"), "asked", *[o for o in own if o != body])
    fetched = wanted.mapInArrow(trimmed(lambda b: _fetch(b, length, gram)), "g long, doc long, tag long, start long, many long, raw binary")
    sorted_out = fetched.repartition("g").sortWithinPartitions("g").mapInArrow(trimmed(lambda b: _sort(b, length)), "doc long, tag long, start long, end long")
    places = met.where("open = 0").select("doc", "tag", "start", "end").union(sorted_out)
    removed = places.groupBy("doc", "tag").agg(F.array_sort(F.collect_set(F.struct("start", "end"))).alias("__gone"))
    return keyed.join(removed, at, "left").select(*[F.col(o).alias(c) for o, c in zip(own, docs.columns)], F.col("__gone").alias(name))


def keep(text: bytes, removed: list) -> tuple[bytes, int]:
    """What is left of a text, and the number of its maximal removed stretches."""
    kept, at, spans = [], 0, 0
    for x in removed or ():
        if x["start"] > at or not spans:
            spans += 1
        kept.append(text[at : x["start"]])
        at = max(at, x["end"])
    return b"".join([*kept, text[at:]]), spans


def digest(found: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for text, removed in zip(batch.column(1), batch.column(2)):
                raw = text.as_buffer().to_pybytes() if text.is_valid else b""
                kept, spans = keep(raw, removed.as_py())
                out.append((len(raw), len(raw) - len(kept), spans, hashlib.sha256(kept).hexdigest()))
            cols = list(zip(*out)) if out else [()] * 4
            yield pa.record_batch([batch.column(0), *[pa.array(x, pa.int64()) for x in cols[:3]], pa.array(cols[3], pa.string())], ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])

    rows = found.select(found[id_col].alias("doc_id"), found[text_col].alias("text"), "__removed")
    return rows.mapInArrow(trimmed(run), f"doc_id {dict(rows.dtypes)['doc_id']}, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = LENGTH) -> DataFrame:
    """docs with the repeated strings cut out of the texts; characters that are cut in two go as a whole."""
    found = repeats(docs, id_col, text_col, length, name=free_name(docs, "removed"))
    at, last, names = found.columns.index(text_col), len(docs.columns), list(docs.columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for text, removed in zip(batch.column(at), batch.column(last)):
                gone = removed.as_py()
                texts.append(keep(text.as_buffer().to_pybytes(), gone)[0].decode("utf-8", "ignore") if gone else text.as_py())
            kept = pa.array(texts, batch.schema.field(at).type)
            yield pa.record_batch([kept if i == at else c for i, c in enumerate(batch.columns) if i != last], names=names)

    return found.mapInArrow(trimmed(run), docs.schema)
