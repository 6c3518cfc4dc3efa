"""Token counts that follow edits: a segment tree over pre-token stretches of each text.

A text is cut into leaves of about LEAF characters at places where no pre-token can reach across: before a space
that stands between two characters that aren't white space. The tree holds characters and tokens of each leaf and
sums over subtrees. An edit goes down the tree by characters, takes the leaves that it touches and one more on
either side (whether a cut is one depends on the characters next to it), encodes these anew and updates the sums
above them; the rest of the text isn't read again. The count equals that of the whole edited text.

trees() gives a table with the leaves of each document and their counts, which is kept; edited() takes such a table and
a batch of edits, and gives the table for the next batch. Texts are encoded whole once, when they come in.

Nulls: a null text is empty, null edits are none, an edit beyond the end is moved to the end. Edits of a document
apply one after the other; ties in their order go by start, then length, then text. Repeated rows each get a row.
An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator
from functools import cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from enctopics.llm.common import free_name, narrow, trimmed

LEAF = 512
#: Texts whose trees are held at once.
ROWS = 256
_CUT = re.compile(r"(?<=\S)(?= \S)")
EDITS = "array<struct<seq:int,start:bigint,n_delete:bigint,inserted:string>>"


@cache
def encoder(ranks: str, pattern: str):
    import tiktoken

    with open(ranks, "rb") as lines:
        table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    return tiktoken.Encoding("counted", pat_str=pattern, mergeable_ranks=table, special_tokens={})


def leaves(text: str, size: int = LEAF) -> list[str]:
    """Stretches of a text of at least size characters, if it has that many, that are encoded apart as together."""
    out, at = [], 0
    while len(text) - at > size:
        cut = _CUT.search(text, at + size)
        if not cut:
            break
        out.append(text[at : cut.start()])
        at = cut.start()
    return [*out, text[at:]] if at < len(text) or not out else out


class TokenTree:
    """Leaves of one text, with sums of characters and tokens over a complete binary tree."""

    def __init__(self, text: str | list[str], encode, counts: list[int] | None = None):
        """Of a text, or of kept leaves and their counts, which are taken as they are."""
        self.encode, self.reencoded = encode, 0
        self.leaves = leaves(text) if counts is None else list(text)
        self.counts = [self._count(x) for x in self.leaves] if counts is None else list(counts)
        self._grow()
        self.reencoded = 0

    def _count(self, text: str) -> int:
        self.reencoded += len(text)
        return len(self.encode(text))

    def _grow(self) -> None:
        self.base = 1 << max(len(self.leaves) - 1, 0).bit_length()
        self.chars, self.tokens = [0] * (2 * self.base), [0] * (2 * self.base)
        for i, (x, n) in enumerate(zip(self.leaves, self.counts)):
            self.chars[self.base + i], self.tokens[self.base + i] = len(x), n
        for i in range(self.base - 1, 0, -1):
            self._sum(i)

    def _sum(self, i: int) -> None:
        self.chars[i] = self.chars[2 * i] + self.chars[2 * i + 1]
        self.tokens[i] = self.tokens[2 * i] + self.tokens[2 * i + 1]

    @property
    def total(self) -> int:
        return self.tokens[1]

    @property
    def length(self) -> int:
        return self.chars[1]

    def find(self, at: int) -> tuple[int, int]:
        """The leaf that holds character at, and where the leaf starts; the last leaf beyond the end."""
        i, start = 1, 0
        while i < self.base:
            i *= 2
            if at >= start + self.chars[i] and start + self.chars[i] < self.length:
                start += self.chars[i]
                i += 1
        return i - self.base, start

    def edit(self, start: int, n_delete: int, inserted: str) -> None:
        start = min(max(start, 0), self.length)
        end = min(start + max(n_delete, 0), self.length)
        first = max(self.find(max(start - 1, 0))[0] - 1, 0)
        last = min(self.find(end)[0] + 1, len(self.leaves) - 1)
        origin = self.find(start)[1] - sum(map(len, self.leaves[first : self.find(start)[0]]))
        text = "".join(self.leaves[first : last + 1])
        fresh = leaves(text[: start - origin] + inserted + text[end - origin :])
        if fresh == [""] and len(self.leaves) > last - first + 1:
            fresh = []
        counts = [self._count(x) for x in fresh]
        same = len(fresh) == last + 1 - first
        self.leaves[first : last + 1] = fresh
        self.counts[first : last + 1] = counts
        if not same:
            self._grow()
            return
        touched = set()
        for i, (x, n) in enumerate(zip(fresh, counts), self.base + first):
            self.chars[i], self.tokens[i] = len(x), n
            touched.add(i // 2)
        while touched - {0}:
            for i in touched - {0}:
                self._sum(i)
            touched = {i // 2 for i in touched}


def with_edits(docs: DataFrame, edits: DataFrame, id_col: str = "doc_id", edits_col: str = "edits") -> DataFrame:
    """docs and the column edits: the edits of each document (seq, start, n_delete, inserted), in order.

    A column of that name in docs is replaced; name another if it is to stay.
    """
    one = F.struct(*[F.col(c).cast(t).alias(c) for c, t in (("seq", "int"), ("start", "bigint"), ("n_delete", "bigint"), ("inserted", "string"))])
    name = free_name(docs, "edits_of")
    listed = edits.groupBy(F.col(id_col).alias(name)).agg(F.sort_array(F.collect_list(one)).alias(edits_col))
    return docs.drop(edits_col).join(listed, docs[id_col].eqNullSafe(listed[name]), "left").drop(name)


TREE = ["leaves", "leaf_tokens", "n_tokens", "n_chars"]
_TREE = "leaves array<string>, leaf_tokens array<int>, n_tokens long, n_chars long"


def _columns(rows: list[TokenTree]) -> list[pa.Array]:
    lists = [pa.array([t.leaves for t in rows], pa.list_(pa.string())), pa.array([t.counts for t in rows], pa.list_(pa.int32()))]
    return [*lists, pa.array([t.total for t in rows], pa.int64()), pa.array([t.length for t in rows], pa.int64())]


def trees(docs: DataFrame, ranks: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, leaves, leaf_tokens, n_tokens, n_chars: the segment tree of each text, as its leaves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(ranks, pattern).encode_ordinary
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                made = [TokenTree(t.as_py() or "", encode) for t in batch.column(1)[at : at + ROWS]]
                yield pa.record_batch([batch.column(0)[at : at + ROWS], *_columns(made)], ["doc_id", *TREE])

    rows = narrow(docs, doc_id=id_col, text=text_col)
    return rows.mapInArrow(trimmed(run), f"doc_id {dict(rows.dtypes)['doc_id']}, {_TREE}")


def edited(kept: DataFrame, ranks: str, pattern: str, edits_col: str = "edits") -> DataFrame:
    """The table of trees after the edits of each row, with n_tokens_before and chars_reencoded: characters of the leaves that were encoded anew."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(ranks, pattern).encode_ordinary
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                ids, texts, counts, edits = (c[at : at + ROWS] for c in batch.columns)
                made = [TokenTree(x.as_py(), encode, n.as_py()) for x, n in zip(texts, counts)]
                before = [t.total for t in made]
                for tree, es in zip(made, edits):
                    for e in es.as_py() or ():
                        if e:
                            tree.edit(e["start"] or 0, e["n_delete"] or 0, e["inserted"] or "")
                more = [pa.array(before, pa.int64()), pa.array([t.reencoded for t in made], pa.int64())]
                yield pa.record_batch([ids, *_columns(made), *more], ["doc_id", *TREE, "n_tokens_before", "chars_reencoded"])

    rows = kept.select("doc_id", "leaves", "leaf_tokens", edits_col)
    return rows.mapInArrow(trimmed(run), f"doc_id {dict(rows.dtypes)['doc_id']}, {_TREE}, n_tokens_before long, chars_reencoded long")
