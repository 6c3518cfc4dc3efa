"""Each operator against a brute-force version, and on nulls, empty and long texts, ties, repeated rows, empty tables, clashing names."""

from __future__ import annotations

import hashlib
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from enctopics.llm import audio, chat, components, decontaminate, langid, packing, sharding, similar, simhash, suffixes, token_counts, toxicity
from enctopics.llm.common import remainder, word_bpe

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def texts(n: int = 40, seed: int = 1) -> list[str]:
    rng = random.Random(seed)
    vocabulary = [f"{a}{b}" for a in ("ba", "du", "ki", "mo", "re", "sa") for b in ("lan", "tor", "ves", "nim", "é", "ß")]
    out = [" ".join(rng.choice(vocabulary) for _ in range(rng.randint(5, 60))) for _ in range(n)]
    out += [out[0], out[0] + " end", out[1][:-9] + " x y " + out[2], "", " \n", "a", "aaa " * 200, "Ärger ohne Ende " * 30]
    return out


def frame(spark, ts, ids=None):
    ids = list(range(len(ts))) if ids is None else ids
    rows = [(i, t, "en", "s", None if t is None else len(t)) for i, t in zip(ids, ts)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture
def odd(spark):
    """Null ids, null texts, repeated rows, one id with two texts, columns called like the operators' own."""
    ts = [None, "", "same words here and there " * 5, "same words here and there " * 5, "other text of the same id " * 5, None]
    return frame(spark, ts, [None, 1, 2, 2, 2, 3]).withColumn("doc", F.lit(1)).withColumn("tag", F.lit("t")).withColumn("key", F.lit(0)).withColumn("row", F.lit(0)).withColumn("label", F.lit(0)).withColumn("part", F.lit(0))


@pytest.fixture
def none(spark):
    return spark.createDataFrame([], SCHEMA)


# 1

def test_simhash_against_brute_force(spark):
    ts = texts()
    got = {r.doc_id: r for r in simhash.near_duplicates(frame(spark, ts)).collect()}
    fps = []
    for t in ts:
        w = re.findall(rb"[^\x20\x09-\x0d]+", bytes(c + 32 if 65 <= c <= 90 else c for c in t.encode()))
        s = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([b" ".join(w)] if w else [])
        hs = [xxhash.xxh64_intdigest(x, 42) for x in s]
        fps.append(sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs)))
    assert [got[i].fingerprint for i in range(len(ts))] == [f"{f:016x}" for f in fps]
    assert [got[i].component_id for i in range(len(ts))] == linked(fps)


def linked(fps):
    label = list(range(len(fps)))
    for i, a in enumerate(fps):
        for j in range(i):
            if (a ^ fps[j]).bit_count() <= 3:
                x, y = label[i], label[j]
                label = [min(x, y) if v in (x, y) else v for v in label]
    return label


@pytest.mark.parametrize("hot,large", [(20_000, 64), (3, 2)])
def test_links_of_close_fingerprints(spark, monkeypatch, hot, large):
    monkeypatch.setattr(simhash, "HOT", hot)
    monkeypatch.setattr(simhash, "LARGE", large)
    rng = random.Random(hot)
    fps = [rng.getrandbits(64) for _ in range(6)]
    for _ in range(60):
        x = rng.choice(fps)
        for _ in range(rng.randint(1, 4)):
            x ^= 1 << rng.randrange(64)
        fps.append(x)
    fps = list(dict.fromkeys(fps))
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    found = simhash.links(spark.createDataFrame([(f,) for f in signed], "fp long"))
    label = {r.node: r.label for r in components.components(found).collect()}
    mine, brute = [label.get(f, f) for f in signed], linked(fps)
    assert [mine.index(x) for x in mine] == [brute.index(x) for x in brute]


def test_components(spark):
    edges = [(i, i + 1) for i in range(20)] + [(30, 31), (31, 30), (40, 40), (None, 3)]
    got = {r.node: r.label for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(21), 0), 30: 30, 31: 30}


def test_near_dedup_on_odd_rows(spark, odd, none):
    assert simhash.near_duplicates(odd).count() == 6 and simhash.near_duplicates(none).count() == 0
    kept = simhash.one_of_each(odd)
    assert kept.columns == odd.columns and kept.where("doc_id = 2").count() <= 2


def test_near_dedup_stage_against_brute_force(spark, odd, none):
    import corpus_pipeline

    rng = random.Random(12)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(4))
    ts = []
    for n in (6, 40, 90, 200):
        base = [word() for _ in range(n)]
        ts.append(" ".join(base))
        for edits in (0, 1, 1, 2, 3, 4, 6, 9):
            new = list(base)
            for _ in range(edits):
                new[rng.randrange(len(new))] = word()
            ts.append(" ".join(new[rng.randrange(3) :]))
    ts += ["", " ", "one two", "One  two", "one", ts[-1] + " end", None]
    rng.shuffle(ts)
    words = [(t or "").lower().split() for t in ts]
    sets = [{tuple(w[i : i + 5]) for i in range(max(len(w) - 4, 1))} if w else set() for w in words]
    label = list(range(len(ts)))
    for i, a in enumerate(sets):
        for j in range(i):
            if a == sets[j] or 5 * len(a & sets[j]) >= 4 * len(a | sets[j]):
                x, y = label[i], label[j]
                label = [min(x, y) if v in (x, y) else v for v in label]
    kept = {r.doc_id for r in corpus_pipeline.near_dedup(spark, frame(spark, ts), "").collect()}
    assert kept == set(label) and len(kept) < len(ts) - 10
    assert {r.doc_id: r.component_id for r in similar.near_duplicates(frame(spark, ts)).collect()} == dict(enumerate(label))
    assert similar.near_duplicates(odd).count() == 6 and similar.near_duplicates(none).isEmpty() and similar.one_of_each(odd).columns == odd.columns


# 2

def test_language_held_out(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    pred = langid.predict(docs, langid.learn(docs.where(remainder(4) != 2))).join(docs.select("doc_id", "lang"), "doc_id").where(remainder(4) == 2).collect()
    assert np.mean([r.lang == r.lang_pred for r in pred]) > 0.95 and all(0 <= r.score <= 1 for r in pred)


def test_language_of_odd_rows(spark, odd, none):
    model = langid.learn(odd)
    got = langid.predict(odd.union(frame(spark, ["1 2 3 !"], [9]).select("*", *[F.lit(0)] * 0).withColumns({c: F.lit(None).cast(t) for c, t in odd.dtypes[5:]})), model)
    by = [(r.doc_id, r.lang_pred, r.score) for r in got.collect()]
    assert (9, "und", 0.0) in by and (1, "und", 0.0) in by and (None, "und", 0.0) in by
    assert langid.predict(odd, langid.learn(none)).where("lang_pred <> 'und'").isEmpty()
    assert langid.accepted(odd, model).columns == odd.columns


def test_long_texts_count_as_in_one_piece(monkeypatch):
    t = "Über die Brücke, und 12 weiter. " * 50
    whole = langid.counts(t)
    monkeypatch.setattr(langid, "CHUNK", 97)
    assert abs(langid.counts(t).sum() - whole.sum()) < 0.1 * whole.sum()


# 3

def test_contamination_against_brute_force(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    items = [" ".join(word() for _ in range(n)) for n in (14, 20, 30, 30)] + ["", "two words"]
    pad = lambda n: " ".join(word() for _ in range(n))
    edited = items[2].split()
    edited[-1] = "changed"
    ts = [f"{pad(20)}. {items[0].upper()}! {pad(9)}", pad(50), f"{pad(5)} {' '.join(edited)} {pad(5)}", f"{items[1][:60]} {pad(30)}", f"{items[3]} {items[3]}", "", "two words", f"{pad(3)} two words {pad(3)}", None]
    docs = frame(spark, ts)
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {(r.doc_id, r.item_id): r.similarity for r in decontaminate.contamination(docs, bench).collect()}
    want = {}
    words = lambda t: re.findall(r"\w+", (t or "").lower())
    shingles = lambda w: [tuple(w[i : i + 5]) for i in range(len(w) - 4)] or ([tuple(w)] if w else [])
    from collections import Counter

    for i, t in enumerate(ts):
        for j, item in enumerate(items):
            w, v = words(t), words(item)
            for at in range(len(w) - len(v) + 1) if v else ():
                a, b = Counter(shingles(w[at : at + len(v)])), Counter(shingles(v))
                s = sum((a & b).values()) / sum((a | b).values())
                if s >= 0.8 and len(v) >= 5:
                    want[i, j] = max(want.get((i, j), 0), round(s, 6))
    assert {k: v for k, v in got.items() if k[1] != 5} == want and (0, 0) in want and (2, 2) in want
    assert decontaminate.clean(docs, bench).where("doc_id IN (0, 2, 4)").isEmpty()


def test_short_documents_and_items_against_brute_force(spark):
    from collections import Counter

    rng = random.Random(31)
    pad = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(n))
    items = [pad(40), pad(12), pad(5), pad(4), pad(2), pad(1), "same " * 30]
    w = items[0].split()
    ts = [" ".join(w[:39]), " ".join(w[6:]), " ".join(w[:30]), " ".join(items[1].split()[1:]), " ".join(items[1].split()[4:]), f"{pad(9)} {items[3]} {pad(3)}", f"{items[4]} {pad(8)}", f"{pad(7)} {items[5]}", items[4], items[3] + " x", " ".join(items[2].split()[:4]), "same " * 26, pad(3), ""]
    got = {(r.doc_id, r.item_id): (r.similarity, r.start_word, r.n_words) for r in decontaminate.contamination(frame(spark, ts), spark.createDataFrame(list(enumerate(items)), "item_id long, text string")).collect()}
    shingles = lambda w: Counter([tuple(w[i : i + 5]) for i in range(len(w) - 4)] or [tuple(w)])
    want = {}
    for i, t in enumerate(ts):
        for j, item in enumerate(items):
            w, v = t.split(), item.split()
            for at in range(max(len(w) - len(v), 0) + 1) if w else ():
                a, b = shingles(w[at : at + len(v)]), shingles(v)
                s = round(sum((a & b).values()) / sum((a | b).values()), 6)
                if s >= 0.8 and s > want.get((i, j), (0,))[0]:
                    want[i, j] = (s, at, min(len(w), len(v)))
    assert got == want and {(0, 0), (1, 0), (3, 1), (5, 3), (6, 4), (7, 5), (8, 4), (9, 3), (11, 6)} <= set(got)


def test_contamination_of_odd_rows(spark, odd, none):
    bench = spark.createDataFrame([(1, "same words here and there same words"), (2, None)], "item_id long, text string")
    assert {r.doc_id for r in decontaminate.contamination(odd, bench).collect()} == {2}
    assert decontaminate.contamination(none, bench).isEmpty() and decontaminate.contamination(odd, bench.limit(0)).isEmpty()


def test_multi_index_finds_what_is_similar(spark):
    """Recall of the index: items with random edits, down to a similarity of 0.8."""
    from collections import Counter

    rng = random.Random(77)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(5))
    items = [[word() for _ in range(rng.randint(25, 60))] for _ in range(12)]
    shingles = lambda w: Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    ts, want = [], set()
    for _ in range(240):
        j = rng.randrange(len(items))
        w = list(items[j])
        for _ in range(rng.choice([0, 1, 1, 2])):
            w[rng.choice([0, 1, 2, len(w) - 2, len(w) - 1, rng.randrange(len(w))])] = word()
        a, b = shingles(w), shingles(items[j])
        if sum((a & b).values()) >= 0.8 * sum((a | b).values()):
            want.add((len(ts), j))
        ts.append(" ".join([*(word() for _ in range(9)), *w, *(word() for _ in range(9))]))
    got = {(r.doc_id, r.item_id) for r in decontaminate.contamination(frame(spark, ts), spark.createDataFrame([(j, " ".join(w)) for j, w in enumerate(items)], "item_id long, text string")).collect()}
    assert len(want) > 120 and got <= want | {(i, j) for i, j in got} and len(got & want) >= 0.98 * len(want) and not {i for i, _ in got} - {i for i, _ in want}


def test_a_text_that_repeats_itself_is_no_trouble(spark):
    bench = spark.createDataFrame([(1, "same " * 30), (2, "a b " * 100)], "item_id long, text string")
    got = decontaminate.contamination(frame(spark, ["same " * 20_000, "a b " * 5_000, "Same " * 25]), bench).collect()
    assert {(r.doc_id, r.item_id, r.start_word) for r in got} == {(0, 1, 0), (1, 2, 0), (2, 1, 0)}


def test_stages_keep_columns_called_like_their_own(spark):
    import corpus_pipeline

    docs = frame(spark, ["same words here and there " * 5] * 2 + ["other things altogether " * 9])
    for c in ("id", "_id", "copy", "__id", "__copy", "key", "__removed", "h"):
        docs = docs.withColumn(c, F.lit(c))
    bench = spark.createDataFrame([(1, "other things altogether " * 5)], "item_id long, text string")
    assert decontaminate.clean(docs, bench).columns == docs.columns and decontaminate.clean(docs, bench).count() == 2
    for kept in (similar.one_of_each(docs), simhash.one_of_each(docs), corpus_pipeline.suffix_dedup(spark, docs, "")):
        assert kept.columns == docs.columns and {r["__copy"] for r in kept.collect()} == {"__copy"}


# 4

def cut_out(rows, length=50):
    """Bytes removed, by brute force."""
    least = {}
    for d, b in rows:
        for i in range(len(b) - length + 1):
            w = b[i : i + length]
            least[w] = min(least.get(w, d), d)
    out = {}
    for d, b in rows:
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if least[b[i : i + length]] < d:
                gone[i : i + length] = b"\1" * length
        out[d] = bytes(c for c, g in zip(b, gone) if not g), sum(1 for i, g in enumerate(gone) if g and (not i or not gone[i - 1]))
    return out


@pytest.mark.parametrize("chunk,records,hot", [(1 << 21, 10_000, 500), (300, 7, 0)])
def test_suffix_dedup_against_brute_force(spark, monkeypatch, chunk, records, hot):
    monkeypatch.setattr(suffixes, "HOT", hot)
    monkeypatch.setattr(suffixes, "CHUNK", chunk)
    monkeypatch.setattr(suffixes, "SORTED", chunk)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(records))
    try:
        rng = random.Random(chunk)
        ts = texts(25, 4)
        for _ in range(25):
            a, b = rng.choice(ts), rng.choice(ts)
            at, to = sorted(rng.randrange(len(a) + 1) for _ in range(2))
            ts.append(b[: rng.randrange(len(b) + 1)] + a[at:to] + "é" * rng.randrange(3))
        ts.append("ab" * 300)
        ts.append("b" + "ab" * 200)
        rng.shuffle(ts)
        got = {r.doc_id: r for r in suffixes.digest(suffixes.repeats(frame(spark, ts))).collect()}
        want = cut_out([(i, t.encode()) for i, t in enumerate(ts)])
        for i, (kept, spans) in want.items():
            n = len(ts[i].encode())
            assert (got[i].n_bytes, got[i].n_removed, got[i].n_spans, got[i].kept_sha256) == (n, n - len(kept), spans, hashlib.sha256(kept).hexdigest())
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_suffix_dedup_of_odd_rows(spark, odd, none):
    got = suffixes.digest(suffixes.repeats(odd)).collect()
    assert len(got) == 6 and all(r.n_removed == 0 for r in got)
    assert suffixes.deduplicate(odd).columns == odd.columns and suffixes.digest(suffixes.repeats(none)).isEmpty()


def test_suffix_dedup_with_columns_called_like_its_own(spark):
    said = "a passage that is surely longer than fifty bytes, said twice"
    names = ["doc_id", "text", "doc", "tag", "asked", "__doc", "__tag", "__c0", "start"]
    docs = spark.createDataFrame([(i, t, *[str(i)] * 7) for i, t in enumerate([said, "x " + said, "else"])], ", ".join(f"`{n}` {'long' if n == 'doc_id' else 'string'}" for n in names))
    got = sorted(map(tuple, suffixes.deduplicate(docs).collect()))
    assert suffixes.deduplicate(docs).columns == names and got == [(0, said, *["0"] * 7), (1, "x ", *["1"] * 7), (2, "else", *["2"] * 7)]


# 5

def test_edited_counts_equal_the_whole(spark):
    import public_tokenizers

    encode = token_counts.encoder(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).encode_ordinary
    rng = random.Random(9)
    for t in [" ".join(texts()), "", "word", "  x  y z" * 300, "a" * 2000, "naïve\n\n 12 'll " * 90]:
        tree, now = token_counts.TokenTree(t, encode), t
        for _ in range(8):
            at, n, s = rng.randint(0, len(now)), rng.choice([0, 1, 5, 90, 900]), rng.choice(["", " ", "  a", "'s", "\n\n", " more of it " * 60])
            tree.edit(at, n, s)
            now = now[:at] + s + now[at + n :]
            assert "".join(tree.leaves) == now and tree.total == len(encode(now)) and tree.length == len(now)
    long = token_counts.TokenTree("some words to count " * 5000, encode)
    long.edit(50_000, 3, "xyz")
    assert long.reencoded < 5000


def test_counts_of_odd_rows(spark, odd, none):
    import public_tokenizers

    args = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    edits = spark.createDataFrame([(2, 1, 3, 2, "zz"), (2, 0, 99999, 5, None), (7, 0, 0, 0, "x")], "doc_id long, seq int, start long, n_delete long, inserted string")
    got = token_counts.edited(token_counts.with_edits(token_counts.trees(odd, *args), edits), *args).collect()
    assert len(got) == 6 and {r.n_tokens for r in got if r.doc_id in (None, 1, 3)} == {0}
    assert token_counts.edited(token_counts.with_edits(token_counts.trees(none, *args), edits), *args).isEmpty()
    named = token_counts.with_edits(odd.withColumn("edits", F.lit(1)).withColumn("edits_of", F.lit(2)), edits)
    assert {*named.columns} == {*odd.columns, "edits_of", "edits"} and named.where("doc_id = 1 AND edits IS NULL").count() == 1


def test_kept_trees_take_one_batch_of_edits_after_the_other(spark, tmp_path):
    import public_tokenizers

    args = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    encode = token_counts.encoder(*args).encode_ordinary
    rng, now = random.Random(4), dict(enumerate(["some words to count " * 400, *texts(12)]))
    kept = token_counts.trees(frame(spark, list(now.values())), *args)
    for batch in range(3):
        kept.write.parquet(f"{tmp_path}/{batch}")
        kept = spark.read.parquet(f"{tmp_path}/{batch}")
        edits = []
        for i, t in now.items():
            for seq in range(rng.randrange(3)):
                at, n, said = rng.randint(0, len(t)), rng.choice([0, 3, 70]), rng.choice(["", " x", "more words ", "\n"])
                edits.append((i, seq, at, n, said))
                t = t[:at] + said + t[at + n :]
            now[i] = t
        kept = token_counts.edited(token_counts.with_edits(kept, spark.createDataFrame(edits, "doc_id long, seq int, start long, n_delete long, inserted string")), *args)
        got = {r.doc_id: r for r in kept.collect()}
        assert all("".join(got[i].leaves) == t and got[i].n_tokens == len(encode(t)) and got[i].n_chars == len(t) for i, t in now.items())
        assert got[0].chars_reencoded < 4000


# 6

def test_recordings_are_aligned(spark):
    rng = np.random.default_rng(2)
    base = [rng.normal(0, 0.2, 64).tolist() for _ in range(6)]
    sounds = {i: audio.melody(v)[0] for i, v in enumerate(base)}
    sounds[10] = sounds[3][audio.HOP * 6 :] + rng.normal(0, 0.03, len(sounds[3]) - audio.HOP * 6)
    sounds[11] = sounds[0]
    rows = [(i, audio.fingerprint(s).view(np.int32).tolist()) for i, s in sounds.items()] + [(20, []), (21, None)]
    prints = spark.createDataFrame(rows, "id long, frames array<int>")
    got = {(r.query_id, r.class_id): r for r in audio.align(prints, audio.class_of(prints).select("class_id").distinct()).collect()}
    assert set(got) == {(3, 10), (10, 3)} and got[10, 3].offset == 6 and got[3, 10].offset == -6 and got[3, 10].bit_error < 0.15
    assert {r.id: r.copies for r in audio.class_of(prints).collect()}[11] == 2


@pytest.mark.parametrize("dense", [1 << 22, 1])
def test_recordings_that_are_cut_anywhere_or_noisy_are_found(spark, monkeypatch, dense):
    monkeypatch.setattr(audio, "DENSE", dense)
    rng = np.random.default_rng(8)
    sounds = {i: audio.melody(rng.normal(0, 0.2, 64).tolist())[0] for i in range(12)}
    made = [(100, 0.0), (128, 0.0), (1128, 0.1), (3000, 0.3), (0, 0.3), (0, 0.6)]
    for i in range(12):
        for k, (skip, noise) in enumerate(made):
            cut = sounds[i][skip:]
            sounds[100 * (k + 1) + i] = cut + rng.normal(0, noise, len(cut)) if noise else cut
    prints = {i: audio.fingerprint(x) for i, x in sounds.items()}

    def error(q, f):
        every = [(q[max(-d, 0) :], f[max(d, 0) :]) for d in range(16 - len(q), len(f) - 15)]
        return min(np.bitwise_count(a[: len(b)] ^ b[: len(a)]).mean() / 32 for a, b in every)

    brute = {(i, 100 * k + i) for i in range(12) for k in range(1, 7) if error(prints[i], prints[100 * k + i]) <= audio.ERROR}
    table = spark.createDataFrame([(i, f.view(np.int32).tolist()) for i, f in prints.items()], "id long, frames array<int>")
    got = audio.align(table, spark.createDataFrame([(i,) for i in range(12)], "class_id long")).collect()
    assert len(brute) > 60 and len(brute & {(r.query_id, r.class_id) for r in got}) >= 0.9 * len(brute)
    for k in (1, 2, 5):
        assert sum((r.query_id, r.class_id) in brute and r.class_id // 100 == k for r in got) >= 11
    for r in got:
        a, b = prints[r.query_id][max(-r.offset, 0) :], prints[r.class_id][max(r.offset, 0) :]
        assert r.n_frames == min(len(a), len(b)) and abs(np.bitwise_count(a[: len(b)] ^ b[: len(a)]).mean() / 32 - r.bit_error) < 1e-6


def test_unrelated_and_damaged_recordings_match_nothing(spark, none):
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(0, 0.2, 64).tolist()) for i in range(60)]
    prints = audio.fingerprints(spark.createDataFrame(rows, "id long, v array<double>"), "id", "v", audio.melody)
    assert audio.align(prints, prints.select(F.col("id").alias("class_id"))).isEmpty()
    cells = spark.createDataFrame([(1, bytearray(b"RIFF")), (2, bytearray(b"")), (3, bytearray(b"no sound at all" * 9)), (4, None)], "id long, wav binary")
    assert [r.frames for r in audio.fingerprints(cells, "id", "wav").collect()] == [[]] * 4
    empty = audio.fingerprints(cells.limit(0), "id", "wav")
    assert audio.align(empty, audio.class_of(empty).select("class_id").distinct()).isEmpty()


def test_short_overlaps_need_fewer_wrong_bits(spark):
    rng = np.random.default_rng(7)
    query = rng.integers(0, 1 << 32, 48).astype(np.uint32)

    def ends_like(start, wrong):
        flips = (rng.random((len(start), 32)) < wrong).astype(np.uint32) @ (np.uint32(1) << np.arange(32, dtype=np.uint32))
        return np.concatenate([rng.integers(0, 1 << 32, 48 - len(start)).astype(np.uint32), start ^ flips.astype(np.uint32)])

    prints = {0: query, 1: ends_like(query[:16], 0.05), 2: ends_like(query[:16], 0.2), 3: ends_like(query[:44], 0.2), 4: query[20:26]}
    table = spark.createDataFrame([(i, f.view(np.int32).tolist()) for i, f in prints.items()], "id long, frames array<int>")
    got = {r.class_id: r for r in audio.align(table, spark.createDataFrame([(0,)], "class_id long")).collect()}
    assert set(got) == {1, 3, 4} and (got[1].n_frames, got[3].n_frames, got[4].bit_error) == (16, 44, 0)


def test_recordings_from_wav_and_odd_rows(spark):
    import io
    import wave

    def wav(x):
        out = io.BytesIO()
        with wave.open(out, "wb") as w:
            w.setparams((2, 2, audio.RATE, 0, "NONE", ""))
            w.writeframes(np.repeat((x * 12000).astype("<i2"), 2).tobytes())
        return out.getvalue()

    x = audio.melody([0.1, -0.3, 0.7, 0.2] * 16)[0]
    df = spark.createDataFrame([(1, bytearray(wav(x))), (2, None), (3, bytearray(wav(x[:100]))), (None, bytearray(b""))], "vid long, sound binary").withColumn("id", F.lit(0))
    got = {r.id: r.frames for r in audio.fingerprints(df, "vid", "sound").collect()}
    assert len(got[1]) > 30 and got[2] == got[3] == got[None] == []
    assert np.mean(np.bitwise_count(np.array(got[1], np.int32).view(np.uint32) ^ audio.fingerprint(x))) < 2


# 7

def test_chats_can_be_read_back(spark):
    rows = [(1, 0, "system", "be <|im_end|>\n kind & &lt;|"), (1, 1, "user", "hi"), (1, 2, "user", "<|im_sep|>"), (1, 3, "assistant", "a<"), (1, 4, "assistant", None), (2, None, None, "x"), (2, 1, "ro\nle&nl;", "<|im_start|>assistant\n"), (None, 1, "assistant", "\U0001f600")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("pieces", F.lit(1))
    chats = chat.format_chats(df).cache()
    turns = {r.conv_id: [(t.role, t.text) for t in r.turns] for r in chats.select("conv_id", chat.read_turns(F.col("formatted")).alias("turns")).collect()}
    assert turns[1] == [(r[2], r[3] or "") for r in rows[:5]]
    assert turns[2] == [("", "x"), ("ro\nle&nl;", "<|im_start|>assistant\n")] and turns[None] == [("assistant", "\U0001f600")]
    got = {r.conv_id: r for r in chat.digest(chats).collect()}
    assert got[1].loss_sha256 == hashlib.sha256(b"a<").hexdigest() and got[1].loss_chars == 2 and got[None].loss_chars == 1
    assert got[2].loss_chars == 0 and got[1].n_turns == 5
    one = chats.where("conv_id = 1").first()
    assert one.formatted.count("<|im_start|>") == 3 and [one.formatted[s.start : s.end] for s in one.loss_spans] == ["a<", ""]
    assert chat.digest(chat.format_chats(df.limit(0))).isEmpty()


# 8

def check_packing(rows, capacity=4096):
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= capacity
    return len(by)


def test_packing_against_the_tokenizer(spark, odd, none):
    from tokenizers import Tokenizer

    ts = [*texts(), " ".join(texts(400, 8)), "naïve Ünïcode “quotes” 東京 \x1c x́ İstanbul ½ can't", None, "_a__b ...!? 1234"]
    got = packing.pack(frame(spark, ts), word_bpe()).collect()
    tokenizer = Tokenizer.from_file(word_bpe())
    want = set()
    for i, t in enumerate(ts):
        ids = np.array([*tokenizer.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        want |= {(i, k // 4096, k, min(4096, len(ids) - k), zlib.crc32(ids[k : k + 4096].tobytes())) for k in range(0, len(ids), 4096)}
    assert {tuple(r)[:5] for r in got} == want and len(got) == len(want)
    check_packing(got)
    assert packing.pack(odd, word_bpe()).count() == 6 and packing.pack(none, word_bpe()).isEmpty()


def test_many_texts_are_encoded_together_by_their_different_parts(monkeypatch):
    from tokenizers import Tokenizer

    rng, tokenizer = random.Random(8), Tokenizer.from_file(word_bpe())
    signs = [*"'''stmdrelvxy0 1_ -.!éÉſİ«»Ç\n\t\"", "'s", "'re", "'LL ", "don't", "''t", "<|endoftext|>", "\xa0", "日"]
    ts = ["".join(rng.choice(signs) for _ in range(rng.randrange(50))) for _ in range(3000)] + ["", " ", "x" * 300]
    want = [np.array(tokenizer.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in ts]
    for chunk in (1, 40, 1 << 21):
        monkeypatch.setattr(packing, "CHUNK", chunk)
        assert packing.Encoder(word_bpe()).many(ts) == want
    encode, asked = packing.Encoder(word_bpe()), []
    monkeypatch.setattr(encode, "part", lambda p: asked.append(p) or b"\1\0\0\0")
    assert encode.many([f"Word, other {i % 10}{i % 7}" for i in range(5000)]) == [b"\1\0\0\0" * 5] * 5000
    assert sorted(asked) == sorted([*"0123456789", ",", "other", "word"])


@pytest.mark.parametrize("seed", range(6))
def test_plans_place_all_and_waste_little(seed):
    rng = random.Random(seed)
    sizes = [min(4096, max(1, int(rng.lognormvariate(6, 1.2)))) for _ in range(3000)]
    histogram = {x: sizes.count(x) for x in set(sizes)}
    plan = packing.Plan(histogram)
    used, placed = {}, {}
    for x, rank, bins, each, first, offset in plan.steps:
        placed[x] = placed.get(x, 0) + bins * each
        for b in range(first, first + bins):
            used.setdefault(b, []).append((offset, x * each))
    assert placed == histogram
    for parts in used.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 4096
    large = sum(2 * x > 4096 for x in sizes)
    assert len(used) <= max(large, -(-sum(sizes) // 4096)) * 1.03 + 1


# 9

@pytest.fixture(scope="module")
def lexicon(spark):
    rng = random.Random(4)
    ts, toxic = [], []
    for i in range(160):
        t = rng.choice(texts(30, i)[:30])
        bad = i % 4 == 0
        ts.append(t + (f" you {rng.choice(['stupid', 'idiot'])} " if bad else " fine ") + f"n{i}")
        toxic.append(int(bad))
    docs = frame(spark, ts)
    labels = spark.createDataFrame([(i, x) for i, x in enumerate(toxic)] + [(None, 1), (999, None)], "doc_id long, toxic int")
    return toxicity.learn(docs, labels)


def test_obfuscated_words_are_restored(lexicon):
    assert toxicity.decode("st*pid".replace("*", "u"), lexicon.model) == "stupid"
    read = toxicity.Reader(lexicon.model, lambda words: words)
    for hidden in ("1d10t", "s t u p i d", "s.t.u.p.i.d", "stuuuupid", "$tup1d", "ID1OT"):
        assert {"idiot", "stupid"} & read(f"you {hidden} there"), hidden
    assert "fine" in read("a fine day") and not {"idiot", "stupid"} & read("bad 12 day")


def test_toxic_scores(spark, lexicon, odd, none):
    got = {r.doc_id: r.score for r in toxicity.score(frame(spark, ["you idiot", "you 1d10t", "badu fine", "", None]), lexicon).collect()}
    assert min(got[0], got[1]) >= 0.7 > max(got[2], got[3], got[4]) and got[3] == got[4]
    assert toxicity.score(odd, lexicon).count() == 6 and toxicity.score(none, lexicon).isEmpty()
    empty = toxicity.learn(none, spark.createDataFrame([], "doc_id long, toxic int"))
    assert {r.score for r in toxicity.score(odd, empty).collect()} == {0.0}


def test_spelled_out_words_of_any_shape_and_length_are_read(lexicon):
    read = toxicity.Reader(lexicon.model, lambda words: words)
    for hidden in ("s t.u p.i d", "x s.t.u.p.i.d", "stupid" + "_stupid" * 20, "s t u p i d " * 20):
        assert "stupid" in read(hidden), hidden
    assert "a" * 300 + "b" in read("so " + "a" * 300 + "b")
    long = "y o u s t u p i d " * 300
    assert "stupid" in read(long) and len(toxicity.decode(long.strip(), lexicon.model, True)) >= len(long) // 2 - 1


def test_toxicity_held_out(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.01/{n}.parquet") for n in ("documents", "labels"))
    got = toxicity.score(docs, toxicity.learn(docs, labels.where(remainder(3) != 1))).join(labels, "doc_id").where(remainder(3) == 1).collect()
    toxic, other = ([r.score for r in got if r.toxic == k] for k in (1, 0))
    assert len(toxic) >= 5 and np.mean([(a > b) + (a == b) / 2 for a in toxic for b in other]) > 0.85
    assert np.mean([s >= 0.7 for s in other]) < 0.05


# 10

@pytest.mark.parametrize("balance", ["bytes", "rows"])
def test_shards(spark, balance):
    ts = texts(200, 6) + ["copy " * 30] * 150 + [None, "long " * 400]
    got = sharding.shard(frame(spark, ts, [i // 2 if i > 300 else i for i in range(len(ts))]), 8, balance).collect()
    assert len(got) == len(ts) and {r.law for r in got} == {balance} and {r.grown_shard for r in got} == {None}
    by = {}
    for r in got:
        by.setdefault(r.shard, []).append(r)
    weights = [sum(r.size if balance == "bytes" else 1 for r in rows) for rows in by.values()]
    biggest = max(r.size for r in got) if balance == "bytes" else 1
    assert set(by) <= set(range(8)) and max(weights) - sum(weights) / 8 <= biggest
    assert all(sorted(r.slot for r in rows) == list(range(len(rows))) for rows in by.values())
    assert all(r.size == len((ts[r.doc_id] or "").encode()) + 8 and r.text_crc32 == zlib.crc32((ts[r.doc_id] or "").encode()) for r in got if r.doc_id is not None and r.doc_id < 150)


def test_shards_of_odd_rows(spark, odd, none):
    assert sharding.shard(odd).count() == 6 and sharding.shard(none).isEmpty()


# pipeline

def test_pipeline_stages(spark):
    import corpus_pipeline

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    before = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, before, "/root/testdata/sf0.001")
        after = spark.createDataFrame(after.toArrow())
        assert after.columns == docs.columns and after.select("doc_id").subtract(before.select("doc_id")).isEmpty(), name
        before = after
    assert before.count() > 0.7 * docs.count()
    last = corpus_pipeline.STAGES[-1][1](spark, before, "/root/testdata/sf0.001").collect()
    assert {r.doc_id for r in last} == {r.doc_id for r in before.collect()}
    check_packing(last)


def test_near_misses_cost_one_key_and_no_sets(spark, monkeypatch):
    """Long texts just under the similarity: of the many keys under which the same ones meet one is kept, and parities tell them apart."""
    rng, saved = random.Random(5), []
    words = lambda n: [f"w{rng.randrange(10**9)}" for _ in range(n)]
    base = words(824)
    ts = [" ".join(base + words(176)) for _ in range(4)] + [" ".join(base[:400]), " ".join(base[:395] + words(5))]
    kept = similar.save
    monkeypatch.setattr(similar, "save", lambda df, *a: saved.append(kept(df, *a)) or saved[-1])
    found = {r.doc_id: r.component_id for r in similar.near_duplicates(frame(spark, ts)).collect()}
    assert found == {0: 0, 1: 1, 2: 2, 3: 3, 4: 4, 5: 4}
    met = [df for df in saved if "fp" in df.columns][-1]
    members = [tuple(sorted(r.keys)) for r in met.groupBy("h").agg(F.collect_set("key").alias("keys")).collect()]
    assert len(members) == len(set(members)) > 1
    assert {r.key for df in saved if "hashes" in df.columns for r in df.collect()} == {similar._key(similar.shingles(t.encode())) for t in ts[4:]}


def test_pairs_of_a_dense_group_are_compared_under_one_key(spark, monkeypatch):
    """Texts that mostly lie just over or just under the similarity: pivots connect most, and what is left comes once and not under each of many keys."""
    rng, made, met = random.Random(7), [], similar._met
    base = [f"w{rng.randrange(10**9)}" for _ in range(150)]

    def edited(n):
        new = list(base)
        for at in rng.sample(range(150), n):
            new[at] = f"w{rng.randrange(10**9)}"
        return " ".join(new)

    ts = [edited(rng.choice((1, 2, 3, 4, 6))) for _ in range(120)]
    sets = [set(similar.shingles(t.encode()).tolist()) for t in ts]
    label = list(range(len(ts)))
    for i, a in enumerate(sets):
        for j in range(i):
            if 5 * len(a & sets[j]) >= 4 * len(a | sets[j]):
                x, y = label[i], label[j]
                label = [min(x, y) if v in (x, y) else v for v in label]
    assert 1 < len(set(label)) < 100

    def counted(one, other, *more):
        if "own" in one.columns:  # after the pivots
            rows = met(one, other, *more)
            made.append((rows.count(), rows.distinct().count(), met(one, other, more[0]).count()))
        return met(one, other, *more)

    monkeypatch.setattr(similar, "_met", counted)
    for pivots, own in ((4, 16), (1, 1)):
        monkeypatch.setattr(similar, "PIVOTS", pivots)
        monkeypatch.setattr(similar, "OWN", own)
        found = {r.doc_id: r.component_id for r in similar.near_duplicates(frame(spark, ts)).collect()}
        assert [found[i] for i in range(len(ts))] == label
    (rows, pairs, all_rows), (_, same, _) = made
    assert 0 < pairs == rows <= same < all_rows / 20


def test_pipeline_hands_texts_to_workers_in_small_batches(spark):
    import pyarrow as pa

    import corpus_pipeline
    from enctopics.llm.common import BATCH_BYTES

    def sizes(batches):
        for b in batches:
            yield pa.record_batch([pa.array([b.num_rows])], ["n"])

    key, docs = "spark.sql.execution.arrow.maxBytesPerBatch", spark.range(0, 400, 1, 1).select(F.col("id").alias("doc_id"), F.expr("repeat('ein Wort ', 10000)").alias("text"), F.lit("de").alias("lang"))
    try:
        for said, most in ((None, 2 * BATCH_BYTES), (str(1 << 20), 2 << 20)):  # a limit of the session's own stays
            spark.conf.unset(key) if said is None else spark.conf.set(key, said)
            assert corpus_pipeline.STAGES[0][1](spark, docs, "").count() == 400
            got = [r.n for r in docs.mapInArrow(sizes, "n long").collect()]
            assert sum(got) == 400 and max(got) * 90_000 <= most
    finally:
        spark.conf.unset(key)
