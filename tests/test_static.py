"""The worked example exactly, identities, bounds, and the walk and the attachment against their plain loops."""

from __future__ import annotations

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from enctopics.operators import centres, dynamic, index, kestimate, relate
from enctopics.plans import experiments

EXACT = {
    "Book": (0.4068, 0.2568, 0.0086, 0.1806, 0.1472),
    "Solve": (0.2615, 0.4592, 0.1318, 0.1305, 0.0170),
    "Traffic": (0.0176, 0.2645, 0.2274, 0.3042, 0.1862),
    "Net": (0.1058, 0.0751, 0.0872, 0.5706, 0.1614),
    "Enter": (0.1335, 0.0152, 0.0826, 0.2498, 0.5190),
}


@pytest.fixture(scope="module")
def example(spark):
    return experiments.worked_example(spark).cache()


def test_similarity_matrix(example):
    got = {(r.tok, r.other): r.q for r in kestimate.topic_similarity(example).collect()}
    for tok, row in EXACT.items():
        for other, q in zip(EXACT, row):
            assert got.get((tok, other), 0) == pytest.approx(q, abs=6e-5)
        assert sum(q for (a, _), q in got.items() if a == tok) == pytest.approx(1, abs=1e-12)


def test_estimate(example):
    sep = {r.tok: r.q for r in kestimate.separation(example).collect()}
    assert sep == pytest.approx({t: row[i] for i, (t, row) in enumerate(EXACT.items())}, abs=6e-5)
    row = kestimate.estimate_k(example).first()
    assert (row.m, row.k) == (5, 3) and row.trace == pytest.approx(2.18306, abs=1e-5)


def test_shares_sum_to_one(example):
    n = kestimate.normalise(example)
    assert all(r.s == pytest.approx(1) for r in kestimate.token_importance(n).groupBy("tok").agg(F.sum("r").alias("s")).collect())
    assert all(r.x == pytest.approx(1) for r in kestimate.document_importance(example).groupBy("doc_id").agg(F.sum("s").alias("x")).collect())


def frame(spark, rows):
    return spark.createDataFrame(rows, "tok string, doc_id long, f long")


def test_bounds_of_k(spark):
    same = frame(spark, [(t, d, 2) for t in "abc" for d in range(4)])
    apart = frame(spark, [(t, i, 2) for i, t in enumerate("abcd")])
    assert kestimate.estimate_k(same).first().k == 1
    assert kestimate.estimate_k(apart).first().k == 4
    assert kestimate.estimate_k(frame(spark, [])).first().k == 0
    twice = apart.union(apart.withColumn("doc_id", F.col("doc_id") + 100))
    assert kestimate.estimate_k(twice).first().k == 4


def test_eligible_centres_of_the_example(example):
    strict = centres.eligible(example).collect()
    assert [r.tok for r in strict] == ["Book"]


def walk(rows, inclusive=False):
    docs = {}
    for t, d, _ in rows:
        docs.setdefault(t, set()).add(d)
    covered, out = set(), []
    for t in sorted(docs, key=lambda t: (-len(docs[t]), t)):
        seen = len(docs[t] & covered)
        new = len(docs[t]) - seen
        if new > seen or inclusive and new == seen:
            covered |= docs[t]
            out.append((t, new, seen))
    return out


@pytest.mark.parametrize("head", [10**6, 12, 0])
def test_walk_in_parts_is_the_walk(spark, head):
    rng = random.Random(head)
    rows = list({(f"t{rng.randint(0, 25)}", rng.randint(0, 30)) for _ in range(90)})
    rows = [(t, d, 1) for t, d in rows]
    got = [(r.tok, r.new_docs, r.seen_docs) for r in centres.eligible(frame(spark, rows), head=head).orderBy("rank").collect()]
    assert got == walk(rows)


def test_relatedness_values_and_closed_form(spark, example):
    want = {("Book", "Solve"): 0.0846, ("Book", "Traffic"): 0.1321, ("Traffic", "Solve"): 0.3002, ("Net", "Traffic"): 0.2305, ("Book", "Net"): -0.0559}
    totals = index.token_stats(example).select("tok", F.col("tf").alias("total"))
    for (c, t), r in want.items():
        one = spark.createDataFrame([(1, c)], "rank int, tok string")
        got = {x.tok: x.r for x in relate.relatedness(example, one).collect()}
        assert got[t] == pytest.approx(r, abs=6e-5)
        rho = relate.relative_by_document(example, one).join(example, ["tok", "doc_id"]).join(totals, "tok")
        summed = {x.tok: x.r for x in rho.groupBy("tok").agg(F.sum(F.col("rho") * F.col("f") / F.col("total")).alias("r")).collect()}
        assert all(summed[k] == pytest.approx(v, abs=1e-12) for k, v in got.items())


def test_every_token_has_one_cluster(spark):
    rng = random.Random(5)
    rows = frame(spark, [(t, d, rng.randint(1, 5)) for t, d in {(f"t{rng.randint(0, 30)}", rng.randint(0, 40)) for _ in range(150)}])
    c = centres.by_document_count(index.token_stats(rows), 4)
    for orphan in ("cooccurring_only", "literal"):
        placed = relate.distribute(relate.relatedness(rows, c), c, rows, orphan).collect()
        assert len(placed) == len({r.tok for r in placed}) == rows.select("tok").distinct().count()
        assert {r.cluster_id for r in placed if r.is_centre} == {1, 2, 3, 4}
        assert all(r.cluster_id > 0 for r in placed) or orphan != "literal"


def loop(new, abstracts, theta):
    """The sequential rule: nearest abstract or founder beyond theta, else found."""
    groups = [(c, v) for c, v in abstracts]
    next_id = max((c for c, _ in groups), default=-1) + 1
    out = {}
    for tok, f, v in sorted(new, key=lambda x: (-x[1], x[0])):
        sims = [(round(float(np.dot(v, u)), 12), c) for c, u in groups]
        best = max(sims, key=lambda s: (s[0], -s[1])) if sims else (-2, -1)
        if best[0] > theta:
            out[tok] = (best[1], False)
        else:
            out[tok] = (next_id, True)
            groups.append((next_id, v))
            next_id += 1
    return out


@pytest.mark.parametrize("n_abstracts", [0, 3])
def test_attachment_is_the_loop(spark, n_abstracts):
    rng = np.random.default_rng(n_abstracts)
    unit = lambda: (lambda v: (v / np.linalg.norm(v)).tolist())(rng.normal(size=3))
    new = [(f"n{i}", int(rng.integers(1, 5)), unit()) for i in range(40)]
    have = [(i, unit()) for i in range(n_abstracts)]
    a = spark.createDataFrame(new, "tok string, f long, vec array<double>")
    b = spark.createDataFrame([(c, f"a{c}", v) for c, v in have], "cluster_id long, tok string, vec array<double>")
    got = {r.tok: (r.cluster_id, r.founded) for r in dynamic.attach(a, b, 0.6).collect()}
    assert got == loop(new, have, 0.6)


def test_attachment_by_blocks_is_the_loop_and_brings_no_vector_to_the_driver(spark, monkeypatch):
    rng = np.random.default_rng(11)
    unit = lambda n: (lambda v: v / np.linalg.norm(v, axis=1, keepdims=True))(np.where(rng.random((n, 24)) < 0.3, rng.integers(1, 4, (n, 24)), 0) + np.eye(24)[rng.integers(0, 24, n)])
    nv, av = unit(90), unit(40)
    new = [(f"n{i:02d}", int(f), v.tolist()) for i, (f, v) in enumerate(zip(rng.integers(1, 6, 90), nv))]
    tops = [(i // 4, f"a{i:02d}", v.tolist()) for i, v in enumerate(av)]
    want, have = {}, [(c, np.array(v)) for c, _, v in tops]
    for tok, _, v in sorted(new, key=lambda r: (-r[1], r[0])):
        sims = [(round(float(np.dot(x, v)), 12), -c) for c, x in have]
        best = max(sims)
        if best[0] > 0.7:
            want[tok] = (-best[1], False)
        else:
            last = max(c for c, _ in have) + 1
            have.append((last, np.array(v)))
            want[tok] = (last, True)
    assert 5 < sum(f for _, f in want.values()) < 85
    a, b = spark.createDataFrame(new, "tok string, f long, vec array<double>"), spark.createDataFrame(tops, "cluster_id long, tok string, vec array<double>")
    monkeypatch.setattr(type(a), "toArrow", None)
    for held, compared in ((1 << 21, 100_000), (40, 13)):
        monkeypatch.setattr(dynamic, "HELD", held)
        monkeypatch.setattr(dynamic, "COMPARED", compared)
        assert {r.tok: (r.cluster_id, r.founded) for r in dynamic.attach(a, b, 0.7).collect()} == want
        assert dynamic.attach(a.limit(0), b, 0.7).count() == 0 and dynamic.attach(a, b, -1.5).where("founded").isEmpty()


def test_attachment_takes_vectors_by_their_places(spark):
    """Vectors that no worker could hold densely: 300 new tokens of 2**30 places, a few of them not zero."""
    rng = random.Random(3)
    made = [(f"t{i}", rng.randint(1, 9), {rng.choice((1, 5, 7, 9, 1 << 29)): rng.choice((-1.0, 1.0, 2.0)) for _ in range(rng.randint(1, 3))}) for i in range(300)]
    made = [(t, f, {k: v / math.sqrt(sum(x * x for x in vec.values())) for k, v in sorted(vec.items())}) for t, f, vec in made]
    shape = "tok string, f long, at array<int>, x array<double>"
    new = spark.createDataFrame([(t, f, list(vec), list(vec.values())) for t, f, vec in made], shape)
    none = new.select(F.lit(0).cast("long").alias("cluster_id"), "tok", "at", "x").limit(0)
    dot = lambda a, b: sum(v * b.get(k, 0.0) for k, v in a.items())
    founders, want = [], {}
    for t, f, vec in sorted(made, key=lambda r: (-r[1], r[0])):
        sims = [dot(vec, other) for other in founders]
        if not sims or max(sims) <= 0.5 + 1e-9:
            founders.append(vec)
            want[t] = (len(founders) - 1, True)
        else:
            want[t] = (min(range(len(sims)), key=lambda i: (-round(sims[i], 9), i)), False)
    assert {r.tok: (r.cluster_id, r.founded) for r in dynamic.attach(new, none, 0.5 + 1e-9).collect()} == want


def test_disparity_rows_are_not_joined_with_each_other(spark):
    """Rows of all documents of one of a pair, as a plain loop gives them; no full join of them."""
    rng = random.Random(8)
    f = {(f"t{rng.randint(0, 12)}", rng.randint(0, 50)): rng.randint(1, 5) for _ in range(200)}
    rows = frame(spark, [(t, d, n) for (t, d), n in f.items()])
    c = centres.by_document_count(index.token_stats(rows), 3)
    names = {r.tok for r in c.collect()}
    docs = {t: {d: n for (u, d), n in f.items() if u == t} for t, _ in f}
    want = {}
    for x in names:
        for t in docs.keys() - names:
            if docs[x].keys() & docs[t].keys():
                mine, its = ({d: n for d, n in docs[u].items() if d not in docs[v]} for u, v in ((t, x), (x, t)))
                want |= {(x, t, d): n / sum(part.values()) for part in (mine, its) for d, n in part.items()}
    made = relate.disparity_by_document(rows, c)
    assert {(r.centre, r.tok, r.doc_id): r.phi for r in made.collect()} == pytest.approx(want)
    assert "FullOuter" not in made._jdf.queryExecution().toString()


def _exchanged(spark, made):
    """The names of the columns of each exchange of a plan."""
    import re

    text = spark._jvm.org.apache.spark.sql.api.python.PythonSQLUtils.explainString(made._jdf.queryExecution(), "formatted")
    return [{c.split("#")[0] for c in line.split(", ")} for line in re.findall(r"\) Exchange *\nInput \[\d+\]: \[(.*)\]", text)]


def test_rows_of_disparity_are_not_shuffled(spark):
    """Neither as rows nor as a centre's documents beside each token; what a pair shares goes by pairs."""
    a = frame(spark, [(f"t{t}", d, 1 + t) for t in range(9) for d in range(40) if (d + t) % (t + 1) == 0])
    c = centres.by_document_count(index.token_stats(a), 2)
    found = _exchanged(spark, relate.disparity_by_document(a, c))
    assert found and not [e for e in found if {"docs", "b"} <= e or {"at", "b"} <= e or {"f", "a"} <= e]


def test_rows_of_relative_cooccurrence_are_not_shuffled(spark):
    a = frame(spark, [(f"t{t}", d, 1 + t) for t in range(9) for d in range(40) if (d + t) % (t + 1) == 0])
    found = _exchanged(spark, relate.relative_by_document(a, centres.by_document_count(index.token_stats(a), 2)))
    assert found and not [e for e in found if {"docs", "b"} <= e or {"at", "b"} <= e or {"rho"} <= e or {"f", "a"} <= e]


def test_worked_example_reads_the_documents(spark):
    """As the SQL has it over the same table."""
    import duckdb

    from enctopics import queries_experiments
    from enctopics.registry import SQL

    d = "/root/testdata/sf0.001"
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{d}/documents.parquet'")
    made = queries_experiments.worked_example(spark, d)
    assert made.inputFiles()
    want = {(t, o): q for t, o, q in con.execute(SQL["worked_example"]).fetchall()}
    assert {(r.tok, r.other): r.q for r in made.collect()} == pytest.approx(want, abs=1e-6) and len(want) > 5
