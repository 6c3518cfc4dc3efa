"""Encryption, decisions, statistics, measures, search, streams, plans."""

from __future__ import annotations

import math
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

from enctopics import schemas
from enctopics.functions import crypto, sql
from enctopics.functions.statistics import chi_square_critical, improvement, student_quantile
from enctopics.operators import asof, dynamic, index, kestimate, metrics, search, tokens, vectors
from enctopics.sources.sinks import Versions
from enctopics.sources.tables import conversation_docs, page_text
from enctopics.streaming import stream

SMALL = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SMALL}/documents.parquet").limit(60).select("doc_id", "text").cache()


def test_handles_and_envelopes(spark):
    df = spark.createDataFrame([("a",), ("a",), ("é",)], "tok string")
    k = "secret"
    row = df.select(crypto.handle(F.col("tok"), k).alias("h"), crypto.seal(F.col("tok"), k).alias("s"), crypto.seal_document(F.col("tok"), k).alias("d"), crypto.open_(crypto.seal(F.col("tok"), k), k).alias("o")).collect()
    assert row[0].h == row[1].h != row[2].h and row[0].s == row[1].s and row[0].d != row[1].d
    assert [r.o for r in row] == ["a", "a", "é"]
    with pytest.raises(Exception):
        df.select(crypto.open_(crypto.seal(F.col("tok"), k), "other")).collect()
    with pytest.raises(ValueError):
        crypto.require_deterministic("gcm")


def test_cloud_tables_hold_no_plain_text(docs):
    p = tokens.keywords(docs)
    schemas.require_cloud(index.encrypt(p, "k"))
    with pytest.raises(ValueError):
        schemas.require_cloud(p)
    with pytest.raises(TypeError):
        schemas.require(p.drop("f"), schemas.POSTINGS)


def test_handles_are_keyed_macs(spark):
    import hashlib
    import hmac

    for key in ("k", "a key longer than a block " * 4):
        got = spark.createDataFrame([("wörd",)], "tok string").select(crypto.handle(F.col("tok"), key)).first()[0]
        assert got == hmac.new(key.encode(), "wörd".encode(), hashlib.sha256).hexdigest()


def test_handles_give_the_same_number_of_clusters(docs):
    p = kestimate.trim(tokens.keywords(docs))
    e = index.encrypt(p, "k").withColumnRenamed("handle", "tok")
    assert kestimate.estimate_k(p).first() == kestimate.estimate_k(e).first()


def test_merge_remove_and_flatten(docs):
    p = tokens.keywords(docs).cache()
    half = p.where("doc_id % 2 = 0")
    assert index.merge(half, p.where("doc_id % 2 = 1")).exceptAll(p).isEmpty()
    assert index.remove(p, half).count() == p.where("doc_id % 2 = 1").count()
    assert index.flatten(index.build(p)).exceptAll(p).isEmpty()


def test_statistics():
    assert chi_square_critical() == pytest.approx(3.841, abs=5e-4)
    assert chi_square_critical(10) == pytest.approx(18.307, abs=5e-4)
    assert student_quantile(9) == pytest.approx(2.262, abs=5e-4)
    assert improvement(3, 2) == 50


def test_decisions():
    assert not dynamic.decide(10, 100).recluster
    assert dynamic.decide(100, 100).recluster and dynamic.decide(150, 100).recluster
    assert not dynamic.decide(150, 100, one_sided=False).recluster
    assert dynamic.decide(0, 0).recluster
    stats = [dynamic.decide(n, 100).statistic for n in (10, 50, 90)]
    assert stats == sorted(stats, reverse=True)


def test_accumulation_starts_anew(spark):
    log = spark.createDataFrame([(1, 5, False), (2, 6, True), (3, 7, False), (4, 1, False)], "batch_id int, new long, recluster boolean")
    assert [r.accumulated for r in dynamic.accumulate(log).orderBy("batch_id").collect()] == [5, 11, 7, 8]


def blobs(spark, spread):
    rng = np.random.default_rng(3)
    rows = [(4 * c + i, c, (np.eye(4)[c] * 10 + rng.normal(0, spread, 4)).tolist()) for c in range(4) for i in range(4)]
    return spark.createDataFrame(rows, "id long, label int, vec array<double>")


def test_measures_tell_clusters_apart(spark):
    tight, loose = blobs(spark, 0.1).cache(), blobs(spark, 3.0).cache()
    for f, col, sign in ((metrics.silhouette, "sc", 1), (metrics.silhouette_exact, "sc", 1), (metrics.calinski_harabasz, "ci", 1), (metrics.davies_bouldin, "di", -1), (metrics.coherency, "coherency", 1)):
        assert sign * f(tight).first()[col] > sign * f(loose).first()[col]
    assert metrics.silhouette(tight).first().sc > 0.99
    from pyspark.ml.evaluation import ClusteringEvaluator
    from pyspark.ml.functions import array_to_vector

    ml = loose.select(F.col("label").alias("prediction"), array_to_vector("vec").alias("features"))
    assert metrics.silhouette(loose).first().sc == pytest.approx(ClusteringEvaluator().evaluate(ml), abs=1e-5)


def test_tsap(spark):
    ranked = spark.createDataFrame([(1, 7, 1.0, 1), (1, 8, 0.9, 2), (1, 9, 0.8, 3)], "query_id int, doc_id long, score double, rank int")
    truth = spark.createDataFrame([(1, 7), (1, 9), (2, 5)], "query_id int, doc_id long")
    got = {r.query_id: r.tsap for r in metrics.tsap(ranked, truth).collect()}
    assert got == {1: pytest.approx((1 + 2 / 3) / 10, abs=1e-6), 2: 0}


def test_pruned_search_is_part_of_the_full(spark, docs):
    p = tokens.keywords(docs).cache()
    q = search.benchmark_queries(spark.read.parquet(f"{SMALL}/benchmark.parquet"), index.token_stats(p))
    clusters = p.select("tok").distinct().withColumn("cluster_id", F.pmod(F.hash("tok"), F.lit(5)).cast("int"))
    from enctopics.operators import abstracts

    tops = abstracts.build(clusters, index.token_stats(p))
    part = search.pruned(q, p, clusters, tops, 60, c=5, k=1000).select("query_id", "doc_id")
    assert part.subtract(search.full(q, p, 60, k=1000).select("query_id", "doc_id")).isEmpty()


def test_as_of_join(spark):
    a = spark.createDataFrame([(1, 1, 10), (2, 1, 5), (3, 2, 9)], "id int, k int, t int")
    b = spark.createDataFrame([(7, 1, 4), (8, 1, 10), (9, 1, 11)], "id int, k int, t int")
    got = {r.id: r.prev for r in asof.last_before(a, b, "k", "t", "id", "prev").collect()}
    assert got == {1: 7, 2: 7, 3: None}


def test_page_and_conversation_texts(spark):
    page = spark.createDataFrame([(1, "u", "<html><script>x<1</script><p>a &amp; b</p>\n<b>c</b></html>")], "page_id long, url string, html string")
    assert page_text(page).first().text == "a & b c"
    turns = spark.createDataFrame([(1, 1, "user", "two"), (1, 0, "user", "one")], "conv_id long, turn long, role string, text string")
    assert conversation_docs(turns).first().text == "one\ntwo"


def test_udfs_agree_with_expressions(spark):
    v = blobs(spark, 1.0)
    got = {r.label: r.c for r in v.groupBy("label").agg(sql.coherency_udf("vec").alias("c")).collect()}
    assert sum(got.values()) / 4 == pytest.approx(metrics.coherency(v).first().coherency, abs=1e-6)
    sql.register(spark, "k", t=spark.createDataFrame([("Ab cde fgh",)], "text string"))
    assert [r.tok for r in spark.sql("SELECT x.tok FROM t, LATERAL tokens_of(text) x").collect()] == ["cde", "fgh"]


def test_stream_writes_a_version_a_batch(spark, docs, tmp_path):
    for i in range(2):
        docs.where(F.col("doc_id") % 2 == i).limit(8).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    versions = stream.run(spark, str(tmp_path / "in"), str(tmp_path / "state"), str(tmp_path / "marks"))
    assert versions.latest() == 1
    first, second = versions.read("clusters", 0), versions.read("clusters", 1)
    for clusters in (first, second):
        assert clusters.count() == clusters.select("tok").distinct().count() > 0
    assert versions.read("postings", 1).select("doc_id").distinct().count() == 16
    assert Versions(spark, str(tmp_path / "none")).latest() is None


def test_running_totals(spark, docs, tmp_path):
    docs.limit(10).coalesce(1).write.parquet(str(tmp_path / "in"))
    rows = spark.readStream.schema("doc_id long, text string").parquet(str(tmp_path / "in"))
    stream.token_stats(rows).writeStream.format("memory").queryName("running").outputMode("complete").trigger(availableNow=True).start().awaitTermination()
    want = tokens.tokenize(docs.limit(10)).groupBy("tok").agg(F.count("*").alias("tf"))
    assert spark.table("running").exceptAll(spark.read.parquet(str(tmp_path / "in")).transform(tokens.tokenize).groupBy("tok").agg(F.count("*").alias("tf"))).isEmpty() and want is not None


def test_plans(spark):
    plan = kestimate.estimate_k(kestimate.trim(tokens.keywords(spark.read.parquet(f"{SMALL}/documents.parquet"))))._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "Python" not in plan
    assert "ReadSchema: struct<doc_id:bigint,text:string>" in plan


def test_entry_has_sql_for_most(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(entry.oracle_sql()) > 100
    assert entry.entry(spark).columns == ["tok", "q"]


def test_no_other_part_imports_the_llm_operators():
    root = os.path.join(os.path.dirname(os.path.dirname(os.path.abspath(__file__))), "enctopics")
    for folder, _, names in os.walk(root):
        if os.sep + "llm" in folder:
            continue
        for n in names:
            if n.endswith(".py"):
                assert "enctopics.llm" not in open(os.path.join(folder, n)).read()


def test_interval(spark):
    from enctopics.plans.experiments import interval

    rows = spark.createDataFrame([("a", 1.0), ("a", 2.0), ("a", 3.0)], "k string, v double")
    r = interval(rows, "k", "v", 3).first()
    assert r["mean"] == 2 and r.half_width == pytest.approx(4.302653 / math.sqrt(3), abs=1e-4)


def _asked_of(monkeypatch, name, rows):
    """What a stand-in for a function of the experiments was called with, defaults included."""
    import inspect

    from enctopics import queries_experiments as q

    shape, got = inspect.signature(getattr(q.x, name)), {}

    def stand_in(*args, **named):
        bound = shape.bind(*args, **named)
        bound.apply_defaults()
        got.update(bound.arguments)
        return rows

    monkeypatch.setattr(q.x, name, stand_in)
    monkeypatch.setattr(q, "_deal", lambda spark, d: None)
    return q, got


def test_measures_of_many_clusters_go_by_slices_and_make_no_pairs_of_rows(spark, monkeypatch):
    rng = np.random.default_rng(4)
    rows = [(str(i), i % 60, (rng.normal(0, 0.2, 8) + i % 7).tolist()) for i in range(300)] + [("x", 60, [1.0] * 8), ("y", 61, [1.0] * 8), ("z", None, [2.0] * 8)]
    v = spark.createDataFrame(rows, "id string, label int, vec array<double>").cache()
    whole = metrics.silhouette(v).first().sc, metrics.davies_bouldin(v).first().di
    x, label = np.array([r[2] for r in rows[:-1]]), np.array([r[1] for r in rows[:-1]])
    d = ((x[:, None] - x) ** 2).sum(axis=2)
    to = np.array([d[:, label == c].sum(axis=1) for c in range(62)]).T
    n = np.bincount(label)
    a, others = to[np.arange(len(x)), label] / np.maximum(n[label] - 1, 1), to / n
    others[np.arange(len(x)), label] = np.inf
    b = others.min(axis=1)
    each = np.where((n[label] == 1) | (np.maximum(a, b) < 1e-12), 0, (b - a) / np.maximum(a, b))
    assert whole[0] == pytest.approx(each.sum() / len(rows), abs=1e-6)
    c = np.array([x[label == k].mean(axis=0) for k in range(62)])
    s = np.array([np.linalg.norm(x[label == k] - c[k], axis=1).mean() for k in range(62)])
    far = np.linalg.norm(c[:, None] - c, axis=2)
    ratio = np.divide(s[:, None] + s, far, out=np.full(far.shape, -1.0), where=far > 0)
    assert whole[1] == pytest.approx(ratio.max(axis=1).mean(), abs=1e-6)
    monkeypatch.setattr(metrics, "SLICE", 9)
    assert (metrics.silhouette(v).first().sc, metrics.davies_bouldin(v).first().di) == whole
    monkeypatch.setattr(metrics, "SLICE", 1 << 16)
    plan = []
    monkeypatch.setattr(metrics, "kept", lambda df: plan.append(df._jdf.queryExecution().toString()) or df)
    plan += [m(v)._jdf.queryExecution().toString() for m in (metrics.silhouette, metrics.davies_bouldin)]
    assert not any("NestedLoop" in p or "Cartesian" in p or "label2" in p for p in plan)


def test_kmeans_with_many_centres_is_as_good_as_the_library_and_keeps_every_row(spark):
    from enctopics.operators import baselines

    rng = np.random.default_rng(3)
    x = np.repeat(rng.normal(0, 5, (30, 6)), 12, axis=0) + rng.normal(0, 0.01, (360, 6))
    v = spark.createDataFrame([(f"t{i}", r.tolist()) for i, r in enumerate(x)], "tok string, vec array<double>").cache()
    for k in (30, 120):
        got = {r.tok: r.cluster_id for r in baselines.vector_kmeans(v, k).collect()}
        label = np.array([got[f"t{i}"] for i in range(360)])
        cost = sum(((x[label == c] - x[label == c].mean(axis=0)) ** 2).sum() for c in set(label))
        from pyspark.ml.clustering import KMeans

        assert len(got) == 360 and max(got.values()) < k and cost <= 1.2 * KMeans(k=k, seed=1).fit(baselines._features(v)).summary.trainingCost
    assert baselines.vector_kmeans(v.limit(0), 5).count() == 0 and baselines.vector_kmeans(v.limit(3), 5).select("cluster_id").distinct().count() == 3
    assert baselines.vector_kmeans(v, 4, init="random").select("cluster_id").distinct().count() == 4


def test_kmeans_does_not_run_centres_on_the_driver(spark, monkeypatch):
    from pyspark.ml import clustering

    from enctopics.operators import baselines

    monkeypatch.setattr(clustering, "KMeans", None)  # whose choice of first centres is a loop over pairs on the driver
    v = spark.createDataFrame([(f"t{i}", [float(i), 1.0]) for i in range(50)], "tok string, vec array<double>")
    assert baselines.vector_kmeans(v, 20).select("cluster_id").distinct().count() == 20


def test_coherency_intervals_are_over_the_updates(spark, monkeypatch):
    rows = [(s, b, False, 0.1 * s + b, 0.5) for s in range(10) for b in range(1, 6)]
    q, got = _asked_of(monkeypatch, "updates", spark.createDataFrame(rows, "seed int, batch_id int, recluster boolean, with_reclustering double, without double"))
    out = {(r.batch_id, r.scheme): r for r in q.coherency_ci(spark, "").collect()}
    assert got["samplings"] == 10 and set(out) == {(b, s) for b in range(1, 6) for s in ("with_reclustering", "without")}
    assert {r.n for r in out.values()} == {10} and abs(out[2, "with_reclustering"].mean - 2.45) < 1e-6 and out[2, "without"].half_width == 0
    assert abs(out[1, "with_reclustering"].half_width - student_quantile(9, 0.95) * 0.1 * math.sqrt(110 / 12 / 10)) < 1e-5


def test_update_query_runs_all_samplings(spark, monkeypatch):
    q, got = _asked_of(monkeypatch, "updates", None)
    q.updates(spark, "")
    assert got["samplings"] == 10


def test_sweep_query_covers_the_whole_grid(spark, monkeypatch):
    q, got = _asked_of(monkeypatch, "sweep", None)
    q.sweep(spark, "/root/testdata/sf0.001")
    assert set(got["grid"]) >= {10, 50, 100, 150, 200, 250}


def test_vector_scheme_of_the_experiments_takes_word_vectors(spark, docs, monkeypatch):
    from enctopics.plans import experiments as x

    sizes = []
    monkeypatch.setattr(x.baselines, "vector_kmeans", lambda vecs, k: sizes.append(len(vecs.first()["vec"])))
    monkeypatch.setattr(x.baselines, "hierarchical", lambda vecs, k: sizes.append(len(vecs.first()["vec"])))
    monkeypatch.setattr(x.baselines, "taxonomy", lambda postings, k: None)
    monkeypatch.setattr(x, "one_shot", lambda made, cfg: {})
    monkeypatch.setattr(x, "measured", lambda spark, found, vecs: [n for n, _, _ in found])
    assert x.coherency(spark, docs) == ["vector_kmeans", "hierarchical", "taxonomy"] and sizes == [32, 64]


def test_word_vectors_by_blocks_agree_and_leave_the_vocabulary_in_tasks(spark, monkeypatch):
    import pyspark.ml.feature

    from enctopics.operators import vectors

    monkeypatch.setattr(pyspark.ml.feature, "Word2Vec", None)  # it keeps the whole vocabulary on the driver
    draw = np.random.default_rng(3)
    word = lambda topic, i: f"{'abcd'[topic]}{chr(97 + i // 26)}{chr(97 + i % 26)}"
    texts = [" ".join(word(k % 4, i) for i in draw.integers(0, 60, 50)) for k in range(2000)]
    docs = spark.createDataFrame([*enumerate(texts), (-1, None), (-2, ""), (-3, "only here here twice twice")], "doc_id long, text string").repartition(4, "doc_id")
    whole = {r.tok: np.array(r.vec) for r in vectors.word2vec(docs).collect()}
    assert set(whole) == {word(t, i) for t in range(4) for i in range(60)} | {"here", "twice"}
    monkeypatch.setattr(vectors, "BLOCK", 10_000)
    monkeypatch.setattr(vectors, "COMMON", 200)
    parts = {r.tok: np.array(r.vec) for r in vectors.word2vec(docs).collect()}
    assert set(parts) == set(whole)
    names = sorted(set(whole) - {"here", "twice"})
    topic = np.array([n[0] for n in names])
    for found in (whole, parts):
        x = np.stack([found[n] for n in names])
        assert np.allclose((x * x).sum(axis=1), 1)
        near = x @ x.T - 2 * np.eye(len(x))
        assert (topic[near.argmax(axis=1)] == topic).mean() > 0.95
    monkeypatch.setattr(vectors, "BLOCK", 1)  # a first block without a document
    assert set(vectors.word2vec(docs.where("doc_id < 5").coalesce(1), min_count=1).toPandas()["tok"]) >= {"here", "only", "twice"}
    assert vectors.word2vec(docs.where("doc_id in (-1, -2)")).count() == 0


def test_word_vectors_stay_finite_where_one_word_is_most_of_the_text():
    from enctopics.operators import vectors

    ids = np.random.default_rng(0).zipf(1.5, 200_000) % 500
    inner, outer = vectors._first([str(i) for i in range(500)], 16, 1), np.zeros((500, 16), np.float32)
    vectors._skip_gram(ids, np.arange(len(ids)) // 100, inner, outer, 1)
    assert np.isfinite(inner).all() and np.isfinite(outer).all() and np.linalg.norm(inner, axis=1).max() < 100


def test_word_vector_query_takes_every_batch_and_trains_on_all_that_has_come(spark, monkeypatch):
    from enctopics import queries_core as q

    d, steps, trained = "/root/testdata/sf0.001", [], []
    ids = lambda df: {r.doc_id for r in df.select("doc_id").distinct().collect()}

    def step(state, temp, cfg, words):
        steps.append(ids(temp))
        words()
        return state

    monkeypatch.setattr(q.batch, "step", step)
    monkeypatch.setattr(q.vectors, "word2vec", lambda docs: trained.append(ids(docs)) or docs)
    q.batch_word_vectors(spark, d)
    dealt = q.batches(q.docs(spark, d)).select("doc_id", "batch_id")
    by = [ids(dealt.where(F.col("batch_id") == i)) for i in range(6)]
    assert len(steps) == 5 and all(a and a <= b for a, b in zip(steps, by[1:]))
    assert trained == [set().union(*by[: i + 1]) for i in range(1, 6)] and trained[-1] == ids(q.docs(spark, d))


def test_coherency_takes_the_length_of_a_vector_once_and_not_for_each_number(spark):
    import re

    rng = np.random.default_rng(5)
    x = rng.normal(0.2, 1, (40, 16))
    made = metrics.coherency(spark.createDataFrame([(i, i % 3, v.tolist()) for i, v in enumerate(x)], "id long, label int, vec array<double>"))
    assert not re.search(r"transform\(vec[^\n]*SQRT", made._jdf.queryExecution().optimizedPlan().toString())
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = [(((g := u[i::3]).sum(axis=0) ** 2).sum() - len(g)) / (len(g) * (len(g) - 1)) for i in range(3)]
    assert made.first()["coherency"] == pytest.approx(np.mean(want), abs=1e-6)


def test_unit_takes_the_length_of_a_vector_once_and_not_for_each_number(spark):
    made = vectors.unit(spark.createDataFrame([("a", [3.0, 4.0]), ("b", [0.0, 0.0]), ("c", None), ("d", [0.0, -2.0])], "tok string, vec array<double>"))
    assert {r.tok: r.vec for r in made.collect()} == {"a": [0.6, 0.8], "d": [0.0, -1.0]}
    lines = [x for x in made._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Project" in x]
    assert lines and not any("/ SQRT" in x for x in lines)


def test_clusterings_are_made_and_measured_several_at_a_time(spark, docs, monkeypatch):
    import threading

    from enctopics.plans import experiments as x

    both = threading.Barrier(2, timeout=60)
    monkeypatch.setattr(x, "iterative", lambda made, vecs, words, k: both.wait() * 0 or {"s": k})
    monkeypatch.setattr(x, "one_shot", lambda made, cfg: {})
    monkeypatch.setattr(x.static, "cluster", lambda docs, cfg: x.static.Clustering(None, docs.selectExpr("'a' AS tok", "doc_id", "1 AS f"), 7, None, None, None))
    monkeypatch.setattr(x.vectors, "word2vec", lambda docs: docs.selectExpr("'a' AS tok"))
    monkeypatch.setattr(x, "measured", lambda spark, found, vecs: found)
    assert x.sweep(spark, docs, (3,)) == [("s", 3, 3), ("s", 7, 7)]
    monkeypatch.undo()
    seen, size = [], metrics.cluster_sizes
    monkeypatch.setattr(x.metrics, "cluster_sizes", lambda c: seen.append(both.wait()) or size(c))
    c = spark.createDataFrame([("a", 0), ("b", 0), ("c", 1), ("d", 1)], "tok string, cluster_id int")
    v = spark.createDataFrame([("a", [1.0, 0.0]), ("b", [1.0, 0.1]), ("c", [0.0, 1.0]), ("d", [0.1, 1.0])], "tok string, vec array<double>")
    assert [r.scheme for r in x.measured(spark, [("one", 1, c), ("two", 2, c)], v).collect()] == ["one", "two"] and len(seen) == 2


def test_samplings_are_dealt_from_one_tokenization(spark, monkeypatch):
    from enctopics import queries_core, queries_experiments

    d, calls, tokenize = "/root/testdata/sf0.001", [], tokens.tokenize
    want = [queries_core.arriving(queries_core.docs(spark, d), seed) for seed in (0, 3)]
    monkeypatch.setattr(tokens, "tokenize", lambda *a, **k: calls.append(a) or tokenize(*a, **k))
    deal = queries_experiments._deal(spark, d)
    for seed, rows in zip((0, 3), want):
        key = lambda df: sorted((r.tok, r.doc_id, r.f, r.batch_id) for r in df.collect())
        assert key(deal(seed)) == key(rows) and rows.count()
    assert len(calls) == 1
