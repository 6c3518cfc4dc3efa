"""Streams against what the same rows give at once."""

from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F

from enctopics import queries_streams as q
from enctopics.operators import tokens
from enctopics.plans import experiments
from enctopics.registry import SQL
from enctopics.streaming import events as ev
from enctopics.streaming import stream

SMALL = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["stream_windows", "stream_once", "stream_static_join", "stream_stream_join", "stream_token_stats"])
def test_streams_equal_their_batch_twins(spark, name):
    con = duckdb.connect()
    for t in ("events", "customer", "documents"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    got = getattr(q, name)(spark, SMALL)
    want = con.execute(SQL[name]).fetchall()
    names = [c[0] for c in con.description]
    assert sorted(map(tuple, got.select(*names).collect())) == sorted(want) and want


def _files(spark, path, *files):
    for rows in files:
        spark.createDataFrame(rows, "id long, ts string").withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.mode("append").parquet(path)


def test_late_rows_are_dropped(spark, tmp_path):
    """A micro-batch drops what was late when the one before it began, so the late row comes two after."""
    at = lambda clock: f"2024-01-01 {clock}:00"
    _files(spark, str(tmp_path / "in"), [(1, at("00:10")), (1, at("05:00"))], [(1, at("04:30"))], [(1, at("00:20"))])
    rows = ev.timed(ev.arriving(spark, str(tmp_path / "in"), 1))
    got = ev.appended(ev.closed_windows(rows, "id")).collect()
    assert [(str(r.start), r.id, r.n) for r in got] == [(at("00:00"), 1, 1)]


def test_a_key_comes_again_once_the_watermark_has_left_it(spark, tmp_path):
    at = lambda clock: f"2024-01-01 {clock}:00"
    _files(spark, str(tmp_path / "in"), [(1, at("00:10")), (2, at("05:00"))], [(2, at("05:30")), (3, at("05:30"))], [(1, at("06:00")), (3, at("05:40"))])
    got = ev.appended(ev.once(ev.timed(ev.arriving(spark, str(tmp_path / "in"), 1)), "id")).collect()
    assert sorted(r.id for r in got) == [1, 1, 2, 3]


def test_no_rows(spark, tmp_path):
    _files(spark, str(tmp_path / "in"), [])
    rows = lambda: ev.timed(ev.arriving(spark, str(tmp_path / "in")))
    assert ev.appended(ev.closed_windows(rows(), "id")).isEmpty()
    assert ev.appended(ev.followed(rows(), rows(), "id", "id", "1 hour")).isEmpty()


def test_totals_with_a_state_of_their_own(spark, tmp_path):
    docs = spark.createDataFrame([(1, "one two two"), (2, "two three")], "doc_id long, text string")
    for i in (1, 2):
        docs.where(F.col("doc_id") == i).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    seen: list[dict] = []
    keep = lambda df, _: seen.append({r.tok: r.tf for r in df.collect()})
    rows = stream.token_totals(ev.arriving(spark, str(tmp_path / "in"), 1))
    rows.writeStream.foreachBatch(keep).outputMode("update").option("checkpointLocation", str(tmp_path / "marks")).trigger(availableNow=True).start().awaitTermination()
    want = {r.tok: r.n for r in tokens.tokenize(docs).groupBy("tok").agg(F.count("*").alias("n")).collect()}
    assert {k: v for batch in seen for k, v in batch.items()} == want and seen[1]["two"] == 3


def test_a_stream_is_batches_of_one_document(spark, tmp_path):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").where("n_chars < 3000").orderBy("doc_id").limit(2).select("doc_id", "text")
    got = experiments.stream_replay(spark, docs, str(tmp_path)).collect()
    assert [(r.version, r.differing) for r in got] == [(0, 0), (1, 0)] and all(r.streamed == r.batched > 0 for r in got)
