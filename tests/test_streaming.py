"""Streams give what their batch twins give."""

import os

import pytest

from treegraph.streaming import log

DIR = "/root/testdata/sf0.001"


@pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")
def test_tumbling_stream_equals_batch(spark, tmp_path):
    e = spark.read.parquet(f"{DIR}/events.parquet")
    e.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = log.tumbling(log.read_events(spark, str(tmp_path / "in"), e.schema))
    got = log.run_to_end(stream, "tumbling", str(tmp_path / "ck"), "complete").collect()
    assert sorted(got) == sorted(log.tumbling(e).collect())


def test_construct_is_idempotent(spark, tmp_path):
    one = spark.createDataFrame([("a b",), ("b c",), ("A b!",)], "sentence string")
    two = spark.createDataFrame([("b c",), ("c d",), (None,)], "sentence string")
    for i, b in ((0, one), (1, two), (1, two)):
        log.construct(b, i, str(tmp_path / "canon"))
    got = [{r.sentence: r.canonical for r in spark.read.parquet(str(tmp_path / f"canon/batch-{i}")).collect()} for i in (0, 1)]
    assert got[0] == {"a b": "A b!", "A b!": "A b!", "b c": "b c"} and got[1] == {"b c": "b c", "c d": "c d"}


@pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")
def test_stateful_stream_equals_its_twin(spark, tmp_path):
    e = spark.read.parquet(f"{DIR}/events.parquet")
    e.orderBy("ts", "event_id").coalesce(1).write.parquet(str(tmp_path / "in"))
    best = log.best_nodes(spark, DIR)
    stream = log.running_mrr_stream(log.read_events(spark, str(tmp_path / "in"), e.schema), best)
    got = log.run_to_end(stream, "running", str(tmp_path / "ck"), "update").groupBy("user_id").agg({"n": "max"}).collect()
    want = {r.user_id: r.n for r in log.running_mrr(e, best).collect()}
    assert {r[0]: r[1] for r in got if r[1]} == want


@pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")
def test_repeated_requests_and_retrieval_stream(spark, tmp_path):
    e = spark.read.parquet(f"{DIR}/events.parquet")
    e.orderBy("ts").coalesce(1).write.parquet(str(tmp_path / "in"))
    source = lambda: log.read_events(spark, str(tmp_path / "in"), e.schema)
    once = log.run_to_end(log.first_requests(source()), "once", str(tmp_path / "ck1")).count()
    assert 0 < once <= e.count()
    best = log.best_nodes(spark, DIR)
    got = log.run_to_end(log.retrieve(source(), best), "retrieved", str(tmp_path / "ck2"))
    assert sorted(got.collect()) == sorted(log.retrieve(e, best).collect())
