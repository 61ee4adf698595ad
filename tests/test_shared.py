"""What several methods need is computed once, and not again where it is stored; grades against their SQL."""

import os
import shutil

import pytest

from tests.test_findings import against_sql
from treegraph.operators import search
from treegraph.plans import workloads
from treegraph.sources.graphs import graph_e, queries_e

DIR = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")


@pytest.fixture
def fresh(tmp_path):
    """Tables of their own, from which nothing is derived yet."""
    for t in ("embeddings", "documents"):
        shutil.copy(f"{DIR}/{t}.parquet", tmp_path)
    return str(tmp_path)


def test_stored_queries_and_labels_start_no_count(spark, monkeypatch):
    queries_e(spark, DIR, graph_e(spark, DIR))

    def counted(self, *args):
        raise AssertionError("counts what is stored")

    frame = type(spark.range(0))
    for name in ("count", "first"):
        monkeypatch.setattr(frame, name, counted)
    queries_e(spark, DIR, graph_e(spark, DIR))


def test_comparisons_search_once(spark, fresh, monkeypatch):
    asked = {"vector": [], "lexical": []}
    vector, terms = search.vector_topk, search.bm25_topk
    monkeypatch.setattr(search, "vector_topk", lambda q, n, k, **o: asked["vector"].append(k) or vector(q, n, k, **o))
    monkeypatch.setattr(search, "bm25_topk", lambda q, n, k, **o: asked["lexical"].append(k) or terms(q, n, k, **o))
    runs = workloads.all_runs(spark, fresh)
    assert asked == {"vector": [workloads.DEPTH], "lexical": [workloads.DEPTH]}
    assert {r.method for r in runs.select("method").distinct().collect()} == set(workloads.METHODS)


@pytest.mark.parametrize("name", ["qrels_e", "eval_cutoffs", "eval_directions", "gain_by_k", "eval_overall", "measures_b1"])
def test_comparisons_against_sql(spark, name):
    got, want = against_sql(spark, name, tables=("embeddings", "documents"))
    assert got == want
