"""The approximate index against its definition: candidates share a code in some table, exact cosines rank them."""

import numpy as np
from pyspark.sql import functions as F

from treegraph.operators import scoring as S
from treegraph.operators import search


def unit(rng, n, dim):
    x = rng.normal(size=(n, dim))
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def test_index_finds_the_best_of_the_shared_buckets(spark, monkeypatch):
    rng = np.random.default_rng(3)
    x, y = unit(rng, 30, 8), unit(rng, 400, 8)
    y[7] = y[8]  # a tie
    q = spark.createDataFrame([(f"q:{i}", v.tolist()) for i, v in enumerate(x)], "query_id string, embedding array<double>")
    n = spark.createDataFrame([(f"v:{i}", v.tolist()) for i, v in enumerate(y)], "node_id string, embedding array<double>")
    options = {"bits": 4, "tables": 3, "seed": 5, "dim": 8}
    a = search.hyperplane_codes(q, "query_id", probes=2, **options)
    b = search.hyperplane_codes(n, "node_id", probes=0, **options)
    pairs = a.join(b, ["table", "bucket"]).select("query_id", "node_id").distinct()
    want = S.cut(pairs.join(search.scored(q, n), ["query_id", "node_id"]), 6, "cos")
    monkeypatch.setattr(search, "written", lambda df, name: (_ for _ in ()).throw(AssertionError("a copy of the rows for each code")))
    got = search.ann_topk(q, n, 6, probes=2, **options)
    rows = lambda df: sorted(map(tuple, df.select("query_id", "node_id", F.round("score", 8), "rank").collect()))
    assert rows(got) == rows(want)
    assert search.ann_topk(q, n.limit(0), 6, **options).count() == 0
