"""Products of blocks against brute force, with blocks far smaller than the sides."""

import os

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from treegraph.functions import vectors as V
from treegraph.operators import blocks, traverse
from treegraph.sources.graphs import graph_e, queries_e

DIR = "/root/testdata/sf0.001"
needs_data = pytest.mark.skipif(not os.path.isdir(DIR), reason="no test data")


def sides(spark, n=300, q=40, copies=90):
    """Unit vectors, the first `copies` nodes all alike."""
    rng = np.random.default_rng(1)
    x = rng.normal(size=(n, 8))
    x[:copies] = x[0]
    x /= np.linalg.norm(x, axis=1)[:, None]
    nodes = [(f"v:{i}", [float(a) for a in v]) for i, v in enumerate(x)]
    queries = [(f"q:{i}", [float(a) for a in v]) for i, v in enumerate(x[n - q :])] + [("q:c", nodes[0][1])]
    return spark.createDataFrame(queries, "query_id string, embedding array<double>"), spark.createDataFrame(nodes, "node_id string, embedding array<double>"), queries, nodes


def brute(queries, nodes, k):
    out = set()
    for q, v in queries:
        s = sorted((-round(sum(a * b for a, b in zip(v, w)), 9), n) for n, w in nodes)
        out |= {(q, n) for _, n in s[:k]}
    return out


def test_topk_over_many_blocks_and_copies(spark):
    q, v, queries, nodes = sides(spark)
    from treegraph.operators.scoring import cut

    got = cut(blocks.topk(q, v, 7, rows=11, columns=23), 7, "cos").collect()
    assert {(r.query_id, r.node_id) for r in got} == brute(queries, nodes, 7)


def test_with_cosine_keeps_each_candidate(spark, monkeypatch):
    monkeypatch.setattr(blocks, "ROWS", 11)
    monkeypatch.setattr(blocks, "COLUMNS", 23)
    q, v, _, _ = sides(spark)
    cands = q.crossJoin(v.withColumnRenamed("embedding", "e")).where("hash(query_id, node_id) % 3 = 0").select("query_id", "node_id", F.lit(0.5).alias("seed_score"))
    cands = cands.unionByName(spark.createDataFrame([("q:c", "v:none", 0.5)], cands.schema))
    got = sorted(blocks.with_cosine(cands, q, v).select("query_id", "node_id", "seed_score", "cos").collect())
    want = cands.join(v, "node_id").join(q.withColumnRenamed("embedding", "qv"), "query_id").select("query_id", "node_id", "seed_score", V.cosine("qv", "embedding").alias("cos"))
    assert got == sorted(want.collect())


@needs_data
@pytest.mark.parametrize("name", ["b1_vector", "b3_hybrid", "td_cosine", "hz_rrf", "hz_allowed", "hz_centroid", "bu_parent", "bu_agg", "bu_rrf", "bu_both", "bu_parents_agg", "filter_cosine"])
def test_no_row_for_every_pair(spark, name):
    """Pairs of a query and a node are cells of a product, never rows of a join without a key."""
    plan = entry.queries()[name](spark, DIR)._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan
    if name == "filter_cosine":  # normalises its vectors, but joins no pairs
        assert "NestedLoop" not in plan and "InArrow" in plan
    else:
        assert "zip_with" not in plan


@needs_data
def test_large_families_are_scored_alike(spark):
    g = graph_e(spark, DIR)
    q = queries_e(spark, DIR, g)[0]
    rows = lambda **o: sorted(map(tuple, traverse.parent_scores(g, q, 5, **o).select("query_id", "parent_id", F.round("agg_score", 6), "n_children", "n_above").collect()))
    assert rows() == rows(family=6) and len(rows()) > 50


@needs_data
def test_children_of_lower_parents_are_left_out_only_behind_k(spark):
    """More children asked for than any parent has: all parents stay."""
    g = graph_e(spark, DIR)
    q = queries_e(spark, DIR, g)[0].limit(3)
    got = traverse.bottomup(g, q, 40, "agg", c=20)
    assert [r["count"] for r in got.groupBy("query_id").count().collect()] == [40] * 3


def test_normalising_evaluates_its_vector_once(spark):
    seen = spark.sparkContext.accumulator(0)

    @F.udf("array<double>")
    def vector(x):
        seen.add(1)
        return [3.0, 4.0, 0.0]

    spark.range(10).select(V.l2_normalise(V.scale(vector("id"), 2.0)).alias("v")).write.format("noop").mode("overwrite").save()
    got = spark.createDataFrame([([3.0, 4.0],), ([0.0, 0.0],), (None,)], "v array<double>").select(V.l2_normalise("v").alias("v")).collect()
    assert [r.v for r in got] == [[0.6, 0.8], [0.0, 0.0], None] and seen.value <= 10


def test_weighted_centroid_counts_rows(spark):
    few = spark.createDataFrame([("a", [1.0, 0.0], 3), ("a", [0.0, 1.0], 1)], "k string, embedding array<double>, c long")
    many = spark.createDataFrame([("a", [1.0, 0.0])] * 3 + [("a", [0.0, 1.0])], "k string, embedding array<double>")
    assert V.centroid(few, ["k"], weight="c").collect() == V.centroid(many, ["k"]).collect()


def test_lexical_search_over_many_blocks(spark, monkeypatch):
    """Texts with frequent and rare terms, copies and empty ones, against the formula; before, a row stood for every shared term."""
    import math

    from treegraph.operators import search

    rng = np.random.default_rng(2)
    texts = [(f"v:{i}", [f"w{int(x)}" for x in rng.zipf(1.6, size=rng.integers(0, 30)) if x < 60]) for i in range(120)]
    texts += [(f"v:c{i}", texts[5][1]) for i in range(20)]
    asks = [(f"q:{i}", t) for i in range(0, 120, 6) for t in sorted(set(texts[i][1]) | {"nowhere"})]
    monkeypatch.setattr(search, "ASKED", 7)
    monkeypatch.setattr(search, "HELD", 3)
    monkeypatch.setattr(blocks, "COLUMNS", 31)
    t, q = spark.createDataFrame(texts, "node_id string, tokens array<string>"), spark.createDataFrame(asks, "query_id string, term string")
    frame = search.bm25_topk(q, t, 8)
    got = {(r.query_id, r["rank"]): (r.node_id, round(r.score, 6)) for r in frame.collect()}
    assert "Join" not in frame._jdf.queryExecution().executedPlan().toString()  # no row for a shared term
    n, avg = len(texts), sum(len(x) for _, x in texts) / len(texts)
    df = {w: sum(w in x for _, x in texts) for w in {w for _, x in texts for w in x}}
    want = {}
    for name in {a for a, _ in asks}:
        s = []
        for node, x in texts:
            both = [w for a, w in asks if a == name and w in x]
            if both:
                s.append((-round(sum(math.log(1 + (n - df[w] + 0.5) / (df[w] + 0.5)) * x.count(w) * 2.2 / (x.count(w) + 1.2 * (0.25 + 0.75 * len(x) / avg)) for w in both), 9), node))
        want |= {(name, i + 1): (node, round(-v, 6)) for i, (v, node) in enumerate(sorted(s)[:8])}
    assert got == want


@needs_data
def test_pairs_of_sections_as_rows_have_them(spark):
    from treegraph.operators import construct

    rows = construct.centroid_filter(construct.candidate_pairs(spark, DIR), construct.relation_ontology(spark, DIR))
    got = construct.scored_pairs(spark, DIR)
    few = lambda df: sorted((r.a, r.b, round(r.best, 8), r.rel_type) for r in df.where("hash(a, b) % 20 = 0").collect())
    assert few(got) == few(rows) and got.count() == rows.count()


def test_quantile_and_signed_sums(spark):
    from treegraph.operators import construct

    x = spark.range(1001).select(F.round(F.sin("id"), 9).alias("x"))
    for p in (0.0, 0.37, 0.5, 1.0):
        want = x.agg(F.percentile("x", F.lit(p))).first()[0]
        assert abs(construct.quantile(x, "x", p) - want) < 1e-12
    assert construct.quantile(x.limit(0), "x", 0.5) is None
    t = spark.createDataFrame([("a", ["one", "two", "one"]), ("b", ["three"])], "k string, t array<string>")
    one = {r.k: r.embedding for r in V.hash_embed(t, ["k"], "t").collect()}
    two = {r.k: r.e for r in t.unionByName(spark.createDataFrame([("c", [])], t.schema)).select("k", V.signed_sums(F.transform("t", lambda w: F.xxhash64(w))).alias("e")).collect()}
    assert two == one | {"c": [0.0] * 64}
