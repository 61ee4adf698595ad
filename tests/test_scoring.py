"""Hand-computed fusion, aggregation and measures."""

import hashlib
import math

import pytest
from pyspark.sql import functions as F

from treegraph.operators import construct, measures, scoring


def run(spark, rows):
    return spark.createDataFrame(rows, "query_id string, node_id string, score double, rank int")


def test_fusion_adds_nothing_for_a_missing_list(spark):
    a = run(spark, [("q", "x", 0.9, 1), ("q", "y", 0.8, 2), ("q", "z", 0.7, 3)])
    b = run(spark, [("q", "y", 5.0, 1), ("q", "x", 4.0, 2)])
    got = {r.node_id: r.score for r in scoring.rrf([a, b]).collect()}
    assert got == pytest.approx({"x": 1 / 61 + 1 / 62, "y": 1 / 62 + 1 / 61, "z": 1 / 63})


def test_equal_scores_share_a_rank(spark):
    d = spark.createDataFrame([("q", "a", 0.5), ("q", "b", 0.5), ("q", "c", 0.1)], "query_id string, node_id string, s double")
    assert {r.node_id: r.r for r in scoring.rank_within(d, "s", "r").collect()} == {"a": 1, "b": 1, "c": 3}
    assert {r.node_id: r.r for r in scoring.rank_within(d, "s", "r", ties="dense").collect()} == {"a": 1, "b": 1, "c": 2}


@pytest.mark.parametrize("scores", [[0.9, 0.5, 0.1], [0.9, 0.5, 0.3, 0.1], [0.7], [0.5, 0.5, 0.1], [-0.2, -0.4]])
def test_parent_score(spark, scores):
    d = spark.createDataFrame([("q", "p", s) for s in scores], "query_id string, parent_id string, s double")
    r = scoring.agg_score(d).first()
    s = sorted(scores)
    mid = (s[(len(s) - 1) // 2] + s[len(s) // 2]) / 2
    above = sum(x >= round(mid, 9) for x in s)
    assert r.n_above == above >= math.ceil(len(s) / 2)
    assert r.agg_score == pytest.approx(sum(s) / len(s) * math.log(1 + above), abs=1e-8)


def test_diversity_skips_the_copy(spark):
    v = spark.createDataFrame([("a", [1.0, 0.0]), ("b", [0.999, 0.0447]), ("c", [0.0, 1.0])], "node_id string, embedding array<double>")
    r = run(spark, [("q", "a", 0.9, 1), ("q", "b", 0.89, 2), ("q", "c", 0.6, 3)])
    order = lambda lam: [x.node_id for x in scoring.mmr(r, v, 3, lam).orderBy("rank").collect()]
    assert order(0.5) == ["a", "c", "b"] and order(1.0) == ["a", "b", "c"]


def test_measures(spark):
    runs = spark.createDataFrame([("m", "q", "a", 1), ("m", "q", "x", 2), ("m", "q", "b", 3)], "method string, query_id string, node_id string, rank int")
    labels = spark.createDataFrame([("q", "a", 2), ("q", "b", 1), ("q", "x", 0), ("none", "a", 0)], "query_id string, node_id string, grade int")
    queries = spark.createDataFrame([("q", "NT"), ("none", "TD")], "query_id string, direction string")
    got = {r.k: r for r in measures.per_query(runs, labels, queries).collect()}
    assert set(got) == {1, 3, 5, 10}
    assert got[3].ndcg == pytest.approx((2 + 1 / 2) / (2 + 1 / math.log2(3)))
    assert (got[1].recall, got[3].recall, got[10].precision, got[10].mrr) == (0.5, 1.0, 0.2, 1.0)
    exp = measures.per_query(runs, labels, queries, ks=(3,), gain="exp", denominator="returned").first()
    assert exp.ndcg == pytest.approx((3 + 1 / 2) / (3 + 1 / math.log2(3))) and exp.precision == pytest.approx(2 / 3)


def test_union_find():
    assert construct.union_find([1, 2, 5, 3], [2, 3, 6, 5], 8).tolist() == [0, 1, 1, 1, 4, 1, 1, 7]


def test_validator_names_the_step(spark):
    o = spark.createDataFrame([("part_of", [1.0, 0.0]), ("before", [0.0, 1.0])], "rel_type string, centroid array<double>")
    p = spark.createDataFrame([("Part Of", [0.0, -1.0], 9), ("within", [0.99, 0.14], 9), ("rare", [-1.0, 0.0], 1), ("new", [-1.0, 0.0], 3)], "name string, embedding array<double>, support int")
    got = {r.name: (r.step, r.verdict, r.alias_of) for r in construct.validate_types(p, o, weak=None, strong=None).collect()}
    assert got == {"Part Of": (1, "alias", "part_of"), "within": (2, "alias", "part_of"), "rare": (3, "rejected", None), "new": (0, "accepted", None)}
    judged = construct.validate_types(p, o, weak=None, strong=lambda j: F.col("name") != "new")
    assert {r.name: r.step for r in judged.collect()}["new"] == 5


def test_every_distinct_sentence_has_a_canonical_one(spark, tmp_path):
    rows = [(1, "Les. Erheed titionly. ***\nOne two three four five.", "fr", "web"), (51, "Les.\n***", "fr", "web")]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").write.parquet(str(tmp_path / "documents.parquet"))
    got = {r.node_id: r.canonical_id for r in construct.QUERIES["dedup_intra"](spark, str(tmp_path)).collect()}
    names = {x: hashlib.md5(x.encode()).hexdigest() for x in ("Les.", "Erheed titionly.", "***", "One two three four five.")}
    assert set(got) == set(names.values()) and got[names["***"]] == names["***"]
