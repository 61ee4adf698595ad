"""The experiments over the given tables, as queries (spark, dir) -> DataFrame."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..operators import measures as A
from ..operators import search, traverse
from ..operators.scoring import agg_score
from ..sources.graphs import GRAPH_TABLES, KINDS, graph_e, graph_s_edges, queries_e
from ..sources.stored import is_stored, stored
from ..sources.tables import load, words

K, DEPTH = 10, 100
RUN_TABLES = ("embeddings", "documents")
#: Methods that run at a time: jobs of one leave cores idle while they are planned and while their last tasks run.
AT_ONCE = 4


def node_texts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_id, tokens): a content node's text is the document of its number, where there is one."""
    d = load(spark, sf_dir, "documents").select("doc_id", "text")
    e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("doc_id"))
    return d.join(e, "doc_id", "left_semi").select(F.concat(F.lit("v:"), "doc_id").alias("node_id"), words("text").alias("tokens"))


def query_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(query_id, term): the distinct tokens of the query's own text."""
    t = node_texts(spark, sf_dir).withColumn("num", F.substring("node_id", 3, 20).cast("long")).where("num % 10 = 0")
    return t.select(F.concat(F.lit("q:"), "num").alias("query_id"), F.explode(F.array_distinct("tokens")).alias("term"))


def firsts(spark: SparkSession, d: str, name: str, tables: tuple[str, ...], k: int, build) -> DataFrame:
    """The stored run build() of the k first, or the k first of a longer one that is stored already: ranks don't depend on the length."""
    for more in (x for x in (traverse.SEEDS, K, traverse.CLIMBERS, DEPTH) if x > k):
        if is_stored(spark, d, f"{name}_{more}", tables):
            return stored(spark, d, f"{name}_{more}", tables, build).where(F.col("rank") <= k)
    return stored(spark, d, f"{name}_{k}", tables, build)


def _b1(spark, d, k=K):
    g = graph_e(spark, d)
    return search.vector_topk(queries_e(spark, d, g)[0], g.content, k)


def _b2(spark, d, k=K):
    return search.bm25_topk(query_terms(spark, d), node_texts(spark, d), k)


def nearest(spark, d, k=K):
    return firsts(spark, d, "nearest", GRAPH_TABLES, k, lambda: _b1(spark, d, k))


def lexical(spark, d, k=K):
    return firsts(spark, d, "lexical", RUN_TABLES, k, lambda: _b2(spark, d, k))


def _on_graph(f, **options):
    def run(spark: SparkSession, d: str) -> DataFrame:
        g = graph_e(spark, d)
        keep = lambda name, build: stored(spark, d, name, GRAPH_TABLES, build)
        if_kept = lambda name, build: keep(name, build) if is_stored(spark, d, name, GRAPH_TABLES) else build()
        near = lambda k: nearest(spark, d, k)
        parts = {traverse.topdown: {"keep": keep}, traverse.horizontal: {"near": near, "share": if_kept}, traverse.bottomup: {"near": near, "keep": keep}}
        return f(g, queries_e(spark, d, g)[0], K, **parts[f], **options)

    return run


METHODS = {
    "b1_vector": _b1,
    "b2_bm25": _b2,
    "b3_hybrid": lambda s, d: search.hybrid_topk(nearest(s, d, DEPTH), lexical(s, d, DEPTH), K),
    "td_cosine": _on_graph(traverse.topdown, variant="cosine"),
    "td_rrf": _on_graph(traverse.topdown, variant="rrf"),
    "td_mmr": _on_graph(traverse.topdown, variant="mmr"),
    "hz_cosine": _on_graph(traverse.horizontal, variant="cosine"),
    "hz_rrf": _on_graph(traverse.horizontal, variant="rrf"),
    "hz_filtered": _on_graph(traverse.horizontal, variant="filtered"),
    "bu_parent": _on_graph(traverse.bottomup, variant="parent"),
    "bu_agg": _on_graph(traverse.bottomup, variant="agg"),
    "bu_rrf": _on_graph(traverse.bottomup, variant="rrf"),
}



def run_of(spark: SparkSession, d: str, name: str) -> DataFrame:
    """One method's run, stored: the comparisons scan it."""
    method = {"b1_vector": nearest, "b2_bm25": lexical}.get(name, METHODS[name])
    rows = lambda: method(spark, d).select(F.lit(name).alias("method"), "query_id", "node_id", F.col("score").cast("double").alias("score"), F.col("rank").cast("int").alias("rank"))
    return stored(spark, d, f"run_{name}", RUN_TABLES, rows)


def all_runs(spark: SparkSession, d: str) -> DataFrame:
    """The twelve runs under their names. What several need is stored first; then some run at a time."""
    g = graph_e(spark, d)
    queries = queries_e(spark, d, g)[0]
    by_terms, by_edges = ("b2_bm25", "b3_hybrid"), ("hz_cosine", "hz_rrf")
    nearest(spark, d, DEPTH)

    def terms() -> None:
        lexical(spark, d, DEPTH)
        for name in by_terms:
            run_of(spark, d, name)

    def hops() -> None:
        start = nearest(spark, d, traverse.SEEDS)
        stored(spark, d, f"hop_{traverse.SEEDS}", GRAPH_TABLES, lambda: traverse.candidates(g, start, queries))
        for name in by_edges:
            run_of(spark, d, name)

    lines = [terms, hops, *[lambda name=name: run_of(spark, d, name) for name in METHODS if name not in by_terms + by_edges]]
    with ThreadPoolExecutor(AT_ONCE) as pool:
        for done in [pool.submit(inheritable_thread_target(spark)(line)) for line in lines]:
            done.result()
    return reduce(DataFrame.unionByName, [run_of(spark, d, name) for name in METHODS])


def measured(spark: SparkSession, d: str, **options) -> DataFrame:
    q, labels = queries_e(spark, d)
    return A.per_query(all_runs(spark, d), labels, q, **options)


def measured_one(name: str):
    def run(spark: SparkSession, d: str) -> DataFrame:
        q, labels = queries_e(spark, d)
        pq = A.per_query(run_of(spark, d, name), labels, q)
        return pq.select("method", "query_id", "direction", F.col("k").cast("int").alias("k"), *[F.round(c, 6).alias(c) for c in ("ndcg", "recall", "precision", "mrr")])

    return run


def eval_overall(spark, d):
    return A.overall(measured(spark, d))


def eval_cutoffs(spark, d):
    return A.by_cutoff(measured(spark, d))


def eval_directions(spark, d):
    return A.by_direction(measured(spark, d))


def gain_by_k(spark, d):
    """Difference of each method's gain from the vector baseline at each cutoff, in points."""
    m = A.by_cutoff(measured(spark, d))
    b = m.where("method = 'b1_vector'").select("k", F.col("ndcg").alias("b"))
    return m.join(F.broadcast(b), "k").select("method", "k", F.round((F.col("ndcg") - F.col("b")) * 100, 4).alias("points"))


PAIRS = (("td_cosine", "td_rrf"), ("td_rrf", "td_mmr"), ("hz_cosine", "hz_rrf"), ("hz_cosine", "hz_filtered"), ("bu_parent", "bu_agg"), ("bu_agg", "bu_rrf"))


def variant_deltas(spark, d):
    m = A.overall(measured(spark, d)).select("method", "ndcg")
    p = spark.createDataFrame(PAIRS, "one string, two string")
    j = p.join(m.toDF("one", "a"), "one").join(m.toDF("two", "b"), "two")
    return j.select("one", "two", F.round((F.col("b") - F.col("a")) * 100, 4).alias("points"))


def method_order(spark, d):
    return A.deltas(A.overall(measured(spark, d)))


def kg_stats_e(spark, d):
    g = graph_e(spark, d)
    nodes = g.structural.select("kind").unionByName(g.content.select(F.lit("content").alias("kind"))).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))
    edges = g.struct_edges.select(F.lit("structural edge").alias("kind")).unionByName(g.sem_edges.select(F.lit("semantic edge").alias("kind"))).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))
    return nodes.unionByName(edges)


def kg_stats_s(spark, d):
    parts = [e.agg(F.lit(level).alias("level"), F.countDistinct("child_id").alias("nodes"), F.count(F.lit(1)).alias("edges")) for level, e in graph_s_edges(spark, d).items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("level", "nodes", "edges")


def followed_by(spark, d) -> DataFrame:
    """(src, dst): a part and the next different one of the same order, each pair once."""
    from pyspark.sql import Window

    x = load(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey")
    return x.select(F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst")).where("dst is not null and src <> dst").distinct()


def top_relations_s(spark, d):
    p = load(spark, d, "part").select("p_partkey", "p_brand", "p_type", "p_size")
    q = p.select(F.col("p_partkey").alias("b"), *[F.col(c).alias(c + "2") for c in ("p_brand", "p_type", "p_size")])
    same = p.join(q, (F.col("p_brand") == F.col("p_brand2")) & (F.col("p_type") == F.col("p_type2")) & (F.col("p_size") == F.col("p_size2")) & (F.col("p_partkey") < F.col("b")))
    both = followed_by(spark, d).select(F.lit("followed_by").alias("rel_type")).unionByName(same.select(F.lit("related").alias("rel_type")))
    return both.groupBy("rel_type").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "rel_type").limit(10)


def descend_s(spark, d):
    """Distinct parts below each customer of the star schema: customer, order, line, part."""
    o = load(spark, d, "orders").select("o_orderkey", "o_custkey")
    x = load(spark, d, "lineitem").select("l_orderkey", "l_partkey")
    return x.join(o, x.l_orderkey == o.o_orderkey).groupBy("o_custkey").agg(F.countDistinct("l_partkey").alias("parts"))


def climb_s(spark, d):
    """Orders and customers above each part."""
    o = load(spark, d, "orders").select("o_orderkey", "o_custkey")
    x = load(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    return x.join(o, x.l_orderkey == o.o_orderkey).groupBy("l_partkey").agg(F.count(F.lit(1)).alias("orders"), F.countDistinct("o_custkey").alias("customers"))


def agg_s(spark, d):
    """Child aggregation at scale: each order's score from the discounts of its lines."""
    x = load(spark, d, "lineitem").select(F.lit("q").alias("query_id"), F.col("l_orderkey").alias("parent_id"), F.round(F.col("l_discount").cast("double"), 9).alias("s"))
    return agg_score(x).select("parent_id", F.round("agg_score", 6).alias("agg_score"), "n_children", "n_above")


def passage_lookup(spark, d):
    """(item_id, doc_id, grade): 2 where a document holds the passage word for word, 1 where half its five-word shingles."""
    grams = lambda c: F.transform(F.sequence(F.lit(0), F.size(c) - 5), lambda i: F.array_join(F.slice(c, i + 1, 5), " "))
    b = load(spark, d, "benchmark").select("item_id", F.split("text", r"\s+").alias("w"), F.col("text").alias("passage")).where(F.size("w") >= 5)
    bg = b.select("item_id", F.explode(F.array_distinct(grams("w"))).alias("g")).persist()
    need = bg.groupBy("item_id").agg(F.count(F.lit(1)).alias("need"))
    docs = load(spark, d, "documents").select("doc_id", "text")
    dg = docs.select("doc_id", F.split("text", r"\s+").alias("w")).where(F.size("w") >= 5).select("doc_id", F.explode(F.array_distinct(grams("w"))).alias("g"))
    hit = dg.join(F.broadcast(bg), "g").groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("shared")).join(need, "item_id").where(F.col("shared") * 2 >= F.col("need"))
    hit = hit.join(docs, "doc_id").join(F.broadcast(b.select("item_id", "passage")), "item_id")
    return hit.select("item_id", "doc_id", F.when(F.contains("text", "passage"), 2).otherwise(1).alias("grade"))


def dialogue_bm25(spark, d):
    """Rank of each user turn's own reply among all assistant turns, by lexical search; null beyond the tenth."""
    c = load(spark, d, "conversations").where("text is not null")
    tag = F.concat_ws(":", F.lit("t"), F.col("conv_id").cast("string"), F.col("turn").cast("string"))
    replies = c.where("role = 'assistant'").select(tag.alias("node_id"), words("text").alias("tokens"))
    asks = c.where("role = 'user'").select(F.concat_ws(":", F.lit("q"), F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("query_id"), F.concat_ws(":", F.lit("t"), F.col("conv_id").cast("string"), (F.col("turn") + 1).cast("string")).alias("own"), words("text").alias("tokens"))
    asks = asks.join(replies.select(F.col("node_id").alias("own")), "own", "left_semi")
    top = search.bm25_topk(asks.select("query_id", F.explode(F.array_distinct("tokens")).alias("term")), replies, K)
    return asks.select("query_id", "own").join(top.select("query_id", F.col("node_id").alias("own"), "rank"), ["query_id", "own"], "left").select("query_id", "rank")


def ann_study(spark, d):
    g = graph_e(spark, d)
    q = queries_e(spark, d, g)[0]
    return search.ann_recall(search.vector_topk(q, g.content, K), search.ann_topk(q, g.content, K))


def topk_arrow(spark, d):
    g = graph_e(spark, d)
    return search.vector_topk_blocks(queries_e(spark, d, g)[0], g.content, K)


def queries_table(spark, d):
    """Every component of every query's vector."""
    q = queries_e(spark, d)[0].select("query_id", "direction", F.posexplode("embedding").alias("place", "value"))
    return q.select("query_id", "direction", (F.col("place") + 1).cast("long").alias("place"), F.round("value", 6).alias("value"))


def qrels_table(spark, d):
    return queries_e(spark, d)[1]


def matched_sections(spark, d):
    g = graph_e(spark, d)
    return traverse.match_sections(g, queries_e(spark, d, g)[0])


def parent_scores(spark, d):
    g = graph_e(spark, d)
    p = traverse.parent_scores(g, queries_e(spark, d, g)[0])
    return p.select("query_id", "parent_id", F.round("cos", 6).alias("cos"), F.round("agg_score", 6).alias("agg_score"), "n_children", "n_above")


def _rounded(f):
    return lambda s, d: f(s, d).select("query_id", "node_id", F.round("score", 6).alias("score"), F.col("rank").cast("int").alias("rank"))


QUERIES = {k: _rounded(f) for k, f in METHODS.items()} | {
    "topk_arrow": _rounded(topk_arrow),
    "bu_parents_agg": _rounded(_on_graph(traverse.bottomup, variant="agg", emit="parents")),
    "bu_both": _rounded(_on_graph(traverse.bottomup, variant="agg", emit="both")),
    "hz_allowed": _rounded(_on_graph(traverse.horizontal, variant="filtered", types_by="allowlist", allow=("r1", "r4"))),
    "hz_centroid": _rounded(_on_graph(traverse.horizontal, variant="filtered", types_by="centroid")),
    "queries_e": queries_table,
    "qrels_e": qrels_table,
    "match_sections": matched_sections,
    "parent_scores": parent_scores,
    "measures_b1": measured_one("b1_vector"),
    "measures_td_rrf": measured_one("td_rrf"),
    "measures_bu_rrf": measured_one("bu_rrf"),
    "measures_hz_rrf": measured_one("hz_rrf"),
    "eval_overall": eval_overall,
    "eval_cutoffs": eval_cutoffs,
    "eval_directions": eval_directions,
    "gain_by_k": gain_by_k,
    "variant_deltas": variant_deltas,
    "method_order": method_order,
    "kg_stats_e": kg_stats_e,
    "kg_stats_s": kg_stats_s,
    "top_relations_s": top_relations_s,
    "descend_s": descend_s,
    "climb_s": climb_s,
    "agg_s": agg_s,
    "passage_lookup": passage_lookup,
    "dialogue_bm25": dialogue_bm25,
    "ann_recall": ann_study,
}

# Oracle SQL

_BASE = """
WITH c AS MATERIALIZED (
  SELECT num, 'v:' || num AS node_id, label, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) AS emb
  FROM (SELECT vec_id AS num, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings)),
leaf AS (
  SELECT num, node_id, label AS a, num % 8 AS m FROM c
  UNION ALL SELECT num, node_id, (label + 1) % 10, num % 8 FROM c WHERE num % 5 = 0),
anc AS MATERIALIZED (
  SELECT DISTINCT num, node_id, unnest(['u:' || a || ':' || m, 's:' || a || ':' || (m % 4), 'l:' || a || ':' || (m % 2), 'c:' || a, 'b:' || (a % 3)]) AS anc FROM leaf),
homes AS MATERIALIZED (SELECT num, node_id, anc AS section_id FROM anc WHERE anc LIKE 's:%'),
mean AS MATERIALIZED (
  SELECT anc, list(x ORDER BY i) AS v FROM (
    SELECT anc, i, round(avg(emb[i]), 6) AS x FROM anc JOIN c USING (num), generate_series(1, 64) AS t(i) GROUP BY anc, i) GROUP BY anc),
st AS MATERIALIZED (SELECT anc, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) AS emb FROM mean),
sem AS MATERIALIZED (
  SELECT x.node_id AS src, y.node_id AS dst, x.num AS a, y.num AS b, 'r' || ((x.label + y.label) % 10) AS rel_type, round(list_dot_product(x.emb, y.emb), 9) AS weight
  FROM c x JOIN c y ON x.num < y.num AND (x.label <> y.label OR x.num % 4 <> y.num % 4)
  WHERE round(list_dot_product(x.emb, y.emb), 9) >= 0.30),
ways AS (SELECT src, dst, a, b, rel_type, weight FROM sem UNION ALL SELECT dst, src, b, a, rel_type, weight FROM sem),
near AS MATERIALIZED (SELECT a AS num, b AS mate FROM ways QUALIFY row_number() OVER (PARTITION BY a ORDER BY weight DESC, b) = 1),
qb AS (
  SELECT c.num AS q, c.label, c.emb AS own, ['NT','TD','HZ','BU','CS'][(c.num // 10) % 5 + 1] AS direction, near.mate, mv.emb AS mate_vec,
    's:' || c.label || ':' || (c.num % 4) AS section_id, 's:' || mv.label || ':' || (mv.num % 4) AS mate_section,
    's:' || ((c.label + 5) % 10) || ':' || (c.num % 4) AS other_id, s1.emb AS summary, s2.emb AS other_summary, f.emb AS far_vec
  FROM c LEFT JOIN near ON near.num = c.num LEFT JOIN c mv ON mv.num = near.mate
  JOIN st s1 ON s1.anc = 's:' || c.label || ':' || (c.num % 4)
  LEFT JOIN st s2 ON s2.anc = 's:' || ((c.label + 5) % 10) || ':' || (c.num % 4)
  JOIN c f ON f.num = (c.num * 7 + 3) % (SELECT count(*) FROM c)
  WHERE c.num % 10 = 0),
qv AS (
  SELECT *, CASE WHEN direction IN ('TD', 'BU') THEN summary
    WHEN direction = 'HZ' AND mate IS NOT NULL THEN list_transform(list_zip(own, mate_vec), lambda p: (p[1] + p[2]) * 0.5)
    WHEN direction = 'CS' AND other_summary IS NOT NULL THEN list_transform(list_zip(summary, other_summary), lambda p: (p[1] + p[2]) * 0.5)
    ELSE own END AS v FROM qb),
qs AS (SELECT *, list_transform(list_zip(v, far_vec), lambda p: p[1] + p[2] * 0.5) AS s FROM qv),
qr AS (SELECT *, list_transform(s, lambda x: round(x / sqrt(list_dot_product(s, s)), 6)) AS r FROM qs),
q AS MATERIALIZED (SELECT *, 'q:' || q AS query_id, list_transform(r, lambda x: x / sqrt(list_dot_product(r, r))) AS emb FROM qr),
cs AS MATERIALIZED (SELECT query_id, node_id, c.num, round(list_dot_product(q.emb, c.emb), 9) AS cos FROM q, c),
"""
_TD = """
ms AS MATERIALIZED (SELECT query_id, anc AS section_id, round(list_dot_product(q.emb, st.emb), 9) AS seed_score FROM q, st WHERE anc LIKE 's:%'
  QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(list_dot_product(q.emb, st.emb), 9) DESC, anc) <= 3),
td AS MATERIALIZED (SELECT query_id, node_id, max(seed_score) AS seed_score FROM ms JOIN homes USING (section_id) GROUP BY ALL),
tc AS (SELECT td.*, cos FROM td JOIN cs USING (query_id, node_id)),
"""
_HZ = """
hs AS (SELECT query_id, node_id, cos AS seed_score FROM cs QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cos DESC, node_id) <= 10),
types AS (SELECT rel_type FROM sem GROUP BY rel_type ORDER BY count(*) DESC, rel_type LIMIT {types}),
ext AS (SELECT query_id, dst AS node_id, seed_score FROM hs JOIN ways ON ways.src = hs.node_id
  WHERE rel_type IN (SELECT rel_type FROM types) AND NOT EXISTS (SELECT 1 FROM homes h1 JOIN homes h2 USING (section_id) WHERE h1.node_id = ways.src AND h2.node_id = ways.dst)),
hz AS MATERIALIZED (SELECT query_id, node_id, max(seed_score) AS seed_score FROM (SELECT * FROM ext UNION ALL SELECT * FROM hs) GROUP BY ALL),
hc AS (SELECT hz.*, cos FROM hz JOIN cs USING (query_id, node_id)),
"""
_BU = """
edge AS (SELECT 'u:' || a || ':' || m AS parent_id, node_id FROM leaf),
bn AS (SELECT query_id, node_id FROM cs QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cos DESC, node_id) <= 50),
pa AS (SELECT DISTINCT query_id, parent_id FROM bn JOIN edge USING (node_id)),
kid AS MATERIALIZED (SELECT query_id, parent_id, node_id, cos FROM pa JOIN edge USING (parent_id) JOIN cs USING (query_id, node_id)),
med AS (SELECT query_id, parent_id, round(median(cos), 9) AS tau FROM kid GROUP BY ALL),
pg AS MATERIALIZED (SELECT query_id, parent_id, round(avg(cos) * ln(1 + count(*) FILTER (cos >= tau)), 9) AS agg_score, count(*) AS n_children, count(*) FILTER (cos >= tau) AS n_above
  FROM kid JOIN med USING (query_id, parent_id) GROUP BY ALL),
ps AS MATERIALIZED (SELECT pg.*, round(list_dot_product(q.emb, st.emb), 9) AS cos FROM pg JOIN q USING (query_id) JOIN st ON st.anc = pg.parent_id),
pr AS (SELECT *, round(1.0 / (60 + rank() OVER (PARTITION BY query_id ORDER BY cos DESC)) + 1.0 / (60 + rank() OVER (PARTITION BY query_id ORDER BY agg_score DESC)), 9) AS fused FROM ps),
"""


def _cut(source: str, score: str, k: int = 10, name: str = "node_id") -> str:
    """SQL for a run: the first k by a score rounded to nine places, then id."""
    return f"run AS (SELECT query_id, {name} AS node_id, round({score}, 9) AS score, CAST(row_number() OVER (PARTITION BY query_id ORDER BY round({score}, 9) DESC, {name}) AS INTEGER) AS rank FROM {source} QUALIFY rank <= {k})"


def _fused(source: str, one: str, two: str) -> str:
    r = "(1.0 / (60 + rank() OVER (PARTITION BY query_id ORDER BY {} DESC)))"
    return f"fz AS (SELECT query_id, node_id, {r.format(one)} + {r.format(two)} AS fused FROM {source}), " + _cut("fz", "fused")


def _kids(score: str) -> str:
    return f"""kb AS (SELECT query_id, node_id, max(round({score}, 9)) AS parent_score FROM pr JOIN edge USING (parent_id) GROUP BY ALL),
run AS (SELECT query_id, node_id, parent_score AS score, CAST(row_number() OVER (PARTITION BY query_id ORDER BY parent_score DESC, cos DESC, node_id) AS INTEGER) AS rank FROM kb JOIN cs USING (query_id, node_id) QUALIFY rank <= 10)"""


_OUT = " SELECT query_id, node_id, round(score, 6) AS score, rank FROM run"
_LEX = r"""
tx AS MATERIALIZED (SELECT 'v:' || doc_id AS node_id, doc_id AS num, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda w: w <> '') AS tokens FROM documents WHERE doc_id IN (SELECT vec_id FROM embeddings)),
post AS MATERIALIZED (SELECT term, node_id, count(*) AS tf FROM (SELECT unnest(tokens) AS term, node_id FROM tx) GROUP BY ALL),
dl AS MATERIALIZED (SELECT node_id, len(tokens) AS dl FROM tx),
stat AS (SELECT count(*) AS n, avg(dl) AS avgdl FROM dl),
dfs AS (SELECT term, count(*) AS df FROM post GROUP BY term),
qt AS (SELECT DISTINCT 'q:' || num AS query_id, unnest(tokens) AS term FROM tx WHERE num % 10 = 0),
lex AS MATERIALIZED (SELECT query_id, node_id, sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * dl / avgdl))) AS score
  FROM qt JOIN post USING (term) JOIN dfs USING (term) JOIN dl USING (node_id), stat GROUP BY ALL),
"""
_LABELS = """
sec AS (SELECT query_id, direction, q, mate, unnest(list_distinct(list_filter([section_id, CASE WHEN direction = 'CS' THEN other_id END, CASE WHEN direction = 'HZ' THEN mate_section END], lambda x: x IS NOT NULL))) AS section_id FROM q),
ins AS (SELECT sec.*, node_id, num, row_number() OVER (PARTITION BY query_id, section_id ORDER BY num) AS k FROM sec JOIN homes USING (section_id)),
us AS (SELECT *, CASE WHEN direction = 'NT' THEN num = q WHEN direction = 'HZ' THEN num = q OR coalesce(num = mate, false) ELSE k <= 5 END AS used FROM ins),
gr AS (SELECT *, row_number() OVER (PARTITION BY query_id, section_id, used ORDER BY num) AS j FROM us),
zero AS (SELECT query_id, c.node_id FROM q, c WHERE NOT EXISTS (SELECT 1 FROM ins WHERE ins.query_id = q.query_id AND ins.node_id = c.node_id) QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY c.num) <= 5),
labels AS (SELECT query_id, node_id, CAST(max(grade) AS INTEGER) AS grade FROM (SELECT query_id, node_id, CASE WHEN used THEN 2 ELSE 1 END AS grade FROM gr WHERE used OR j <= 5 UNION ALL SELECT query_id, node_id, 0 FROM zero) GROUP BY ALL),
"""
_MEASURE = """,
ks AS (SELECT unnest([1, 3, 5, 10]) AS k),
idl AS (SELECT query_id, grade, row_number() OVER (PARTITION BY query_id ORDER BY grade DESC, node_id) AS r FROM labels WHERE grade > 0),
idc AS (SELECT query_id, k, sum(CASE WHEN r <= k THEN grade / log2(r + 1) ELSE 0 END) AS idcg, count(*) AS n_rel FROM idl, ks GROUP BY ALL),
hit AS (SELECT query_id, k, rank, coalesce(grade, 0) AS grade FROM run LEFT JOIN labels USING (query_id, node_id), ks WHERE rank <= k),
got AS (SELECT query_id, k, sum(grade / log2(rank + 1)) AS dcg, count(*) FILTER (grade >= 1) AS found, min(rank) FILTER (grade >= 1) AS first FROM hit GROUP BY ALL)
SELECT '{name}' AS method, query_id, direction, CAST(k AS INTEGER) AS k, round(coalesce(dcg / idcg, 0), 6) AS ndcg, round(coalesce(found / n_rel, 0), 6) AS recall,
  round(coalesce(found / k, 0), 6) AS precision, round(coalesce(1.0 / first, 0), 6) AS mrr
FROM idc LEFT JOIN got USING (query_id, k) JOIN q USING (query_id)
"""
_CENTROID = """
ends AS (SELECT rel_type, src AS node_id FROM sem UNION ALL SELECT rel_type, dst FROM sem),
cen AS MATERIALIZED (SELECT rel_type, list(x ORDER BY i) AS v FROM (SELECT rel_type, i, round(avg(emb[i]), 6) AS x FROM ends JOIN c USING (node_id), generate_series(1, 64) AS t(i) GROUP BY rel_type, i) GROUP BY rel_type),
near_type AS MATERIALIZED (SELECT query_id, rel_type FROM (SELECT query_id, rel_type, round(list_dot_product(q.emb, list_transform(cen.v, lambda x: x / sqrt(list_dot_product(cen.v, cen.v)))), 9) AS cos FROM q, cen)
  QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY cos DESC, rel_type) <= 3),
"""
_ALL, _THREE = _HZ.replace("{types}", "1000"), _HZ.replace("{types}", "3")
_NEAREST = _CENTROID + _ALL.replace("rel_type IN (SELECT rel_type FROM types)", "EXISTS (SELECT 1 FROM near_type nt WHERE nt.query_id = hs.query_id AND nt.rel_type = ways.rel_type)")


def _diverse(k: int = 10, pool: int = 50, lam: float = 0.7) -> str:
    """SQL for maximal marginal relevance over the fused candidates: one pick of each query after another."""
    r = "(1.0 / (60 + rank() OVER (PARTITION BY query_id ORDER BY {} DESC)))"
    out = f"""fz AS MATERIALIZED (SELECT query_id, node_id, {r.format("cos")} + {r.format("seed_score")} AS fused FROM tc),
pool AS MATERIALIZED (SELECT query_id, node_id, round(fused, 9) AS score, row_number() OVER (PARTITION BY query_id ORDER BY fused DESC, node_id) AS rank FROM fz QUALIFY rank <= {pool}),
s0 AS MATERIALIZED (SELECT query_id, node_id, rank, score / max(score) OVER (PARTITION BY query_id) AS rel, emb, 0.0::DOUBLE AS worst, false AS taken FROM pool JOIN c USING (node_id)),"""
    for i in range(1, k + 1):
        most = "list_dot_product(s.emb, p.emb)" if i == 1 else "greatest(worst, list_dot_product(s.emb, p.emb))"
        out += f"""
p{i} AS MATERIALIZED (SELECT query_id, node_id, emb, round({lam} * rel - {1 - lam} * worst, 9) AS value FROM s{i - 1} WHERE NOT taken QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY value DESC, rank) = 1),
s{i} AS MATERIALIZED (SELECT s.query_id, s.node_id, rank, rel, s.emb, {most} AS worst, taken OR s.node_id = p.node_id AS taken FROM s{i - 1} s JOIN p{i} p USING (query_id)),"""
    picks = " UNION ALL ".join(f"SELECT query_id, node_id, value AS score, {i} AS rank FROM p{i}" for i in range(1, k + 1))
    return out + f"\nrun AS ({picks})"


_HYBRID = _cut("cs", "cos", 100).replace("run AS", "r1 AS", 1) + ", " + _cut("lex", "score", 100).replace("run AS", "r2 AS", 1) + """,
uni AS (SELECT query_id, node_id, sum(1.0 / (60 + rank)) AS score FROM (SELECT query_id, node_id, rank FROM r1 UNION ALL SELECT query_id, node_id, rank FROM r2) GROUP BY ALL), """ + _cut("uni", "score")
#: What each method needs besides the graph and the queries.
_PARTS = {
    "b1_vector": _cut("cs", "cos"),
    "b2_bm25": _LEX + _cut("lex", "score"),
    "b3_hybrid": _LEX + _HYBRID,
    "td_cosine": _TD + _cut("tc", "cos"),
    "td_rrf": _TD + _fused("tc", "cos", "seed_score"),
    "td_mmr": _TD + _diverse(),
    "hz_cosine": _ALL + _cut("hc", "cos"),
    "hz_rrf": _ALL + _fused("hc", "seed_score", "cos"),
    "hz_filtered": _THREE + _cut("hc", "cos"),
    "bu_parent": _BU + _kids("cos"),
    "bu_agg": _BU + _kids("agg_score"),
    "bu_rrf": _BU + _kids("fused"),
    "bu_parents_agg": _BU + _cut("pr", "agg_score", name="parent_id"),
    "hz_centroid": _NEAREST + _cut("hc", "cos"),
    "hz_allowed": _ALL.replace("rel_type IN (SELECT rel_type FROM types)", "rel_type IN ('r1', 'r4')") + _cut("hc", "cos"),
    "bu_both": _BU + """kb AS (SELECT query_id, node_id, max(agg_score) AS parent_score FROM pr JOIN edge USING (parent_id) GROUP BY ALL),
bo AS (SELECT query_id, node_id, parent_score, cos FROM kb JOIN cs USING (query_id, node_id) UNION ALL SELECT query_id, parent_id, agg_score, 2.0 FROM pr),
run AS (SELECT query_id, node_id, parent_score AS score, CAST(row_number() OVER (PARTITION BY query_id ORDER BY parent_score DESC, cos DESC, node_id) AS INTEGER) AS rank FROM bo QUALIFY rank <= 10)""",
}
_RUN = {k: _BASE + v for k, v in _PARTS.items()}
#: The runs of all methods: each in a query of its own inside, over the graph and the queries outside.
_RUNS = "runs AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT '{k}' AS method, query_id, node_id, rank FROM (WITH {_PARTS[k]} SELECT query_id, node_id, rank FROM run)" for k in METHODS) + "),"
_PER_QUERY = _BASE + _LABELS + _RUNS + """
ks AS (SELECT unnest([1, 3, 5, 10]) AS k),
idl AS (SELECT query_id, grade, row_number() OVER (PARTITION BY query_id ORDER BY grade DESC, node_id) AS r FROM labels WHERE grade > 0),
idc AS (SELECT query_id, k, sum(CASE WHEN r <= k THEN grade / log2(r + 1) ELSE 0 END) AS idcg, count(*) AS n_rel FROM idl, ks GROUP BY ALL),
hit AS (SELECT method, query_id, k, rank, coalesce(grade, 0) AS grade FROM runs LEFT JOIN labels USING (query_id, node_id), ks WHERE rank <= k),
got AS (SELECT method, query_id, k, sum(grade / log2(rank + 1)) AS dcg, count(*) FILTER (grade >= 1) AS found, min(rank) FILTER (grade >= 1) AS first FROM hit GROUP BY ALL),
pq AS MATERIALIZED (SELECT method, query_id, direction, CAST(k AS INTEGER) AS k, coalesce(dcg / idcg, 0) AS ndcg, coalesce(found / n_rel, 0) AS recall, coalesce(found / k, 0) AS precision, coalesce(1.0 / first, 0) AS mrr
  FROM (SELECT * FROM (SELECT DISTINCT method FROM runs), idc) LEFT JOIN got USING (method, query_id, k) JOIN q USING (query_id)),
by_k AS MATERIALIZED (SELECT method, k, round(avg(ndcg), 6) AS ndcg, round(avg(recall), 6) AS recall, round(avg(precision), 6) AS precision, round(avg(mrr), 6) AS mrr, count(*) AS n_queries FROM pq GROUP BY method, k)
"""
_EVAL = {
    "eval_overall": "SELECT method, ndcg, recall, precision, mrr, n_queries FROM by_k WHERE k = 10",
    "eval_cutoffs": "SELECT * FROM by_k",
    "eval_directions": "SELECT method, " + ", ".join(f"round(avg(ndcg) FILTER (direction = '{x}'), 6) AS {x}" for x in ("TD", "HZ", "BU", "NT", "CS")) + " FROM pq WHERE k = 10 GROUP BY method",
    "gain_by_k": "SELECT a.method, a.k, round((a.ndcg - b.ndcg) * 100, 4) AS points FROM by_k a JOIN by_k b ON a.k = b.k AND b.method = 'b1_vector'",
    "variant_deltas": "SELECT one, two, round((b.ndcg - a.ndcg) * 100, 4) AS points FROM (VALUES " + ", ".join(f"('{x}', '{y}')" for x, y in PAIRS) + ") AS v(one, two) JOIN by_k a ON a.method = one AND a.k = 10 JOIN by_k b ON b.method = two AND b.k = 10",
    "method_order": "SELECT a.method, a.ndcg, CAST(row_number() OVER (ORDER BY a.ndcg DESC, a.method) AS INTEGER) AS place, round((a.ndcg - b.ndcg) * 100, 4) AS points FROM by_k a, by_k b WHERE a.k = 10 AND b.k = 10 AND b.method = 'b1_vector'",
}
_DIALOGUE = r"""
WITH conv AS (SELECT conv_id, turn, role, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda w: w <> '') AS tokens FROM conversations WHERE text IS NOT NULL),
rep AS MATERIALIZED (SELECT 't:' || conv_id || ':' || turn AS node_id, tokens FROM conv WHERE role = 'assistant'),
ask AS MATERIALIZED (SELECT 'q:' || conv_id || ':' || turn AS query_id, 't:' || conv_id || ':' || (turn + 1) AS own, tokens FROM conv WHERE role = 'user' AND 't:' || conv_id || ':' || (turn + 1) IN (SELECT node_id FROM rep)),
post AS MATERIALIZED (SELECT term, node_id, count(*) AS tf FROM (SELECT unnest(tokens) AS term, node_id FROM rep) GROUP BY ALL),
stat AS (SELECT count(*) AS n, avg(len(tokens)) AS avgdl FROM rep), dfs AS (SELECT term, count(*) AS df FROM post GROUP BY term),
qt AS (SELECT DISTINCT query_id, unnest(tokens) AS term FROM ask),
lex AS (SELECT query_id, node_id, sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (1 - 0.75 + 0.75 * len(tokens) / avgdl))) AS score FROM qt JOIN post USING (term) JOIN dfs USING (term) JOIN rep USING (node_id), stat GROUP BY ALL),
top AS (SELECT query_id, node_id, row_number() OVER (PARTITION BY query_id ORDER BY round(score, 9) DESC, node_id) AS rank FROM lex QUALIFY rank <= 10)
SELECT ask.query_id, CAST(rank AS INTEGER) AS rank FROM ask LEFT JOIN top ON top.query_id = ask.query_id AND top.node_id = own"""
ORACLES = {k: v + _OUT for k, v in _RUN.items()} | {k: _PER_QUERY + v for k, v in _EVAL.items()} | {
    "topk_arrow": _RUN["b1_vector"] + _OUT,
    "queries_e": _BASE.rstrip().rstrip(",") + " SELECT query_id, direction, i AS place, round(emb[i], 6) AS value FROM q, generate_series(1, 64) AS t(i)",
    "dialogue_bm25": _DIALOGUE,
    "qrels_e": _BASE + _LABELS.rstrip().rstrip(",") + " SELECT query_id, node_id, grade FROM labels",
    "match_sections": _BASE + _TD.rstrip().rstrip(",") + " SELECT query_id, section_id, seed_score FROM ms",
    "parent_scores": _BASE + _BU.rstrip().rstrip(",") + " SELECT query_id, parent_id, round(cos, 6) AS cos, round(agg_score, 6) AS agg_score, n_children, n_above FROM ps",
    **{f"measures_{short}": _RUN[name].replace(_BASE, _BASE + _LABELS, 1) + _MEASURE.replace("{name}", name) for short, name in (("b1", "b1_vector"), ("td_rrf", "td_rrf"), ("bu_rrf", "bu_rrf"), ("hz_rrf", "hz_rrf"))},
    "kg_stats_e": _BASE.rstrip().rstrip(",") + f""" SELECT kind, count(*) AS n FROM (
      SELECT DISTINCT anc, CASE substr(anc, 1, 1) {' '.join(f"WHEN '{a}' THEN '{b}'" for a, b in zip("bclsu", KINDS))} END AS kind FROM anc) GROUP BY kind
      UNION ALL SELECT 'content', count(*) FROM c UNION ALL SELECT 'semantic edge', count(*) FROM sem
      UNION ALL SELECT 'structural edge', (SELECT count(*) FROM leaf) + count(DISTINCT (k, p)) FROM (
        SELECT unnest(['u:' || a || ':' || m, 's:' || a || ':' || (m % 4), 'l:' || a || ':' || (m % 2), 'c:' || a]) AS k,
               unnest(['s:' || a || ':' || (m % 4), 'l:' || a || ':' || (m % 2), 'c:' || a, 'b:' || (a % 3)]) AS p FROM leaf)""",
    "kg_stats_s": """
      SELECT 'chapter' AS level, count(DISTINCT n_nationkey) AS nodes, count(*) AS edges FROM nation UNION ALL
      SELECT 'lesson', count(DISTINCT c_custkey), count(*) FROM customer UNION ALL SELECT 'section', count(DISTINCT o_orderkey), count(*) FROM orders UNION ALL
      SELECT 'subsection', count(*), count(*) FROM (SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem) UNION ALL
      SELECT 'content', count(DISTINCT l_partkey), count(*) FROM (SELECT DISTINCT l_orderkey, l_linenumber, l_partkey FROM lineitem)""",
    "top_relations_s": """
      WITH f AS (SELECT DISTINCT src, dst FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey) AS dst FROM lineitem) WHERE dst IS NOT NULL AND src <> dst)
      SELECT rel_type, n FROM (SELECT 'followed_by' AS rel_type, count(*) AS n FROM f UNION ALL
      SELECT 'related', count(*) FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_size = b.p_size AND a.p_partkey < b.p_partkey) WHERE n > 0""",
    "descend_s": "SELECT o_custkey, count(DISTINCT l_partkey) AS parts FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey",
    "climb_s": "SELECT l_partkey, count(*) AS orders, count(DISTINCT o_custkey) AS customers FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) JOIN orders ON l_orderkey = o_orderkey GROUP BY l_partkey",
    "agg_s": """
      WITH x AS (SELECT l_orderkey AS parent_id, round(CAST(l_discount AS DOUBLE), 9) AS s FROM lineitem), m AS (SELECT parent_id, round(median(s), 9) AS tau FROM x GROUP BY parent_id)
      SELECT parent_id, round(round(avg(s) * ln(1 + count(*) FILTER (s >= tau)), 9), 6) AS agg_score, count(*) AS n_children, count(*) FILTER (s >= tau) AS n_above FROM x JOIN m USING (parent_id) GROUP BY parent_id""",
    "passage_lookup": r"""
      WITH b AS (SELECT item_id, text AS passage, regexp_split_to_array(text, '\s+') AS w FROM benchmark), d AS (SELECT doc_id, text, regexp_split_to_array(text, '\s+') AS w FROM documents),
      bg AS (SELECT DISTINCT item_id, array_to_string(w[i:i+4], ' ') AS g FROM b, generate_series(1, 30000) AS t(i) WHERE i <= len(w) - 4),
      dg AS (SELECT DISTINCT doc_id, g FROM (SELECT doc_id, unnest(list_transform(generate_series(1, len(w) - 4), lambda i: array_to_string(w[i:i+4], ' '))) AS g FROM d WHERE len(w) >= 5)),
      need AS (SELECT item_id, count(*) AS need FROM bg GROUP BY item_id)
      SELECT item_id, doc_id, CASE WHEN contains(text, passage) THEN 2 ELSE 1 END AS grade FROM (SELECT item_id, doc_id, count(*) AS shared FROM bg JOIN dg USING (g) GROUP BY ALL)
      JOIN need USING (item_id) JOIN d USING (doc_id) JOIN b USING (item_id) WHERE shared * 2 >= need""",
}
