"""Benchmark generation from a graph's own subgraphs: seed, enrich, bound, quality checks, spot checks, statistics."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..plans.strategy import small
from ..sources.graphs import GRAPH_TABLES, Graph, graph_e
from ..sources.stored import stored
from ..sources.tables import load, parse_answers
from .traverse import both_ways

#: Review rates by confidence.
SPOT = {"high": 0.10, "medium": 0.50, "low": 1.00}


def seed_subgraphs(g: Graph, kind: str = "section") -> DataFrame:
    """(subgraph_id, node_id, role): the content below each structural node of the kind that has any."""
    s = g.structural.where(F.col("kind") == kind).select(F.col("node_id").alias("subgraph_id"))
    return g.closure.where("node_id like 'v:%'").join(small(s), F.col("anc_id") == F.col("subgraph_id")).select("subgraph_id", "node_id", F.lit("core").alias("role"))


def enrich(core: DataFrame, g: Graph, max_sections: int = 2) -> DataFrame:
    """core and the content of the at most two other sections with most relations to it, with their sections (role parent)."""
    step = core.join(both_ways(g.sem_edges).withColumnRenamed("src", "node_id"), "node_id").select("subgraph_id", F.col("dst").alias("node_id"))
    step = step.join(g.homes, "node_id").where("section_id <> subgraph_id")
    step = step.join(core.select("subgraph_id", "node_id"), ["subgraph_id", "node_id"], "left_anti")
    w = Window.partitionBy("subgraph_id").orderBy(F.desc("n"), "section_id")
    best = step.groupBy("subgraph_id", "section_id").agg(F.count(F.lit(1)).alias("n")).withColumn("k", F.row_number().over(w)).where(F.col("k") <= max_sections)
    more = best.join(g.homes, "section_id").select("subgraph_id", "node_id", F.lit("enriched").alias("role")).distinct()
    more = more.join(core.select("subgraph_id", "node_id"), ["subgraph_id", "node_id"], "left_anti")
    return core.unionByName(more).unionByName(best.select("subgraph_id", F.col("section_id").alias("node_id"), F.lit("parent").alias("role")))


def bound(nodes: DataFrame, g: Graph) -> DataFrame:
    """(subgraph_id, src, dst, rel_type): semantic edges with both ends inside."""
    n = nodes.where("role <> 'parent'").select("subgraph_id", "node_id").distinct()
    e = g.sem_edges.select("src", "dst", "rel_type").join(n.withColumnRenamed("node_id", "src"), "src")
    return e.join(n.withColumnRenamed("node_id", "dst"), ["subgraph_id", "dst"]).select("subgraph_id", "src", "dst", "rel_type")


#: Nodes of a section that a query is made of at most; cosines to them from which confidence is high or medium.
USED, HIGH, MEDIUM = 5, 0.6, 0.45


def ranked_sections(core: DataFrame, g: Graph, max_sections: int = 2) -> DataFrame:
    """(subgraph_id, section_id, k): the other sections with most relations to a subgraph's core, in order."""
    step = core.join(both_ways(g.sem_edges).withColumnRenamed("src", "node_id"), "node_id").select("subgraph_id", F.col("dst").alias("node_id"))
    step = step.join(g.homes, "node_id").where("section_id <> subgraph_id")
    step = step.join(core.select("subgraph_id", "node_id"), ["subgraph_id", "node_id"], "left_anti")
    w = Window.partitionBy("subgraph_id").orderBy(F.desc("n"), "section_id")
    return step.groupBy("subgraph_id", "section_id").agg(F.count(F.lit(1)).alias("n")).withColumn("k", F.row_number().over(w)).where(F.col("k") <= max_sections).select("subgraph_id", "section_id", "k")


def material(g: Graph) -> DataFrame:
    """(subgraph_id, direction, node_id, embedding): the nodes that each query of a subgraph is made of.

    NT the first core node; TD and BU the first USED of the core; HZ the ends of the strongest edge from the core to its
    enriched content; CS the first USED of the core and of the section with most relations to it. Without such an edge or
    section there is no such query.
    """
    core = seed_subgraphs(g).select("subgraph_id", "node_id").join(g.content.select("node_id", "num"), "node_id")
    core = core.withColumn("k", F.row_number().over(Window.partitionBy("subgraph_id").orderBy("num")))
    nodes = enrich(seed_subgraphs(g), g)
    inside = bound(nodes, g).join(g.sem_edges.select("src", "dst", "weight"), ["src", "dst"])
    role = nodes.where("role <> 'parent'").select("subgraph_id", "node_id", "role").distinct()
    ends = inside.join(role.toDF("subgraph_id", "src", "rs"), ["subgraph_id", "src"]).join(role.toDF("subgraph_id", "dst", "rd"), ["subgraph_id", "dst"]).where("rs <> rd")
    best = ends.groupBy("subgraph_id").agg(F.min(F.struct((-F.col("weight")).alias("w"), "src", "dst")).alias("e"))
    other = ranked_sections(seed_subgraphs(g), g, 1).select("subgraph_id", F.col("section_id").alias("other"))
    first = core.where(F.col("k") <= USED)
    tag = lambda df, d: df.select("subgraph_id", F.lit(d).alias("direction"), "node_id")
    mates = other.join(first.select(F.col("subgraph_id").alias("other"), "node_id"), "other").select("subgraph_id", "node_id")
    both = first.join(other, "subgraph_id", "left_semi").select("subgraph_id", "node_id").unionByName(mates).distinct()
    made = [tag(core.where("k = 1"), "NT"), tag(first, "TD"), tag(first, "BU"), tag(best.select("subgraph_id", F.explode(F.array("e.src", "e.dst")).alias("node_id")), "HZ"), tag(both, "CS")]
    return reduce(DataFrame.unionByName, made).join(g.content.select("node_id", "embedding"), "node_id")


def generate(g: Graph) -> tuple[DataFrame, DataFrame]:
    """(queries, labels) written from the subgraphs: (query_id, direction, subgraph_id, embedding), (query_id, node_id, grade).

    A query's vector is the normalised mean of what it is made of; BU has its section's summary, CS the mean of both
    sections' summaries. Grades are inside the subgraph: 2 for what the query is made of, 1 for the rest of the core (of CS
    also of the other section), 0 for what enriches it beside that.
    """
    used = material(g)
    query_id = F.concat_ws(":", F.lit("g"), "direction", "subgraph_id")
    mean = V.centroid(used, ["subgraph_id", "direction"])
    summary = g.structural.where("kind = 'section'").select(F.col("node_id").alias("subgraph_id"), F.col("embedding").alias("own"))
    other = ranked_sections(seed_subgraphs(g), g, 1).select("subgraph_id", F.col("section_id").alias("other"))
    far = summary.select(F.col("subgraph_id").alias("other"), F.col("own").alias("theirs"))
    q = mean.join(summary, "subgraph_id").join(other, "subgraph_id", "left").join(far, "other", "left")
    both = V.l2_normalise(V.rounded(V.scale(V.add("own", "theirs"), 0.5)))
    vector = F.when(F.col("direction") == "BU", F.col("own")).when(F.col("direction") == "CS", both).otherwise(F.col("embedding"))
    queries = q.select(query_id.alias("query_id"), "direction", "subgraph_id", "other", vector.alias("embedding"))
    two = used.select(query_id.alias("query_id"), "node_id", F.lit(2).alias("grade"))
    nodes = enrich(seed_subgraphs(g), g).where("role <> 'parent'").select("subgraph_id", "node_id", "role").distinct()
    at = g.homes.select("node_id", F.col("section_id").alias("other"), F.lit(1).alias("theirs"))
    near = queries.select("query_id", "direction", "subgraph_id", "other").join(nodes, "subgraph_id").join(at, ["node_id", "other"], "left")
    one = near.select("query_id", "node_id", F.when((F.col("role") == "core") | ((F.col("direction") == "CS") & F.col("theirs").isNotNull()), 1).otherwise(0).alias("grade"))
    labels = two.unionByName(one).groupBy("query_id", "node_id").agg(F.max("grade").cast("int").alias("grade"))
    return queries.select("query_id", "direction", "subgraph_id", "embedding"), labels


def records(queries: DataFrame, labels: DataFrame, nodes: DataFrame) -> DataFrame:
    """(query_id, payload, confidence): what a writer would send, as JSON: the query, its nodes and grades, direction, confidence.

    Confidence is the mean cosine of the query to its grade-2 nodes: high, medium or low by HIGH and MEDIUM.
    """
    v = labels.join(nodes.select("node_id", "embedding"), "node_id").join(small(queries.select("query_id", F.col("embedding").alias("qv"))), "query_id")
    v = v.withColumn("c", V.cosine("qv", "embedding"))
    list_ = F.array_sort(F.collect_list(F.struct("node_id", "grade")))
    r = v.groupBy("query_id").agg(list_.alias("relevant"), F.avg(F.when(F.col("grade") == 2, F.col("c"))).alias("sure")).join(queries.select("query_id", "direction"), "query_id")
    level = F.when(F.col("sure") >= HIGH, "high").when(F.col("sure") >= MEDIUM, "medium").otherwise("low")
    return r.select("query_id", F.to_json(F.struct(F.col("query_id").alias("query"), "relevant", "direction", F.round("sure", 6).alias("confidence"))).alias("payload"), level.alias("confidence"))


def qa(queries: DataFrame, qrels: DataFrame, nodes: DataFrame, homes: DataFrame, *, tau: float = 0.3, quota: int = 5, payloads: DataFrame | None = None) -> DataFrame:
    """(query_id, direction, flags): which of the seven checks each generated query fails.

    bad_json (payloads(query_id, payload) given: it doesn't parse), missing_node, off_topic (no graded node at tau),
    no_relevant, wrong_direction (one node for NT, more than one section for HZ and CS), over_quota (more than quota of a
    direction, by id), duplicate (the same vector as an earlier one). The quota keeps quota rows a task before they move.
    """
    rel = qrels.where("grade > 0").join(nodes.select("node_id", "embedding"), "node_id", "left").join(small(queries.select("query_id", F.col("embedding").alias("qv"))), "query_id")
    used = qrels.where("grade = 2").join(homes, "node_id", "left").groupBy("query_id").agg(F.countDistinct("node_id").alias("n2"), F.countDistinct("section_id").alias("sections"))
    facts = rel.groupBy("query_id").agg(F.count_if(F.col("embedding").isNull()).alias("gone"), F.max(V.cosine("qv", "embedding")).alias("best"))
    order = "num" if "num" in queries.columns else "query_id"
    w = Window.partitionBy("direction").orderBy(order)
    within = queries.select("query_id", "direction", order).distinct().withColumn("k", F.row_number().over(w)).where(F.col("k") <= quota).select("query_id", F.lit(True).alias("within"))
    name = F.md5(F.array_join(F.transform("embedding", lambda x: F.round(x, 6).cast("string")), ","))
    same = Window.partitionBy("name").orderBy(order)
    q = queries.withColumn("name", name).select("query_id", "direction", F.row_number().over(same).alias("copy")).join(within, "query_id", "left").join(facts, "query_id", "left").join(used, "query_id", "left")
    broken = F.lit(False)
    if payloads is not None:
        parsed = parse_answers(payloads.select("query_id", "payload")).select("query_id", (F.col("answer").isNull() | F.col("answer._corrupt_record").isNotNull()).alias("broken"))
        q, broken = q.join(parsed, "query_id", "left"), F.coalesce("broken", F.lit(True))
    d = F.col("direction")
    wrong = ((d == "NT") & (F.col("n2") != 1)) | (d.isin("HZ", "CS") & (F.col("sections") < 2))
    flag = lambda c, name: F.when(F.coalesce(c, F.lit(False)), F.lit(name))
    flags = F.array_compact(F.array(flag(broken, "bad_json"), flag(F.col("gone") > 0, "missing_node"), flag(F.col("best") < tau, "off_topic"), flag(F.col("best").isNull(), "no_relevant"), flag(wrong, "wrong_direction"), flag(F.col("within").isNull(), "over_quota"), flag(F.col("copy") > 1, "duplicate")))
    return q.select("query_id", "direction", F.array_join(flags, ",").alias("flags"))


def spot_check(items: DataFrame, key: str = "doc_id", level: str = "confidence", seed: int = 7) -> DataFrame:
    """The reviewed subset: a hash of the key against the rate of its level, the same under any partitioning."""
    rate = F.element_at(F.create_map(*[x for k, v in SPOT.items() for x in (F.lit(k), F.lit(int(v * 100)))]), F.col(level))
    return items.where(F.pmod(F.col(key) * 7919 + seed, F.lit(100)) < rate)


def confidence(spark, d) -> DataFrame:
    l = load(spark, d, "labels")
    return l.select("doc_id", F.when((F.col("quality") == 1) & (F.col("toxic") == 0), "high").when(F.col("quality") == 0, "low").otherwise("medium").alias("confidence"))


def _seed(s, d):
    return seed_subgraphs(graph_e(s, d))


def _enrich(s, d):
    return enrich(_seed(s, d), graph_e(s, d))


def generated(s, d) -> tuple[DataFrame, DataFrame]:
    """Queries and labels written from the vector graph's subgraphs, stored."""
    g = graph_e(s, d)
    made: list[DataFrame] = []

    def part(i: int):
        if not made:
            made.extend(generate(g))
        return made[i]

    return stored(s, d, "generated_queries", GRAPH_TABLES, lambda: part(0)), stored(s, d, "generated_labels", GRAPH_TABLES, lambda: part(1))


def _records(s, d):
    q, labels = generated(s, d)
    return records(q, labels, graph_e(s, d).content)


def _qa(s, d, quota: int = 30):
    g = graph_e(s, d)
    q, labels = generated(s, d)
    return qa(q, labels, g.content, g.homes, quota=quota, payloads=_records(s, d))


def _stats(s, d):
    q, labels = generated(s, d)
    n = labels.join(small(q.select("query_id", "direction")), "query_id").groupBy("direction", "grade").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("share", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 6))  # five directions by three grades


def _flagged(s, d):
    """Clean and flagged queries of each direction."""
    return _qa(s, d).groupBy("direction").agg(F.count_if(F.col("flags") == "").alias("clean"), F.count_if(F.col("flags") != "").alias("flagged"))


def _reviewed(s, d):
    """The generated queries that are reviewed, by confidence."""
    r = _records(s, d).select("query_id", "confidence", F.substring("query_id", 3, 2).alias("direction"))
    key = F.conv(F.substring(F.md5("query_id"), 1, 7), 16, 10).cast("long")
    return spot_check(r.withColumn("key", key), key="key").select("query_id", "confidence")


QUERIES = {
    "bench_seed": _seed,
    "bench_enrich": _enrich,
    "bench_bound": lambda s, d: bound(_enrich(s, d), graph_e(s, d)),
    "bench_queries": lambda s, d: generated(s, d)[0].select("query_id", "direction", "subgraph_id", F.posexplode("embedding").alias("place", "value")).select("query_id", "direction", "subgraph_id", F.col("place").cast("long").alias("place"), F.round("value", 5).alias("value")),
    "bench_labels": lambda s, d: generated(s, d)[1],
    "bench_qa": _qa,
    "bench_flagged": _flagged,
    "bench_stats": _stats,
    "bench_reviewed": _reviewed,
    "bench_spotcheck": lambda s, d: spot_check(confidence(s, d)),
}


def oracles(base: str, labels: str) -> dict[str, str]:
    end = lambda x: x.rstrip().rstrip(",")
    core = base + "core AS (SELECT DISTINCT section_id AS subgraph_id, node_id FROM homes), "
    rich = core + """
      step AS (SELECT core.subgraph_id, ways.dst AS node_id FROM core JOIN ways ON ways.src = core.node_id),
      far AS (SELECT step.subgraph_id, step.node_id, h.section_id FROM step JOIN homes h USING (node_id) WHERE h.section_id <> step.subgraph_id
        AND NOT EXISTS (SELECT 1 FROM core c2 WHERE c2.subgraph_id = step.subgraph_id AND c2.node_id = step.node_id)),
      best AS (SELECT subgraph_id, section_id FROM far GROUP BY subgraph_id, section_id QUALIFY row_number() OVER (PARTITION BY subgraph_id ORDER BY count(*) DESC, section_id) <= 2),
      more AS (SELECT DISTINCT subgraph_id, node_id FROM best JOIN homes USING (section_id) EXCEPT SELECT subgraph_id, node_id FROM core),
      nodes AS (SELECT subgraph_id, node_id, 'core' AS role FROM core UNION ALL SELECT subgraph_id, node_id, 'enriched' FROM more UNION ALL SELECT subgraph_id, section_id, 'parent' FROM best)"""
    made = rich.replace("best AS (SELECT subgraph_id, section_id FROM far", "best AS MATERIALIZED (SELECT subgraph_id, section_id, row_number() OVER (PARTITION BY subgraph_id ORDER BY count(*) DESC, section_id) AS k FROM far") + """,
      num AS (SELECT subgraph_id, core.node_id, num, row_number() OVER (PARTITION BY subgraph_id ORDER BY num) AS k FROM core JOIN c USING (node_id)),
      inb AS (SELECT a.subgraph_id, src, dst, weight FROM sem JOIN nodes a ON a.node_id = src AND a.role <> 'parent' JOIN nodes b ON b.node_id = dst AND b.role <> 'parent' AND b.subgraph_id = a.subgraph_id WHERE a.role <> b.role),
      edge1 AS (SELECT subgraph_id, src, dst FROM inb QUALIFY row_number() OVER (PARTITION BY subgraph_id ORDER BY weight DESC, src, dst) = 1),
      oth AS (SELECT subgraph_id, section_id AS other FROM best WHERE k = 1), first5 AS (SELECT subgraph_id, node_id FROM num WHERE k <= 5),
      used AS MATERIALIZED (SELECT subgraph_id, 'NT' AS direction, node_id FROM num WHERE k = 1 UNION ALL SELECT subgraph_id, 'TD', node_id FROM first5 UNION ALL SELECT subgraph_id, 'BU', node_id FROM first5
        UNION ALL SELECT subgraph_id, 'HZ', unnest([src, dst]) FROM edge1
        UNION ALL SELECT subgraph_id, 'CS', node_id FROM (SELECT subgraph_id, node_id FROM first5 JOIN oth USING (subgraph_id) UNION SELECT oth.subgraph_id, f.node_id FROM oth JOIN first5 f ON f.subgraph_id = other)),
      gm AS (SELECT subgraph_id, direction, list(x ORDER BY i) AS v FROM (SELECT subgraph_id, direction, i, round(avg(emb[i]), 6) AS x FROM used JOIN c USING (node_id), generate_series(1, 64) AS t(i) GROUP BY ALL) GROUP BY subgraph_id, direction),
      cs2 AS (SELECT oth.subgraph_id, list_transform(list_zip(a.emb, b.emb), lambda p: round((p[1] + p[2]) * 0.5, 6)) AS w FROM oth JOIN st a ON a.anc = oth.subgraph_id JOIN st b ON b.anc = other),
      gq AS MATERIALIZED (SELECT 'g:' || direction || ':' || gm.subgraph_id AS query_id, direction, gm.subgraph_id, other, CASE direction WHEN 'BU' THEN st.emb WHEN 'CS' THEN list_transform(w, lambda x: x / sqrt(list_dot_product(w, w))) ELSE list_transform(gm.v, lambda x: x / sqrt(list_dot_product(gm.v, gm.v))) END AS emb
        FROM gm JOIN st ON st.anc = gm.subgraph_id LEFT JOIN oth USING (subgraph_id) LEFT JOIN cs2 USING (subgraph_id)),
      gl AS MATERIALIZED (SELECT query_id, node_id, CAST(max(grade) AS INTEGER) AS grade FROM (
        SELECT 'g:' || direction || ':' || subgraph_id AS query_id, node_id, 2 AS grade FROM used
        UNION ALL SELECT query_id, n.node_id, CASE WHEN role = 'core' OR direction = 'CS' AND EXISTS (SELECT 1 FROM homes h WHERE h.node_id = n.node_id AND h.section_id = other) THEN 1 ELSE 0 END FROM gq JOIN (SELECT DISTINCT * FROM nodes WHERE role <> 'parent') n USING (subgraph_id)) GROUP BY query_id, node_id),
      gc AS MATERIALIZED (SELECT query_id, grade, round(list_dot_product(gq.emb, c.emb), 9) AS cos FROM gl JOIN gq USING (query_id) JOIN c USING (node_id)),
      sure AS MATERIALIZED (SELECT query_id, avg(cos) FILTER (grade = 2) AS sure, max(cos) FILTER (grade > 0) AS best FROM gc GROUP BY query_id),
      lev AS MATERIALIZED (SELECT query_id, CASE WHEN sure >= 0.6 THEN 'high' WHEN sure >= 0.45 THEN 'medium' ELSE 'low' END AS confidence FROM sure),
      n2 AS (SELECT query_id, count(DISTINCT node_id) AS n2, count(DISTINCT section_id) AS sections FROM gl JOIN homes USING (node_id) WHERE grade = 2 GROUP BY query_id),
      fl AS MATERIALIZED (SELECT query_id, direction, array_to_string(list_filter([CASE WHEN best < 0.3 THEN 'off_topic' END, CASE WHEN best IS NULL THEN 'no_relevant' END,
          CASE WHEN direction = 'NT' AND n2 <> 1 OR direction IN ('HZ', 'CS') AND sections < 2 THEN 'wrong_direction' END,
          CASE WHEN row_number() OVER (PARTITION BY direction ORDER BY query_id) > 30 THEN 'over_quota' END,
          CASE WHEN row_number() OVER (PARTITION BY list_transform(emb, lambda x: round(x, 6)) ORDER BY query_id) > 1 THEN 'duplicate' END], lambda x: x IS NOT NULL), ',') AS flags FROM gq LEFT JOIN sure USING (query_id) LEFT JOIN n2 USING (query_id))"""
    return {
        "bench_seed": end(core) + " SELECT subgraph_id, node_id, 'core' AS role FROM core",
        "bench_enrich": rich + " SELECT * FROM nodes",
        "bench_bound": rich + " SELECT a.subgraph_id, src, dst, rel_type FROM sem JOIN nodes a ON a.node_id = src AND a.role <> 'parent' JOIN nodes b ON b.node_id = dst AND b.role <> 'parent' AND b.subgraph_id = a.subgraph_id",
        "bench_queries": made + " SELECT query_id, direction, subgraph_id, i - 1 AS place, round(emb[i], 5) AS value FROM gq, generate_series(1, 64) AS t(i)",
        "bench_labels": made + " SELECT * FROM gl",
        "bench_qa": made + " SELECT * FROM fl",
        "bench_flagged": made + " SELECT direction, count(*) FILTER (flags = '') AS clean, count(*) FILTER (flags <> '') AS flagged FROM fl GROUP BY direction",
        "bench_stats": made + " SELECT direction, grade, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM gl JOIN gq USING (query_id) GROUP BY direction, grade",
        "bench_reviewed": made + " SELECT query_id, confidence FROM (SELECT *, CAST('0x' || substr(md5(query_id), 1, 7) AS BIGINT) AS key FROM lev) WHERE (key * 7919 + 7) % 100 < CASE confidence WHEN 'high' THEN 10 WHEN 'medium' THEN 50 ELSE 100 END",
        "bench_spotcheck": """WITH x AS (SELECT doc_id, CASE WHEN quality = 1 AND toxic = 0 THEN 'high' WHEN quality = 0 THEN 'low' ELSE 'medium' END AS confidence FROM labels)
          SELECT doc_id, confidence FROM x WHERE (doc_id * 7919 + 7) % 100 < CASE confidence WHEN 'high' THEN 10 WHEN 'medium' THEN 50 ELSE 100 END""",
    }
