"""Graphs over the given tables: two tiers, structural nodes that are never merged over content nodes that may be."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from .stored import stored
from .tables import load

#: Levels of structural nodes below the root; content hangs below the last.
KINDS = ("book", "chapter", "lesson", "section", "subsection")
#: Cosine from which two content nodes of different sections are joined by a semantic edge.
EDGE_COSINE = 0.30


@dataclass
class Graph:
    content: DataFrame  # node_id, num, label, embedding
    struct_edges: DataFrame  # parent_id, child_id
    closure: DataFrame  # anc_id, node_id, depth
    homes: DataFrame  # node_id, section_id
    structural: DataFrame  # node_id, kind, embedding
    sem_edges: DataFrame  # src, dst, rel_type, weight, cross (whether no section holds both ends)


#: Vectors in a block of the exact product behind semantic edges.
EDGE_BLOCK = 4_096


def closure_of(edges: DataFrame, levels: int = 5) -> DataFrame:
    """(anc_id, node_id, depth) of all ancestors, each pair at its least depth; one join a level, at most the tree's height."""
    walk = edges.select(F.col("parent_id").alias("anc_id"), F.col("child_id").alias("node_id"), F.lit(1).alias("depth"))
    out, step = walk, walk
    up = edges.select(F.col("parent_id").alias("above"), F.col("child_id").alias("anc_id"))
    for depth in range(2, levels + 1):
        step = step.join(up, "anc_id").select(F.col("above").alias("anc_id"), "node_id", F.lit(depth).alias("depth"))
        out = out.unionByName(step)
    return out.groupBy("anc_id", "node_id").agg(F.min("depth").alias("depth"))


def kind_of(node: str = "node_id"):
    return F.element_at(F.create_map(*[F.lit(x) for k, v in zip("bclsu", KINDS) for x in (k, v)]), F.substring(node, 1, 1))


def near_pairs(content: DataFrame, least: float, block: int = EDGE_BLOCK) -> DataFrame:
    """(a, b, weight): pairs of content numbers a < b whose unit vectors have a cosine of at least `least`.

    Exact, by matrix products of blocks of vectors: every pair of blocks is one bounded task and gives only the pairs at the
    threshold. Its work grows with the square of the vectors; beyond some ten million `near_pairs_by_buckets` is the way.
    """
    n = max(1, -(-content.count() // block))
    own = F.pmod(F.xxhash64("num"), F.lit(n)).cast("int")
    dealt = content.select("num", "embedding", own.alias("own")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
    dealt = dealt.select("num", "embedding", "own", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"))

    def run(key: tuple, g: pd.DataFrame) -> pd.DataFrame:
        i, j = (int(k) for k in key)
        left, right = g[g["own"] == i], g[g["own"] == j]
        if not len(left) or not len(right):
            return pd.DataFrame({"a": [], "b": [], "weight": []})
        x, y = np.stack(left["embedding"].to_numpy()), np.stack(right["embedding"].to_numpy())
        p, q = left["num"].to_numpy(), right["num"].to_numpy()
        out = []
        for at in range(0, len(x), 512):
            s = x[at : at + 512] @ y.T
            u, v = np.nonzero(s >= least - 2e-9)  # only the few that may reach the threshold are rounded
            a, b, w = p[at + u], q[v], np.round(s[u, v], 9)
            keep = (a < b if i == j else a != b) & (w >= least)
            out.append(pd.DataFrame({"a": np.minimum(a, b)[keep], "b": np.maximum(a, b)[keep], "weight": w[keep]}))
        return pd.concat(out, ignore_index=True)

    return dealt.groupBy("i", "j").applyInPandas(run, "a long, b long, weight double")


def near_pairs_by_buckets(content: DataFrame, least: float, **options) -> DataFrame:
    """The same, but only pairs that share a code of some hash table (see search.hyperplane_codes), exact cosines deciding."""
    from ..operators.search import hyperplane_codes

    bits = {"bits": 6, "tables": 16, "probes": 0, "seed": 42, "dim": 64} | options
    codes = hyperplane_codes(content.select("num", "embedding"), "num", **bits)
    pairs = codes.withColumnRenamed("num", "a").join(codes.withColumnRenamed("num", "b"), ["table", "bucket"]).where("a < b").select("a", "b").distinct()
    one, two = content.select(F.col("num").alias("a"), F.col("embedding").alias("ea")), content.select(F.col("num").alias("b"), F.col("embedding").alias("eb"))
    return pairs.join(one, "a").join(two, "b").select("a", "b", V.cosine("ea", "eb").alias("weight")).where(F.col("weight") >= least)


GRAPH_TABLES = ("embeddings",)


def graph_e(spark: SparkSession, sf_dir: str) -> Graph:
    """Vectors as content under label and id remainders; every fifth vector has a second parent. Its tables are stored."""
    keep = lambda name, build: stored(spark, sf_dir, name, GRAPH_TABLES, build)
    name = lambda k, *xs: F.concat_ws(":", F.lit(k), *[x.cast("string") for x in xs])

    def vectors() -> DataFrame:
        e = load(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("num"), F.col("label").cast("int").alias("label"), V.l2_normalise(F.col("embedding").cast("array<double>")).alias("embedding"))
        return e.select(F.concat(F.lit("v:"), "num").alias("node_id"), "num", "label", "embedding")

    content = keep("content", vectors)

    def structure() -> DataFrame:
        sub = lambda label: name("u", label, F.pmod("num", F.lit(8)))
        first = content.select(sub(F.col("label")).alias("parent_id"), F.col("node_id").alias("child_id"))
        more = content.where("num % 5 = 0").select(sub((F.col("label") + 1) % 10).alias("parent_id"), F.col("node_id").alias("child_id"))
        leaf = first.unionByName(more)
        u = leaf.select(F.split("parent_id", ":").alias("p")).distinct().select(F.element_at("p", 2).cast("int").alias("a"), F.element_at("p", 3).cast("int").alias("m"))
        a, m = F.col("a"), F.col("m")
        layers = [(name("s", a, m % 4), name("u", a, m)), (name("l", a, m % 2), name("s", a, m % 4)), (name("c", a), name("l", a, m % 2)), (name("b", a % 3), name("c", a))]
        links = u.select(F.explode(F.array(*[F.struct(p.alias("parent_id"), c.alias("child_id")) for p, c in layers])).alias("e")).select("e.*").distinct()
        return leaf.unionByName(links)

    edges = keep("struct_edges", structure)
    closure = keep("closure", lambda: closure_of(edges))
    below = closure.where("node_id like 'v:%'")
    homes = keep("homes", lambda: below.where("anc_id like 's:%'").select("node_id", F.col("anc_id").alias("section_id")))

    def summaries() -> DataFrame:
        vecs = below.join(content.select("node_id", "embedding"), "node_id").select("anc_id", "embedding")
        return V.centroid(vecs, ["anc_id"]).select(F.col("anc_id").alias("node_id"), kind_of("anc_id").alias("kind"), "embedding")

    def relations() -> DataFrame:
        at = homes.groupBy("node_id").agg(F.collect_set("section_id").alias("sections"))
        c = content.select("num", "node_id", "label", name("s", F.col("label"), F.col("num") % 4).alias("section")).join(at, "node_id")
        one = c.select(F.col("num").alias("a"), F.col("node_id").alias("src"), F.col("label").alias("la"), F.col("section").alias("sa"), F.col("sections").alias("in_a"))
        two = c.select(F.col("num").alias("b"), F.col("node_id").alias("dst"), F.col("label").alias("lb"), F.col("section").alias("sb"), F.col("sections").alias("in_b"))
        pairs = near_pairs(content, EDGE_COSINE).join(one, "a").join(two, "b").where("sa <> sb")
        return pairs.select("src", "dst", F.concat(F.lit("r"), (F.col("la") + F.col("lb")) % 10).alias("rel_type"), "weight", (~F.arrays_overlap("in_a", "in_b")).alias("cross"))

    return Graph(content, edges, closure, homes, keep("structural", summaries), keep("sem_edges", relations))


def graph_s_edges(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    """The star schema as a graph: structural edges of each level and content edges to parts, for traversal at scale."""
    t = lambda n: load(spark, sf_dir, n)
    tag = lambda k, *c: F.concat_ws(":", F.lit(k), *[F.col(x).cast("string") for x in c])
    lines = t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    return {
        "chapter": t("nation").select(tag("region", "n_regionkey").alias("parent_id"), tag("nation", "n_nationkey").alias("child_id")),
        "lesson": t("customer").select(tag("nation", "c_nationkey").alias("parent_id"), tag("customer", "c_custkey").alias("child_id")),
        "section": t("orders").select(tag("customer", "o_custkey").alias("parent_id"), tag("order", "o_orderkey").alias("child_id")),
        "subsection": lines.select("l_orderkey", "l_linenumber").distinct().select(tag("order", "l_orderkey").alias("parent_id"), tag("line", "l_orderkey", "l_linenumber").alias("child_id")),
        "content": lines.distinct().select(tag("line", "l_orderkey", "l_linenumber").alias("parent_id"), tag("part", "l_partkey").alias("child_id")),
    }


def graph_d_sentences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sentences of documents with their layout: (lang, source, doc_id, section, line, ord, sentence, batch_id)."""
    d = load(spark, sf_dir, "documents").select("doc_id", "lang", "source", F.posexplode(F.split("text", "\n")).alias("line", "t"))
    s = d.select("doc_id", "lang", "source", "line", F.posexplode(F.split("t", r"(?<=[.!?]) ")).alias("ord", "sentence"))
    s = s.withColumn("sentence", F.trim("sentence")).where("sentence <> ''")
    return s.select("lang", "source", "doc_id", F.floor(F.col("line") / 8).cast("int").alias("section"), "line", "ord", "sentence", F.floor(F.col("doc_id") / 50).cast("long").alias("batch_id"))


def queries_e(spark: SparkSession, sf_dir: str, g: Graph | None = None) -> tuple[DataFrame, DataFrame]:
    """(queries, qrels) over graph_e: every tenth node gives a query in one of five directions, blended with a distant vector.

    Grades: 2 for the nodes that the query is made of (at most five of a section), 1 for five more of their sections, 0 for
    five others; the highest counts.
    """
    g = g or graph_e(spark, sf_dir)
    c = g.content.withColumn("section_id", F.concat_ws(":", F.lit("s"), F.col("label").cast("string"), (F.col("num") % 4).cast("string")))
    base = c.where("num % 10 = 0").select(F.col("num").alias("q"), "label", "section_id", F.col("embedding").alias("own"))
    base = base.withColumn("direction", F.element_at(F.array(*[F.lit(x) for x in ("NT", "TD", "HZ", "BU", "CS")]), (F.floor(F.col("q") / 10) % 5 + 1).cast("int")))
    base = base.withColumn("other_id", F.concat_ws(":", F.lit("s"), ((F.col("label") + 5) % 10).cast("string"), (F.col("q") % 4).cast("string")))
    both = g.sem_edges.select("src", "dst", "weight").unionByName(g.sem_edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "weight"))
    both = both.where(F.substring("src", 3, 20).cast("long") % 10 == 0)
    near = both.withColumn("d", F.substring("dst", 3, 20).cast("long")).groupBy("src").agg(F.max(F.struct("weight", (-F.col("d")).alias("d"))).alias("m")).select(F.substring("src", 3, 20).cast("long").alias("q"), (-F.col("m.d")).alias("mate"))
    vec = c.select(F.col("num").alias("mate"), F.col("embedding").alias("mate_vec"), F.col("section_id").alias("mate_section"))
    summary = g.structural.where("kind = 'section'").select(F.col("node_id").alias("section_id"), F.col("embedding").alias("summary"))
    base = base.join(near, "q", "left").join(vec, "mate", "left").join(summary, "section_id")
    base = base.join(summary.select(F.col("section_id").alias("other_id"), F.col("summary").alias("other_summary")), "other_id", "left")
    far = c.select(F.col("num").alias("far"), F.col("embedding").alias("far_vec"))
    half = lambda x, y: V.scale(V.add(x, y), 0.5)
    v = F.when(F.col("direction").isin("TD", "BU"), F.col("summary")).when((F.col("direction") == "HZ") & F.col("mate").isNotNull(), half("own", "mate_vec"))
    v = v.when((F.col("direction") == "CS") & F.col("other_summary").isNotNull(), half("summary", "other_summary")).otherwise(F.col("own"))

    def asked(base: DataFrame = base) -> DataFrame:
        base = base.withColumn("far", F.pmod(F.col("q") * 7 + 3, F.lit(c.count()))).join(far, "far")
        base = base.withColumn("embedding", V.l2_normalise(V.rounded(V.l2_normalise(V.add(v, V.scale("far_vec", 0.5))))))
        return base.withColumn("query_id", F.concat(F.lit("q:"), "q"))

    base = stored(spark, sf_dir, "asked", GRAPH_TABLES, asked)
    queries = base.select("query_id", "direction", "embedding", F.col("q").alias("num"))

    return queries, stored(spark, sf_dir, "qrels", GRAPH_TABLES, lambda: labels_of(g, base))


def labels_of(g: Graph, base: DataFrame) -> DataFrame:
    """(query_id, node_id, grade) of base(query_id, direction, q, mate, section_id, other_id, mate_section).

    A node's place in its section is counted once, for all queries: grades need the first ten of a section and the nodes that a query
    is made of. Nodes of grade 0 depend on the sections alone, so that each set of sections finds them once.
    """
    d = F.col("direction")
    sections = F.array_compact(F.array("section_id", F.when(d == "CS", F.col("other_id")), F.when(d == "HZ", F.col("mate_section"))))
    base = base.select("query_id", "direction", "q", "mate", F.array_sort(F.array_distinct(sections)).alias("sections"))
    members = g.homes.join(g.content.select("node_id", "num"), "node_id")
    members = members.withColumn("k", F.row_number().over(Window.partitionBy("section_id").orderBy("num")))
    each = base.select("query_id", "direction", "q", "mate", F.explode("sections").alias("section_id"))
    inside = each.join(members.where("k <= 10"), "section_id")
    own = each.withColumn("num", F.explode(F.array_compact(F.array_distinct(F.array("q", "mate"))))).join(members, ["section_id", "num"])
    inside = inside.unionByName(own).dropDuplicates(["query_id", "section_id", "node_id"])
    used = F.when(d == "NT", F.col("num") == F.col("q")).when(d == "HZ", (F.col("num") == F.col("q")) | F.coalesce(F.col("num") == F.col("mate"), F.lit(False))).otherwise(F.col("k") <= 5)
    graded = inside.withColumn("used", used).withColumn("j", F.row_number().over(Window.partitionBy("query_id", "section_id", "used").orderBy("num")))
    graded = graded.where("used or j <= 5").select("query_id", "node_id", F.when(F.col("used"), 2).otherwise(1).alias("grade"))
    # a set of two sections at most holds no more of the first nodes than twice the largest has, so the nodes up to five more hold five others
    most = g.homes.groupBy("section_id").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n")).first()[0] or 0
    low = g.content.orderBy("num").limit(2 * most + 5).select("node_id", "num").join(g.homes.groupBy("node_id").agg(F.collect_set("section_id").alias("at")), "node_id")
    none = base.select("sections").distinct().join(F.broadcast(low), ~F.arrays_overlap("sections", "at"))
    none = none.withColumn("k", F.row_number().over(Window.partitionBy("sections").orderBy("num"))).where("k <= 5")
    none = base.select("query_id", "sections").join(none, "sections").select("query_id", "node_id", F.lit(0).alias("grade"))
    return graded.unionByName(none).groupBy("query_id", "node_id").agg(F.max("grade").cast("int").alias("grade"))
