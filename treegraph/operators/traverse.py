"""The three traversals, three rankings each. Candidates are (query_id, node_id, cos, ...); results are runs."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..plans.strategy import small
from ..sources.graphs import Graph
from ..sources.stored import written
from . import blocks, search
from . import scoring as S
from .blocks import with_cosine

#: Defaults of ours: sections matched, content seeds, content candidates for climbing, relation types kept.
TOP_SECTIONS, SEEDS, CLIMBERS, TOP_TYPES = 3, 10, 50, 3


Keep = Callable[[str, Callable[[], DataFrame]], DataFrame]  # (name, build) -> frame: how a part is kept that several methods need


Near = Callable[[int], DataFrame]  # k -> the k nearest content nodes of each query, as vector_topk gives them


def kept(name: str, build: Callable[[], DataFrame]) -> DataFrame:
    return written(build(), name)


# Top-down


def match_sections(g: Graph, queries: DataFrame, kind: str = "section", top: int = TOP_SECTIONS) -> DataFrame:
    """(query_id, section_id, seed_score) of the sections whose summaries are nearest."""
    return search.sections_first(queries, g.structural.where(F.col("kind") == kind), top)


def descend(seeds: DataFrame, closure: DataFrame) -> DataFrame:
    """All content below the seeds, once, with the best seed score of its ancestors."""
    c = closure.where("node_id like 'v:%'").select(F.col("anc_id").alias("section_id"), "node_id")
    return c.join(small(seeds), "section_id").groupBy("query_id", "node_id").agg(F.max("seed_score").alias("seed_score"))


def below(g: Graph, seeds: DataFrame, queries: DataFrame, k: int) -> DataFrame:
    """(query_id, node_id, cos): the k nearest of the content below each seed; a section's queries meet its content in blocks."""
    asked = seeds.select("query_id", "section_id").join(queries.select("query_id", "embedding"), "query_id")
    inside = g.closure.where("node_id like 'v:%'").select(F.col("anc_id").alias("section_id"), "node_id")
    inside = inside.join(asked.select("section_id").distinct(), "section_id", "left_semi").join(g.content.select("node_id", "embedding"), "node_id")
    return blocks.topk(asked, inside, k, by=["section_id"]).distinct()


def topdown(g: Graph, queries: DataFrame, k: int, variant: str = "cosine", *, kind: str = "section", top: int = TOP_SECTIONS, lam: float = 0.7, pool: int = 50, keep: Keep = kept) -> DataFrame:
    seeds = keep(f"seeds_{kind}_{top}", lambda: match_sections(g, queries, kind, top))
    if variant == "cosine":
        return S.cut(below(g, seeds, queries, k), k, "cos")

    def fused() -> DataFrame:
        c = with_cosine(descend(seeds, g.closure), queries, g.content)
        return S.cut(S.rrf_columns(c, ["cos", "seed_score"]), max(k, pool))

    first = keep(f"fused_{kind}_{top}_{max(k, pool)}", fused)
    return S.cut(first, k) if variant == "rrf" else S.mmr(first, g.content, k, lam, pool)


# Horizontal


def both_ways(edges: DataFrame) -> DataFrame:
    more = [c for c in ("cross", "weight") if c in edges.columns]
    return edges.select("src", "dst", "rel_type", *more).unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "rel_type", *more))


def relation_centroids(g: Graph, out: str = "embedding") -> DataFrame:
    """(rel_type, out): the mean vector of the ends of each type's edges; an end counts as often as it has such edges."""
    ends = g.sem_edges.select("rel_type", F.explode(F.array("src", "dst")).alias("node_id")).groupBy("rel_type", "node_id").agg(F.count(F.lit(1)).alias("c"))
    return V.centroid(ends.join(g.content.select("node_id", "embedding"), "node_id"), ["rel_type"], out=out, weight="c")


def select_relations(g: Graph, mode: str = "all", top: int = TOP_TYPES, queries: DataFrame | None = None, allow: tuple[str, ...] = ()) -> DataFrame:
    """Relation types to follow: all, those of allow (allowlist), the commonest (frequency), or those nearest to each query (centroid), as (query_id, rel_type)."""
    types = g.sem_edges.groupBy("rel_type").agg(F.count(F.lit(1)).alias("c"))
    if mode == "all":
        return types.select("rel_type")
    if mode == "allowlist":
        return types.where(F.col("rel_type").isin(list(allow))).select("rel_type")
    if mode == "frequency":
        return types.orderBy(F.desc("c"), "rel_type").limit(top).select("rel_type")
    cents = relation_centroids(g).withColumnRenamed("rel_type", "node_id")
    return search.vector_topk(queries, cents, top).select("query_id", F.col("node_id").alias("rel_type"))


def hop(g: Graph, seeds: DataFrame, relations: DataFrame | None = None, cross_branch: bool = True) -> DataFrame:
    """(query_id, node_id, seed_score): seeds and the ends of one semantic edge from them in sections none of theirs shares."""
    edges = both_ways(g.sem_edges.where("cross") if cross_branch else g.sem_edges)
    if relations is not None and "query_id" not in relations.columns:
        edges = edges.join(F.broadcast(relations), "rel_type", "left_semi")  # a few types
    step = edges.join(small(seeds.withColumnRenamed("node_id", "src")), "src")
    if relations is not None and "query_id" in relations.columns:
        step = step.join(small(relations), ["query_id", "rel_type"], "left_semi")
    out = step.select("query_id", F.col("dst").alias("node_id"), "seed_score").unionByName(seeds.select("query_id", "node_id", "seed_score"))
    return out.groupBy("query_id", "node_id").agg(F.max("seed_score").alias("seed_score"))


def candidates(g: Graph, start: DataFrame, queries: DataFrame, relations: DataFrame | None = None) -> DataFrame:
    """(query_id, node_id, seed_score, cos) of the run start and of what is one hop away."""
    seeds = start.select("query_id", "node_id", F.col("score").alias("seed_score"))
    return with_cosine(hop(g, seeds, relations), queries, g.content)


def horizontal(g: Graph, queries: DataFrame, k: int, variant: str = "cosine", *, seeds: int = SEEDS, top_types: int = TOP_TYPES, types_by: str = "frequency", allow: tuple[str, ...] = (), near: Near | None = None, share: Keep = lambda name, build: build()) -> DataFrame:
    """share keeps the candidates, which are many, for other rankings of them."""
    start = near(seeds) if near else written(search.vector_topk(queries, g.content, seeds), "seeds")
    if variant == "filtered":
        c = candidates(g, start, queries, select_relations(g, types_by, top_types, queries, allow))
    else:
        c = share(f"hop_{seeds}", lambda: candidates(g, start, queries))
    return S.cut(S.rrf_columns(c, ["seed_score", "cos"]), k) if variant == "rrf" else S.cut(c, k, "cos")


# Bottom-up


def climb(g: Graph, queries: DataFrame, c: int = CLIMBERS, near: Near | None = None) -> DataFrame:
    """(query_id, parent_id): parents of the nearest content."""
    near = (near(c) if near else search.vector_topk(queries, g.content, c)).select("query_id", F.col("node_id").alias("child_id"))
    return g.struct_edges.join(small(near), "child_id").select("query_id", "parent_id").distinct()


#: Children of a parent up to which one task has them all; larger parents' children are scored as rows.
FAMILY = 1 << 16


def family_scores(asked: DataFrame, kids: DataFrame) -> DataFrame:
    """(query_id, parent_id, agg_score, n_children, n_above) of asked(parent_id, query_id, embedding) over kids(parent_id, node_id, embedding), as scoring.agg_score has it."""

    def run(l: pa.Table, r: pa.Table) -> pa.Table:
        x, y, n = blocks.matrix(l), blocks.matrix(r), r.num_rows
        mean, above = np.empty(len(x)), np.empty(len(x), dtype=np.int64)
        step = max(1, (blocks.AT_ONCE * blocks.COLUMNS) // n)
        for at in range(0, len(x), step):
            s = blocks.nine(x[at : at + step] @ y.T)
            mean[at : at + step] = s.mean(axis=1)
            above[at : at + step] = (s >= blocks.nine(np.median(s, axis=1))[:, None]).sum(axis=1)
        arrays = [*blocks.picked(l, ["query_id", "parent_id"], np.arange(len(x))), pa.array(mean), pa.array(np.full(len(x), n, dtype=np.int64)), pa.array(above)]
        return pa.Table.from_arrays(arrays, ["query_id", "parent_id", "mean", "n_children", "n_above"])

    out = blocks.products(asked, kids, run, "query_id string, parent_id string, mean double, n_children long, n_above long", by=["parent_id"], columns=None)
    return out.select("query_id", "parent_id", F.round(V.damped(F.col("mean"), "n_above"), 9).alias("agg_score"), "n_children", "n_above")


def parent_scores(g: Graph, queries: DataFrame, c: int = CLIMBERS, child_scope: str = "all", family: int = FAMILY, near: Near | None = None) -> DataFrame:
    """(query_id, parent_id, cos, agg_score, n_children, n_above): the summary's cosine and the score from all children."""
    parents = written(climb(g, queries, c, near), "parents")
    own = with_cosine(parents.withColumnRenamed("parent_id", "node_id"), queries, g.structural).withColumnRenamed("node_id", "parent_id")
    edges = g.struct_edges.where("child_id like 'v:%'").select("parent_id", F.col("child_id").alias("node_id"))
    as_rows = lambda some: with_cosine(edges.join(small(some), "parent_id").select("query_id", "parent_id", "node_id"), queries, g.content)
    score = lambda kids: S.agg_score(kids.select("query_id", "parent_id", F.col("cos").alias("s")))
    if child_scope == "retrieved":
        near = search.vector_topk(queries, g.content, c).select("query_id", "node_id")
        return own.join(score(as_rows(parents).join(near, ["query_id", "node_id"], "left_semi")), ["query_id", "parent_id"])
    sizes = edges.groupBy("parent_id").agg(F.count(F.lit(1)).alias("c"))
    large = [r[0] for r in sizes.where(F.col("c") > family).select("parent_id").collect()]
    is_large = F.col("parent_id").isin(large) if large else F.lit(False)
    kids = edges.where(~is_large).join(g.content.select("node_id", "embedding"), "node_id")
    asked = parents.where(~is_large).join(queries.select("query_id", "embedding"), "query_id")
    agg = family_scores(asked, kids)
    if large:
        agg = agg.unionByName(score(as_rows(parents.where(is_large))))
    return own.join(agg, ["query_id", "parent_id"])


def bottomup(g: Graph, queries: DataFrame, k: int, variant: str = "parent", *, emit: str = "children", c: int = CLIMBERS, near: Near | None = None, keep: Keep = lambda name, build: build()) -> DataFrame:
    """Parents by summary cosine, child score, or both fused; emit parents, their children in the order of the parents, or both:
    each parent before its children."""
    p = keep(f"parent_scores_{c}", lambda: parent_scores(g, queries, c, near=near)).withColumnRenamed("parent_id", "node_id")
    p = S.rrf_columns(p, ["cos", "agg_score"]) if variant == "rrf" else p.withColumn("score", F.col({"parent": "cos", "agg": "agg_score"}[variant]))
    if emit == "parents":
        return S.cut(p, k)
    p = p.select("query_id", F.col("node_id").alias("parent_id"), F.round("score", 9).alias("parent_score"), "n_children")
    # k children or more stand at the best parent that has as many, so none of a lower parent is among the first k
    least = F.max(F.when(F.col("n_children") >= k, F.col("parent_score"))).over(Window.partitionBy("query_id"))
    p = written(p.withColumn("least", least).where("least is null or parent_score >= least").drop("least", "n_children"), "ranked")
    edges = g.struct_edges.where("child_id like 'v:%'").select("parent_id", F.col("child_id").alias("node_id")).join(g.content.select("node_id", "embedding"), "node_id")
    asked = p.join(queries.select("query_id", "embedding"), "query_id")

    def run(l: pa.Table, r: pa.Table) -> pa.Table:
        i, j, cos = blocks.best(blocks.matrix(l), blocks.matrix(r), r.column("node_id").combine_chunks(), k)
        return pa.Table.from_arrays([*blocks.picked(l, ["query_id"], i), *blocks.picked(r, ["node_id"], j), *blocks.picked(l, ["parent_score"], i), pa.array(cos)], ["query_id", "node_id", "parent_score", "cos"])

    kids = blocks.products(asked, edges, run, "query_id string, node_id string, parent_score double, cos double", by=["parent_id"])
    kids = kids.groupBy("query_id", "node_id").agg(F.max("parent_score").alias("parent_score"), F.max("cos").alias("cos"))
    if emit == "both":
        kids = kids.unionByName(p.select("query_id", F.col("parent_id").alias("node_id"), "parent_score", F.lit(2.0).alias("cos")))
    w = Window.partitionBy("query_id").orderBy(F.desc("parent_score"), F.desc("cos"), "node_id")
    return kids.select("query_id", "node_id", F.col("parent_score").alias("score"), F.row_number().over(w).alias("rank")).where(F.col("rank") <= k)
