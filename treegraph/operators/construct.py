"""Construction: dedup inside and across batches, merging, the centroid filter, extraction and the five-step validator.

Language-model steps stand behind functions that map frames to frames; the ones here are deterministic stand-ins. Inner steps
and thresholds are this engine's own.
"""

from __future__ import annotations

from typing import Protocol

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..plans.strategy import small
from ..sources.graphs import graph_d_sentences, graph_e
from ..sources.stored import drop, written
from ..sources.tables import words
from . import blocks, search
from .traverse import relation_centroids


def union_find(a: list[int], b: list[int], n: int) -> np.ndarray:
    """The smallest member of each one's set, after joining a[i] and b[i]; paths are halved on the way."""
    up = np.arange(n)

    def root(x: int) -> int:
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for x, y in zip(a, b):
        x, y = root(x), root(y)
        up[max(x, y)] = min(x, y)
    return np.array([root(i) for i in range(n)])


def dedup_batch(items: DataFrame, tau: float = 0.9) -> DataFrame:
    """(batch_id, node_id, canonical_id): inside a batch of items(batch_id, node_id, embedding), near-equal vectors are one.

    A batch is bounded by its producer (some thousand items); it is one group, with one shuffle and no rounds.
    """

    def run(g: pa.Table) -> pa.Table:
        g = g.sort_by("node_id")
        x, a, b = blocks.matrix(g), [], []
        for at in range(0, len(x), 512):
            i, j = np.nonzero(x[at : at + 512] @ x[at:].T >= tau)
            a += (i + at)[i < j].tolist()
            b += (j + at)[i < j].tolist()
        top = np.arange(len(x))
        if a:  # only what has a partner is joined
            some, back = np.unique(a + b, return_inverse=True)
            top[some] = some[union_find(back[: len(a)].tolist(), back[len(a) :].tolist(), len(some))]
        return pa.Table.from_arrays([g.column("batch_id"), g.column("node_id"), g.column("node_id").take(pa.array(top))], ["batch_id", "node_id", "canonical_id"])

    return items.select("batch_id", "node_id", "embedding").groupBy("batch_id").applyInArrow(run, "batch_id long, node_id string, canonical_id string")


def match_canonical(items: DataFrame, canon: DataFrame, tau: float = 0.9, **options) -> DataFrame:
    """(node_id, canonical_id): the nearest canonical item of earlier batches at tau or more, by approximate search."""
    q = items.select(F.col("node_id").alias("query_id"), "embedding")
    near = search.ann_topk(q, canon.select("node_id", "embedding"), 1, **options)
    return near.where(F.col("score") >= tau).select(F.col("query_id").alias("node_id"), F.col("node_id").alias("canonical_id"))


def match_by_text(items: DataFrame) -> DataFrame:
    """(node_id, canonical_id) of items(node_id, batch_id, key) whose key an earlier batch has: its first item by batch and id.

    The narrow table of keys is grouped with partial sums before it is joined back. Null and empty keys match nothing.
    """
    kept = items.where("key is not null and key <> ''")
    first = kept.groupBy("key").agg(F.min(F.struct("batch_id", "node_id")).alias("first"), F.count(F.lit(1)).alias("c")).where("c > 1")
    return kept.join(first, "key").where("batch_id > first.batch_id").select("node_id", F.col("first.node_id").alias("canonical_id"))


def connected_components(pairs: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node_id, canonical_id) of all nodes in pairs(a, b): the smallest id that links reach.

    Each round hangs the larger neighbours of every node on its smallest one, then the smaller ones, so that rounds grow with
    the logarithm of the longest path; each is written to the shared folder, the one before it deleted. Loops and null ends go.
    """
    e = pairs.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("a is not null and b is not null and u <> v").distinct()
    e = written(e, "links")
    for _ in range(max_rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.where("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small_ = large.join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        after = written(small_.unionByName(low.select("u", F.col("m").alias("v"))).where("u <> v").distinct(), "links")
        same = e.count() == after.count() and after.join(e, ["u", "v"], "left_anti").isEmpty()
        drop(e)
        e = after
        if same:
            return e.select(F.col("u").alias("node_id"), F.col("v").alias("canonical_id")).unionByName(e.select(F.col("v").alias("node_id"), F.col("v").alias("canonical_id")).distinct())
    raise RuntimeError("components did not settle")


def guard_tiers(components: DataFrame, structural: DataFrame) -> DataFrame:
    """components, unless it would merge a structural node: then ValueError names one. Layout is never merged."""
    ids = components.select("node_id").unionByName(components.select(F.col("canonical_id").alias("node_id")))
    bad = ids.join(structural.select("node_id"), "node_id", "left_semi").limit(1).collect()
    if bad:
        raise ValueError(f"structural node {bad[0][0]} can't be merged")
    return components


def merge_content(edges: DataFrame, components: DataFrame) -> DataFrame:
    """struct_edges with children replaced by their canonical node; all parents stay. Structural nodes are never in components."""
    c = components.select(F.col("node_id").alias("child_id"), "canonical_id")
    return edges.join(c, "child_id", "left").select("parent_id", F.coalesce("canonical_id", "child_id").alias("child_id")).distinct()


def centroid_filter(pairs: DataFrame, ontology: DataFrame, theta: float | None = None, keep_fraction: float = 0.5) -> DataFrame:
    """pairs(a, b, embedding) with best (cosine to the nearest relation centroid), rel_type, and kept: at least theta.

    Without theta the threshold is the quantile that keeps keep_fraction. The ontology is some dozens of rows, broadcast.
    """
    o = small(ontology.select("rel_type", "centroid"))
    s = pairs.crossJoin(o).groupBy("a", "b").agg(F.max(F.struct(V.cosine("embedding", "centroid").alias("best"), "rel_type")).alias("m")).select("a", "b", "m.best", "m.rel_type")
    if theta is None:
        theta = quantile(s, "best", 1 - keep_fraction)
    return s.withColumn("kept", F.col("best") >= F.lit(theta if theta is not None else 1.0))


def quantile(df: DataFrame, c: str, p: float) -> float | None:
    """The exact quantile of a column of cosines of nine places, between its neighbours: counts of bins, then of the values in two of them."""
    bins = sorted(map(tuple, df.where(F.col(c).isNotNull()).groupBy(F.floor(F.col(c) * 10_000).alias("bin")).agg(F.count(F.lit(1)).alias("n")).collect()))  # at most 20,001
    total = sum(n for _, n in bins)
    if not total:
        return None
    at = p * (total - 1)
    ranks, upto, found = (int(np.floor(at)), int(np.ceil(at))), np.cumsum([n for _, n in bins]), []
    for r in ranks:
        k = int(np.searchsorted(upto, r, "right"))
        values = sorted(map(tuple, df.where(F.floor(F.col(c) * 10_000) == bins[k][0]).groupBy(c).agg(F.count(F.lit(1)).alias("n")).collect()))  # at most 100,000
        inside = np.cumsum([n for _, n in values])
        found.append(values[int(np.searchsorted(inside, r - (upto[k] - bins[k][1]), "right"))][0])
    return found[0] if ranks[0] == ranks[1] or found[0] == found[1] else (ranks[1] - at) * found[0] + (at - ranks[0]) * found[1]


def prompt_saving(filtered: DataFrame) -> DataFrame:
    return filtered.agg(F.count(F.lit(1)).alias("pairs"), F.count_if(~F.col("kept")).alias("saved"), F.round(F.count_if(~F.col("kept")) / F.count(F.lit(1)), 6).alias("share"))


class Extractor(Protocol):
    """A weak model's client: opened once a partition, called once a pair."""

    def open(self) -> None: ...

    def extract(self, pair: np.ndarray) -> tuple[str, float]:
        """The relation of a pair, by its vector: a name, known or new, and how sure it is."""
        ...


class RuleExtractor:
    """A stand-in for a language model: the nearest known type, or below `known` a new name after it."""

    def __init__(self, types: list[str], centroids: list[list[float]], known: float = 0.2):
        self.types, self.centroids, self.known = types, np.array(centroids, dtype=float), known

    def open(self) -> None:
        pass

    def extract(self, pair: np.ndarray) -> tuple[str, float]:
        s = np.round(self.centroids @ pair, 9)
        best = max(range(len(s)), key=lambda i: (s[i], self.types[i]))
        return (self.types[best] if s[best] >= self.known else f"near_{self.types[best]}"), float(s[best])


def extract_relations(pairs: DataFrame, extractor: Extractor) -> DataFrame:
    """(a, b, name, confidence): one call of the extractor for each of pairs(a, b, embedding), in batches, a client a partition."""

    def run(it):
        extractor.open()
        for batch in it:
            got = [extractor.extract(v.values.to_numpy()) for v in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.float64())], ["a", "b", "name", "confidence"])

    return pairs.select("a", "b", "embedding").mapInArrow(run, "a string, b string, name string, confidence double")


def normal_name(c):
    return F.regexp_replace(F.lower(F.trim(c)), r"[^a-z0-9]+", "_")


def weak_judge(j: DataFrame):
    """A stand-in: a relation's name is a word of letters first, of at least four characters."""
    return F.col("norm").rlike("^[a-z][a-z0-9_]{3,}$")


def strong_judge(j: DataFrame):
    """A stand-in: a new type must be far (below 0.5) from all known ones."""
    return F.col("n.c") < 0.5


def validate_types(proposals: DataFrame, ontology: DataFrame, *, tau: float = 0.85, support: int = 2, weak=weak_judge, strong=strong_judge) -> DataFrame:
    """(name, step, verdict, alias_of, weak_calls, strong_calls) for proposals(name, embedding, support): what stopped each, or 0.

    Steps: 1 same normalised name, 2 nearest centroid at tau, 3 too little support, 4 a weak judge, 5 a strong judge. Judges
    map the frame of (name, norm, n.c, n.rel_type, support) to a Column verdict; None accepts all. The weak one is called for
    what steps 1 to 3 let pass, the strong one for what the weak one lets pass.
    """
    p = proposals.withColumn("norm", normal_name(F.col("name")))
    o = ontology.select("rel_type", "centroid", normal_name(F.col("rel_type")).alias("o_norm"))
    near = p.crossJoin(small(o)).groupBy("name").agg(F.max(F.struct(V.cosine("embedding", "centroid").alias("c"), "rel_type")).alias("n"), F.max(F.when(F.col("norm") == F.col("o_norm"), F.col("rel_type"))).alias("same"))
    j = p.join(near, "name")
    yes = F.lit(True)
    w, s = (weak(j) if weak else yes), (strong(j) if strong else yes)
    step = F.when(F.col("same").isNotNull(), 1).when(F.col("n.c") >= tau, 2).when(F.col("support") < support, 3).when(~w, 4).when(~s, 5).otherwise(0)
    verdict = F.when(step.isin(1, 2), "alias").when(step == 0, "accepted").otherwise("rejected")
    alias = F.when(step == 1, F.col("same")).when(step == 2, F.col("n.rel_type"))
    return j.select("name", step.alias("step"), verdict.alias("verdict"), alias.alias("alias_of"), step.isin(0, 4, 5).cast("int").alias("weak_calls"), step.isin(0, 5).cast("int").alias("strong_calls"))


def blocking_rate(trace: DataFrame, truth: DataFrame) -> DataFrame:
    """How many of the proposals that truth(name, duplicate) calls duplicates of known types were stopped."""
    t = trace.join(truth.where("duplicate").select("name"), "name", "left_semi")
    stopped = F.col("verdict") != "accepted"
    return t.agg(F.count_if(stopped).alias("blocked"), F.count(F.lit(1)).alias("duplicates"), F.round(F.count_if(stopped) / F.count(F.lit(1)), 6).alias("rate"))


def call_split(trace: DataFrame, n_extracted: DataFrame) -> DataFrame:
    """(judge, calls, share): calls of the weak model (extraction and step 4) and of the strong one (step 5)."""
    t = trace.agg(F.coalesce(F.sum("weak_calls"), F.lit(0)).alias("w"), F.coalesce(F.sum("strong_calls"), F.lit(0)).alias("s")).crossJoin(n_extracted.agg(F.count(F.lit(1)).alias("e")))
    total = F.col("w") + F.col("s") + F.col("e")
    rows = F.array(*[F.struct(F.lit(k).alias("judge"), c.cast("long").alias("calls"), F.round(c / total, 6).alias("share")) for k, c in (("weak", F.col("w") + F.col("e")), ("strong", F.col("s")))])
    return t.select(F.explode(rows).alias("r")).select("r.*")


def grow_ontology(ontology: DataFrame, trace: DataFrame, proposals: DataFrame) -> DataFrame:
    new = trace.where("verdict = 'accepted'").join(proposals, "name").select(F.col("name").alias("rel_type"), F.col("embedding").alias("centroid"))
    return ontology.select("rel_type", "centroid").unionByName(new)


# Workloads


def sentence_items(spark: SparkSession, d: str) -> DataFrame:
    """Distinct sentences with hashed vectors: (node_id, batch_id of the first one, embedding); zero without tokens."""
    s = graph_d_sentences(spark, d).groupBy("sentence").agg(F.min("batch_id").alias("batch_id"))
    s = s.select(F.md5("sentence").alias("node_id"), "batch_id", F.filter(F.split(F.lower("sentence"), r"[^\p{L}\p{N}]+"), lambda w: w != "").alias("t"))
    return s.select("node_id", "batch_id", V.signed_sums(F.transform("t", lambda x: F.xxhash64(x))).alias("embedding"))


def relation_ontology(spark: SparkSession, d: str) -> DataFrame:
    return relation_centroids(graph_e(spark, d), "centroid")


def candidate_pairs(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of content of one section with their mean vector: what an extractor would be asked about."""
    g = graph_e(spark, d)
    h = g.homes.join(g.content.select("node_id", "embedding"), "node_id")
    o = h.select("section_id", F.col("node_id").alias("b"), F.col("embedding").alias("eb"))
    p = h.join(o, "section_id").where("node_id < b").select(F.col("node_id").alias("a"), "b", V.l2_normalise(V.add("embedding", "eb")).alias("embedding"))
    return p.dropDuplicates(["a", "b"])


def proposals(spark: SparkSession, d: str) -> DataFrame:
    """Proposed relation names, and which are duplicates: known types respelt, renamed, or drifted far off (one in four), and new ones.

    A new one for every label has its centroid; that of label 3 is named too shortly, that of label 5 is half a known type's.
    """
    o = relation_ontology(spark, d)
    take = lambda name, vec, dup: (F.concat(*name).alias("name"), vec.alias("embedding"), F.lit(5).alias("support"), F.lit(dup).alias("duplicate"))
    again = o.select(*take((F.lit(" "), F.upper("rel_type")), F.col("centroid"), True))
    turned = F.when(F.substring("rel_type", 2, 9).cast("int") % 4 == 3, V.scale("centroid", -1.0)).otherwise(F.col("centroid"))
    renamed = o.select(*take((F.lit("like_"), F.col("rel_type")), turned, True))
    g = graph_e(spark, d)
    own = V.centroid(g.content, ["label"])
    mixed = own.where("label = 5").crossJoin(F.broadcast(o.where("rel_type = 'r0'").select("centroid"))).select("label", V.l2_normalise(V.add("embedding", "centroid")).alias("embedding"))
    own = own.where("label <> 5").unionByName(mixed)
    name = F.when(F.col("label") == 3, F.lit("x")).otherwise(F.lit("label_"))
    return again.unionByName(renamed).unionByName(own.select(F.concat(name, "label").alias("name"), "embedding", (F.col("label") % 3 + 1).cast("int").alias("support"), F.lit(False).alias("duplicate")))


def _trace(s, d):
    return validate_types(proposals(s, d), relation_ontology(s, d))


def _growth(s, d):
    """Relation types before, after the validator, and after accepting every proposal as it is."""
    o, p = relation_ontology(s, d), proposals(s, d)
    after, off = grow_ontology(o, _trace(s, d), p), o.select("rel_type").unionByName(p.select(F.col("name").alias("rel_type"))).distinct()
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return n(o, "before").crossJoin(n(after, "after")).crossJoin(n(off, "without"))


def scored_pairs(spark: SparkSession, d: str, least: float | None = None) -> DataFrame:
    """(a, b, best, rel_type) of candidate_pairs, as centroid_filter has them; from `least` on, (a, b, embedding) of those that reach it.

    A section's pairs are cells of products of its blocks; a pair of several sections counts in the first of them.
    """
    g = graph_e(spark, d)
    types = sorted(relation_ontology(spark, d).collect(), reverse=True)  # some dozens; the last name wins among equals
    names, centroids = pa.array([r["rel_type"] for r in types], pa.string()), np.array([r["centroid"] for r in types], dtype=float)
    at = g.homes.groupBy("node_id").agg(F.collect_set("section_id").alias("sections"))
    h = written(g.homes.join(at, "node_id").join(g.content.select("node_id", "embedding"), "node_id").select("section_id", "node_id", "embedding", "sections"), "members")

    def run(l: pa.Table, r: pa.Table) -> pa.Table:
        section, x, y = l.column("section_id")[0].as_py(), blocks.matrix(l), blocks.matrix(r)
        one, two = l.column("query_id").to_pylist(), r.column("node_id").to_pylist()
        place = {n: i for i, n in enumerate(sorted({*one, *two}, key=str.encode))}
        live = np.array([place[n] for n in one])[:, None] < np.array([place[n] for n in two])[None]
        inside = [[set(s) for s in t.column("sections").to_pylist()] for t in (l, r)]
        for other in sorted({o for s in inside[0] for o in s if o < section}):
            live &= ~(np.array([other in s for s in inside[0]])[:, None] & np.array([other in s for s in inside[1]])[None])
        i, j = np.nonzero(live)
        best, which, kept = np.empty(len(i)), np.empty(len(i), dtype=np.int64), []
        for p in range(0, len(i), blocks.PAIRS):
            cut = slice(p, p + blocks.PAIRS)
            v = x[i[cut]] + y[j[cut]]
            n = np.sqrt(np.cumsum(v * v, axis=1)[:, -1:])
            v = np.divide(v, n, out=v, where=n > 0)
            s = blocks.nine(v @ centroids.T)
            which[cut] = s.argmax(axis=1)
            best[cut] = s.max(axis=1)
            if least is not None:
                kept.append(v[best[cut] >= least])
        pick = np.arange(len(i)) if least is None else np.flatnonzero(best >= least)
        ends = [*blocks.picked(l, ["query_id"], i[pick]), *blocks.picked(r, ["node_id"], j[pick])]
        if least is None:
            return pa.Table.from_arrays([*ends, pa.array(best), names.take(pa.array(which))], ["a", "b", "best", "rel_type"])
        flat = np.concatenate([k.ravel() for k in kept]) if kept else np.zeros(0)
        vectors = pa.ListArray.from_arrays(pa.array(np.arange(len(pick) + 1) * x.shape[1], pa.int32()), pa.array(flat))
        return pa.Table.from_arrays([*ends, vectors], ["a", "b", "embedding"])

    schema = "a string, b string, best double, rel_type string" if least is None else "a string, b string, embedding array<double>"
    if not types:
        return spark.createDataFrame([], schema)
    again = spark.read.schema(h.schema).parquet(h.inputFiles()[0].rsplit("/", 1)[0])  # a side of its own: sides must not share columns
    return blocks.products(h.withColumnRenamed("node_id", "query_id"), again, run, schema, by=["section_id"], rows=1_024, columns=1_024)


def _filtered(s, d, keep_fraction: float = 0.5) -> tuple[DataFrame, float]:
    """(best, kept) of all candidate pairs, and the threshold."""
    best = written(scored_pairs(s, d).select("best"), "best")
    theta = quantile(best, "best", 1 - keep_fraction)
    theta = 1.0 if theta is None else theta
    return best.withColumn("kept", F.col("best") >= F.lit(theta)), theta


def _extracted(s, d):
    o = relation_ontology(s, d).orderBy("rel_type").collect()  # some dozens of relation types
    return extract_relations(scored_pairs(s, d, _filtered(s, d)[1]), RuleExtractor([r["rel_type"] for r in o], [r["centroid"] for r in o]))


def text_items(s, d) -> DataFrame:
    """(node_id, batch_id, key) of every sentence of every batch; the key is its words, however cased or marked."""
    x = graph_d_sentences(s, d).select("sentence", "batch_id").distinct()
    key = F.array_join(F.filter(F.split(F.lower("sentence"), r"[^\p{L}\p{N}]+"), lambda w: w != ""), " ")
    return x.select(F.concat(F.md5("sentence"), F.lit(":"), F.col("batch_id").cast("string")).alias("node_id"), "batch_id", key.alias("key"))


def lead_summaries(items: DataFrame, by: list[str], tokens: str = "tokens", n: int = 5) -> DataFrame:
    """(by, summary): a stand-in for a written summary, the n commonest tokens of each group, ties by token.

    Counts are partial sums by group and token; each task keeps its n first of a group before they move.
    """
    c = items.select(*by, F.explode(tokens).alias("t")).groupBy(*by, "t").agg(F.count(F.lit(1)).alias("c"))
    first = c.withColumn("k", F.row_number().over(Window.partitionBy(*by).orderBy(F.desc("c"), "t"))).where(F.col("k") <= n)
    return first.groupBy(*by).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("k", "t"))), lambda x: x["t"]), " ").alias("summary"))


def _lead(s, d):
    """Summaries of every chapter (language and source) and of every document of the text graph."""
    x = graph_d_sentences(s, d).select("lang", "source", "doc_id", words("sentence").alias("tokens"))
    chapter = lead_summaries(x, ["lang", "source"]).select(F.concat_ws(":", F.lit("chapter"), "lang", "source").alias("node_id"), "summary")
    return chapter.unionByName(lead_summaries(x, ["doc_id"]).select(F.concat_ws(":", F.lit("document"), F.col("doc_id").cast("string")).alias("node_id"), "summary"))


def _merged(s, d):
    """What merging does to the text graph: edges from lines to sentences, sentences and their most parents, before and after."""
    x = graph_d_sentences(s, d).select(F.concat_ws(":", F.lit("line"), F.col("doc_id").cast("string"), F.col("line").cast("string")).alias("parent_id"), F.concat(F.md5("sentence"), F.lit(":"), F.col("batch_id").cast("string")).alias("child_id")).distinct()
    found = guard_tiers(connected_components(match_by_text(text_items(s, d)).select(F.col("node_id").alias("a"), F.col("canonical_id").alias("b"))), x.select(F.col("parent_id").alias("node_id")))
    out = []
    for state, e in (("before", x), ("after", merge_content(x, found))):
        parents = e.groupBy("child_id").agg(F.count(F.lit(1)).alias("c"))
        out.append(parents.agg(F.lit(state).alias("state"), F.sum("c").alias("edges"), F.count(F.lit(1)).alias("sentences"), F.max("c").alias("most_parents")))
    return out[0].unionByName(out[1])


QUERIES = {
    "dedup_intra": lambda s, d: dedup_batch(sentence_items(s, d)),
    "dedup_cross": lambda s, d: match_by_text(text_items(s, d)),
    "components": lambda s, d: connected_components(graph_e(s, d).sem_edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))),
    "merge_study": _merged,
    "summaries_lead": _lead,
    "centroid_filter_saving": lambda s, d: prompt_saving(_filtered(s, d)[0]),
    "extracted_types": lambda s, d: _extracted(s, d).groupBy("name").agg(F.count(F.lit(1)).alias("n")),
    "validator_trace": _trace,
    "validator_blocking": lambda s, d: blocking_rate(_trace(s, d), proposals(s, d)),
    "call_split": lambda s, d: call_split(_trace(s, d), _filtered(s, d)[0].where("kept")),
    "ontology_growth": _growth,
}

_KEYS = r"""
WITH l AS (SELECT doc_id, doc_id // 50 AS batch_id, unnest(string_split(text, chr(10))) AS t, unnest(generate_series(0, len(string_split(text, chr(10))) - 1)) AS line FROM documents),
s AS (SELECT doc_id, batch_id, line, unnest(string_split(regexp_replace(t, '([.!?]) ', '\1' || chr(1), 'g'), chr(1))) AS x FROM l),
sen AS MATERIALIZED (SELECT doc_id, batch_id, line, trim(x) AS sentence FROM s WHERE trim(x) <> ''),
it AS MATERIALIZED (SELECT DISTINCT md5(sentence) || ':' || batch_id AS node_id, batch_id, array_to_string(list_filter(regexp_split_to_array(lower(sentence), '[^\p{L}\p{N}]+'), lambda w: w <> ''), ' ') AS key FROM sen),
fi AS MATERIALIZED (SELECT key, min((batch_id, node_id)) AS f FROM it WHERE key <> '' GROUP BY key),
hit AS MATERIALIZED (SELECT node_id, f[2] AS canonical_id FROM it JOIN fi USING (key) WHERE batch_id > f[1])
"""


def oracles(base: str) -> dict[str, str]:
    pairs = base + """
ends AS (SELECT rel_type, src AS node_id FROM sem UNION ALL SELECT rel_type, dst FROM sem),
onto AS MATERIALIZED (SELECT rel_type, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) AS cen FROM (SELECT rel_type, list(x ORDER BY i) AS v FROM
  (SELECT rel_type, i, round(avg(emb[i]), 6) AS x FROM ends JOIN c USING (node_id), generate_series(1, 64) AS t(i) GROUP BY rel_type, i) GROUP BY rel_type)),
cand AS MATERIALIZED (SELECT DISTINCT h1.node_id AS a, h2.node_id AS b FROM homes h1 JOIN homes h2 USING (section_id) WHERE h1.node_id < h2.node_id),
sums AS (SELECT a, b, list_transform(list_zip(x.emb, y.emb), lambda p: p[1] + p[2]) AS v FROM cand JOIN c x ON x.node_id = a JOIN c y ON y.node_id = b),
prs AS MATERIALIZED (SELECT a, b, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) AS pe FROM sums),
cf AS MATERIALIZED (SELECT a, b, max((round(list_dot_product(pe, cen), 9), rel_type)) AS m FROM prs, onto GROUP BY a, b),
th AS (SELECT quantile_cont(m[1], 0.5) AS theta FROM cf),
kp AS MATERIALIZED (SELECT a, b, m[1] AS best, m[2] AS rel_type, m[1] >= theta AS kept FROM cf, th),
"""
    trace = pairs + """
lab AS (SELECT label, list(x ORDER BY i) AS v FROM (SELECT label, i, round(avg(emb[i]), 6) AS x FROM c, generate_series(1, 64) AS t(i) GROUP BY label, i) GROUP BY label),
labn AS (SELECT label, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) AS v FROM lab),
labm AS (SELECT label, list_transform(list_zip(v, cen), lambda p: p[1] + p[2]) AS v FROM labn, onto WHERE label = 5 AND rel_type = 'r0'),
prop AS MATERIALIZED (SELECT ' ' || upper(rel_type) AS name, cen AS e, 5 AS support, true AS duplicate FROM onto
  UNION ALL SELECT 'like_' || rel_type, CASE WHEN CAST(substr(rel_type, 2) AS INTEGER) % 4 = 3 THEN list_transform(cen, lambda x: -x) ELSE cen END, 5, true FROM onto
  UNION ALL SELECT CASE WHEN label = 3 THEN 'x' ELSE 'label_' END || label, v, label % 3 + 1, false FROM (SELECT * FROM labn WHERE label <> 5 UNION ALL SELECT label, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) FROM labm)),
nm AS (SELECT *, regexp_replace(lower(trim(name)), '[^a-z0-9]+', '_', 'g') AS norm FROM prop),
nt AS MATERIALIZED (SELECT name, norm, support, duplicate, max((round(list_dot_product(e, cen), 9), rel_type)) AS n, max(CASE WHEN norm = regexp_replace(lower(trim(rel_type)), '[^a-z0-9]+', '_', 'g') THEN rel_type END) AS same FROM nm, onto GROUP BY ALL),
stp AS (SELECT *, CASE WHEN same IS NOT NULL THEN 1 WHEN n[1] >= 0.85 THEN 2 WHEN support < 2 THEN 3 WHEN NOT regexp_matches(norm, '^[a-z][a-z0-9_]{3,}$') THEN 4 WHEN n[1] >= 0.5 THEN 5 ELSE 0 END AS step FROM nt),
tr AS MATERIALIZED (SELECT name, duplicate, step, CASE WHEN step IN (1, 2) THEN 'alias' WHEN step = 0 THEN 'accepted' ELSE 'rejected' END AS verdict, CASE step WHEN 1 THEN same WHEN 2 THEN n[2] END AS alias_of,
  CAST(step IN (0, 4, 5) AS INTEGER) AS weak_calls, CAST(step IN (0, 5) AS INTEGER) AS strong_calls FROM stp)
"""
    kept = pairs.rstrip().rstrip(",")
    return {
        "dedup_cross": _KEYS + "SELECT * FROM hit",
        "merge_study": _KEYS + """, e AS (SELECT DISTINCT doc_id, line, md5(sentence) || ':' || batch_id AS child FROM sen), f AS (SELECT DISTINCT doc_id, line, coalesce(canonical_id, child) AS child FROM e LEFT JOIN hit ON node_id = child)
          SELECT state, CAST(sum(c) AS BIGINT) AS edges, count(*) AS sentences, max(c) AS most_parents FROM (SELECT 'before' AS state, child, count(*) AS c FROM e GROUP BY child UNION ALL SELECT 'after', child, count(*) FROM f GROUP BY child) GROUP BY state""",
        "summaries_lead": _KEYS.rstrip() + """, tk AS (SELECT doc_id, unnest(list_filter(regexp_split_to_array(lower(sentence), '[^\\p{L}\\p{N}]+'), lambda w: w <> '')) AS t FROM sen),
          g AS (SELECT 'document:' || doc_id AS node_id, t FROM tk UNION ALL SELECT concat_ws(':', 'chapter', lang, source), t FROM tk JOIN documents USING (doc_id)),
          n AS (SELECT node_id, t, row_number() OVER (PARTITION BY node_id ORDER BY count(*) DESC, t) AS k FROM g GROUP BY node_id, t QUALIFY k <= 5)
          SELECT node_id, array_to_string(list(t ORDER BY k), ' ') AS summary FROM n GROUP BY node_id""",
        "components": base.replace("WITH c", "WITH RECURSIVE c", 1) + "reach(node, top) AS (SELECT src, src FROM ways UNION SELECT ways.dst, top FROM reach JOIN ways ON ways.src = reach.node) SELECT node AS node_id, min(top) AS canonical_id FROM reach GROUP BY node",
        "centroid_filter_saving": kept + " SELECT count(*) AS pairs, count(*) FILTER (NOT kept) AS saved, round(count(*) FILTER (NOT kept) / count(*), 6) AS share FROM kp",
        "extracted_types": kept + " SELECT CASE WHEN best >= 0.2 THEN rel_type ELSE 'near_' || rel_type END AS name, count(*) AS n FROM kp WHERE kept GROUP BY 1",
        "validator_trace": trace + " SELECT name, step, verdict, alias_of, weak_calls, strong_calls FROM tr",
        "validator_blocking": trace + " SELECT count(*) FILTER (verdict <> 'accepted') AS blocked, count(*) AS duplicates, round(count(*) FILTER (verdict <> 'accepted') / count(*), 6) AS rate FROM tr WHERE duplicate",
        "call_split": trace + """, n AS (SELECT CAST(sum(weak_calls) AS BIGINT) + (SELECT count(*) FROM kp WHERE kept) AS w, CAST(sum(strong_calls) AS BIGINT) AS s FROM tr)
          SELECT 'weak' AS judge, w AS calls, round(w / (w + s), 6) AS share FROM n UNION ALL SELECT 'strong', s, round(s / (w + s), 6) FROM n""",
        "ontology_growth": trace + " SELECT (SELECT count(*) FROM onto) AS before, (SELECT count(*) FROM onto) + (SELECT count(*) FROM tr WHERE verdict = 'accepted') AS after, (SELECT count(*) FROM (SELECT rel_type FROM onto UNION SELECT name FROM prop)) AS without",
    }
