"""Flat retrieval: exact, blockwise and approximate vector search, lexical search, and their fusion."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..plans.strategy import small
from ..sources.stored import written
from . import blocks
from . import scoring as S


def scored(queries: DataFrame, nodes: DataFrame) -> DataFrame:
    """All pairs (query_id, node_id, cos): the stated query set against every node, queries broadcast if few."""
    q = queries.select("query_id", F.col("embedding").alias("qv"))
    return nodes.select("node_id", "embedding").crossJoin(small(q)).select("query_id", "node_id", V.cosine("qv", "embedding").alias("cos"))


def vector_topk(queries: DataFrame, nodes: DataFrame, k: int) -> DataFrame:
    """The k nearest nodes of each query, exactly: every pair of blocks keeps its k best of each query before the shuffle."""
    return S.cut(blocks.topk(queries, nodes, k), k, "cos")


def vector_topk_blocks(queries: DataFrame, nodes: DataFrame, k: int, block: int = 256) -> DataFrame:
    """The same by matrix products: each task keeps its k best of each query, so that only tasks times queries times k rows move.

    Queries travel in a broadcast variable; they must fit a worker (a query set, not a table of nodes).
    """
    spark = queries.sparkSession
    rows = queries.select("query_id", "embedding").collect()
    shared = spark.sparkContext.broadcast(([r[0] for r in rows], np.array([r[1] for r in rows], dtype=float)))

    def run(it):
        names, q = shared.value
        best: list[list[tuple[float, str]]] = [[] for _ in names]
        for batch in it:
            ids = batch.column(0).to_pylist()
            x = np.array(batch.column(1).to_pylist(), dtype=float)
            for at in range(0, len(names), block):
                s = np.round(q[at : at + block] @ x.T, 9)
                for i, row in enumerate(s):
                    top = np.flatnonzero(row >= np.partition(row, -k)[-k]) if len(row) > k else range(len(row))  # ties stay
                    kept = best[at + i] + [(-float(row[j]), ids[j]) for j in top]
                    best[at + i] = sorted(kept)[:k]
        flat = [(n, i, -s) for n, b in zip(names, best) for s, i in b]
        yield pa.RecordBatch.from_pydict({"query_id": [f[0] for f in flat], "node_id": [f[1] for f in flat], "cos": [f[2] for f in flat]}, schema=pa.schema([("query_id", pa.string()), ("node_id", pa.string()), ("cos", pa.float64())]))

    return S.cut(nodes.select("node_id", "embedding").mapInArrow(run, "query_id string, node_id string, cos double"), k, "cos")


def hyperplane_codes(df: DataFrame, id_col: str, bits: int, tables: int, probes: int, seed: int, dim: int) -> DataFrame:
    """(id_col, table, bucket) by the signs of projections on fixed planes; probes flips the least certain signs as well."""
    rng = np.random.default_rng(seed)
    planes = rng.normal(size=(tables, bits, dim))
    parts = []
    for t in range(tables):
        p = F.array(*[V.dot("embedding", F.array(*[F.lit(float(x)) for x in planes[t, b]])) for b in range(bits)])
        parts.append(F.struct(F.lit(t).alias("table"), p.alias("p")))
    d = df.select(id_col, F.explode(F.array(*parts)).alias("x")).select(id_col, "x.table", "x.p")
    code = F.aggregate(F.transform("p", lambda x, i: F.when(x > 0, F.pow(F.lit(2.0), i)).otherwise(0.0)), F.lit(0.0), lambda a, x: a + x).cast("long")
    weak = F.slice(F.array_sort(F.transform("p", lambda x, i: F.struct(F.abs(x).alias("a"), i.alias("i")))), 1, probes)
    flips = F.transform(weak, lambda s: F.pow(F.lit(2.0), s["i"]).cast("long"))
    each = F.array_union(F.array(code), F.transform(flips, lambda f: code.bitwiseXOR(f))) if probes else F.array(code)
    return d.select(id_col, "table", F.explode(each).alias("bucket"))


def codes(x: np.ndarray, planes: np.ndarray, probes: int) -> np.ndarray:
    """(row, table, bucket): the buckets of each row as hyperplane_codes gives them, its own one first."""
    p = np.einsum("nd,tbd->ntb", x, planes, optimize=True)
    bit = 1 << np.arange(planes.shape[1])
    own = ((p > 0) * bit).sum(axis=2)[:, :, None]
    weak = np.argsort(np.abs(p), axis=2, kind="stable")[:, :, :probes]
    return np.concatenate([own, own ^ bit[weak]], axis=2)


def best_in_buckets(x: np.ndarray, y: np.ndarray, names: pa.Array, k: int, planes: np.ndarray, probes: int):
    """(row of x, row of y, cosine) of the k best of each row of x among the rows of y in a bucket of its own."""
    asked, held, cells = codes(x, planes, probes), codes(y, planes, 0)[:, :, 0], []
    for t in range(len(planes)):
        by_x, by_y = np.argsort(asked[:, t].ravel(), kind="stable"), np.argsort(held[:, t], kind="stable")
        ends = np.arange((1 << planes.shape[1]) + 1)
        of_x, of_y = np.searchsorted(asked[:, t].ravel()[by_x], ends), np.searchsorted(held[by_y, t], ends)
        rows = by_x // asked.shape[2]
        for c in np.flatnonzero((np.diff(of_x) > 0) & (np.diff(of_y) > 0)):
            j = by_y[of_y[c] : of_y[c + 1]]
            right = y[j].T
            for at in range(of_x[c], of_x[c + 1], blocks.AT_ONCE):
                i = rows[at : min(at + blocks.AT_ONCE, of_x[c + 1])]
                u, v = blocks.leading(x[i] @ right, k)
                cells.append(i[u] * len(y) + j[v])
    i, j = np.divmod(np.unique(np.concatenate([np.zeros(0, dtype=np.int64), *cells])), len(y))
    return blocks.firsts(i, j, blocks.cosines(x, y, i, j), blocks.places(names), k)


def ann_topk(queries: DataFrame, nodes: DataFrame, k: int, *, bits: int = 6, tables: int = 16, probes: int = 4, seed: int = 42, dim: int = 64) -> DataFrame:
    """Approximate search: equal codes in some table make candidates, exact cosines rank them. A block of queries and one of nodes find
    their codes in the task where they meet, so that neither side travels once for each code; each keeps the k best of a query."""
    planes = np.random.default_rng(seed).normal(size=(tables, bits, dim))

    def run(l: pa.Table, r: pa.Table) -> pa.Table:
        i, j, cos = best_in_buckets(blocks.matrix(l), blocks.matrix(r), r.column("node_id").combine_chunks(), k, planes, probes)
        return pa.Table.from_arrays([*blocks.picked(l, ["query_id"], i), *blocks.picked(r, ["node_id"], j), pa.array(cos)], ["query_id", "node_id", "cos"])

    q, n = queries.select("query_id", "embedding"), nodes.select("node_id", "embedding")
    return S.cut(blocks.products(q, n, run, "query_id string, node_id string, cos double"), k, "cos")


def postings(texts: DataFrame, tokens: str = "tokens") -> tuple[DataFrame, DataFrame, DataFrame]:
    """(term, node_id, tf), (node_id, dl) and one row (n, avgdl) of texts(node_id, tokens)."""
    p = texts.select("node_id", F.explode(tokens).alias("term")).groupBy("term", "node_id").agg(F.count(F.lit(1)).alias("tf"))
    dl = texts.select("node_id", F.size(tokens).alias("dl"))
    return p, dl, dl.agg(F.count(F.lit(1)).alias("n"), F.avg("dl").alias("avgdl"))


#: Queries of a block, and those whose scores of a block of texts are held at a time; the share of its cells that a term must
#: touch to go into the dense product.
ASKED, HELD, DENSE = 4_096, 512, 0.03


def lexical_best(asked: pa.Table, texts: pa.Table, k: int, n: int, avgdl: float, k1: float, b: float):
    """(row of asked, row of texts, score) of the k best texts of each query by BM25: frequent terms as a dense product, others cell by cell."""
    lists = asked.column("terms").combine_chunks()
    coded = pc.dictionary_encode(pc.struct_field(lists.flatten(), "term"))
    q_term = np.asarray(coded.indices).astype(np.int64)
    q_row = np.repeat(np.arange(len(lists)), np.asarray(pc.list_value_length(lists)))
    df = np.zeros(len(coded.dictionary))
    df[q_term] = np.asarray(pc.struct_field(lists.flatten(), "df"))
    tokens = texts.column("tokens").combine_chunks()
    dl = np.asarray(pc.fill_null(pc.list_value_length(tokens), 0)).astype(np.int64)
    found = np.asarray(pc.fill_null(pc.index_in(tokens.flatten(), value_set=coded.dictionary), -1)).astype(np.int64)
    cell, tf = np.unique((found * len(dl) + np.repeat(np.arange(len(dl)), dl))[found >= 0], return_counts=True)
    d_term, d_row = np.divmod(cell, max(1, len(dl)))
    weight = np.log(1 + (n - df + 0.5) / (df + 0.5))[d_term] * tf * (k1 + 1) / (tf + k1 * (1 - b + b * dl[d_row] / avgdl))
    ends = np.searchsorted(d_term, np.arange(len(df) + 1))
    order, out = blocks.places(texts.column("node_id").combine_chunks()), []
    by_term = np.lexsort((q_row, q_term))
    for at in range(0, len(lists), HELD):
        rows = min(HELD, len(lists) - at)
        mine = by_term[(q_row[by_term] >= at) & (q_row[by_term] < at + rows)]
        qt, qr = q_term[mine], q_row[mine] - at
        terms, first = np.unique(qt, return_index=True)
        last = np.append(first[1:], len(qt))
        share = (last - first) * (ends[terms + 1] - ends[terms]) / (rows * len(dl))
        s = np.zeros((rows, len(dl)))
        frequent = terms[share > DENSE]
        for part in range(0, len(frequent), 512):
            some = frequent[part : part + 512]
            number = np.full(len(df), -1)
            number[some] = np.arange(len(some))
            x, y = np.zeros((rows, len(some))), np.zeros((len(some), len(dl)))
            in_q = np.flatnonzero(number[qt] >= 0)
            x[qr[in_q], number[qt[in_q]]] = 1
            in_d = np.flatnonzero(number[d_term] >= 0)
            y[number[d_term[in_d]], d_row[in_d]] = weight[in_d]
            s += x @ y
        for i in np.flatnonzero(share <= DENSE):
            t = terms[i]
            if ends[t] < ends[t + 1]:
                s[qr[first[i] : last[i], None], d_row[ends[t] : ends[t + 1]]] += weight[ends[t] : ends[t + 1]]
        i, j = blocks.leading(s, k)
        hit = s[i, j] > 0  # a text without a term scores 0, one with any more
        i, j, score = blocks.firsts(i[hit], j[hit], blocks.nine(s[i[hit], j[hit]]), order, k)
        out.append((i + at, j, score))
    return tuple(np.concatenate(c) for c in zip(*out))


def bm25_topk(query_terms: DataFrame, texts: DataFrame, k: int, *, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """Lexical search; query_terms (query_id, term) are distinct per query. Documents without a term don't appear.

    A block of queries, with their terms' document frequencies, meets a block of texts(node_id, tokens) in one task; no row stands for a
    shared term, nor for a posting.
    """
    texts = written(texts.select("node_id", "tokens"), "texts")
    n, avgdl = texts.agg(F.count(F.lit(1)), F.avg(F.size("tokens"))).first()
    df = texts.select(F.explode(F.array_distinct("tokens")).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    asked = query_terms.select("query_id", "term").join(df, "term").groupBy("query_id").agg(F.collect_list(F.struct("term", "df")).alias("terms"))

    def run(l: pa.Table, r: pa.Table) -> pa.Table:
        i, j, score = lexical_best(l, r, k, n, avgdl, k1, b)
        return pa.Table.from_arrays([*blocks.picked(l, ["query_id"], i), *blocks.picked(r, ["node_id"], j), pa.array(score)], ["query_id", "node_id", "score"])

    return S.cut(blocks.products(written(asked, "asked"), texts, run, "query_id string, node_id string, score double", rows=ASKED), k)


def hybrid_topk(vector: DataFrame, lexical: DataFrame, k: int, k_rrf: int = 60) -> DataFrame:
    return S.cut(S.rrf([vector, lexical], k_rrf), k)


def ann_recall(exact: DataFrame, approx: DataFrame) -> DataFrame:
    hit = exact.select("query_id", "node_id").join(approx.select("query_id", "node_id", F.lit(1).alias("hit")), ["query_id", "node_id"], "left")
    return hit.agg(F.count(F.lit(1)).alias("n"), F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))


def sections_first(queries: DataFrame, nodes: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("query_id").orderBy(F.desc("seed_score"), "section_id")
    s = scored(queries, nodes).select("query_id", F.col("node_id").alias("section_id"), F.col("cos").alias("seed_score"))
    return s.withColumn("k", F.row_number().over(w)).where(F.col("k") <= k).drop("k")
