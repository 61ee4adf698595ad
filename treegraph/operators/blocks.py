"""Cosines by matrix products: sides are dealt into blocks, each pair of blocks is one bounded task that reduces its own product.

A side's count of blocks comes from a count, so that it should be a stored frame. Blocks travel once for each block of the other side.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

#: Rows in a block of queries and of nodes; rows of a product at a time; pairs whose cosines are summed at a time.
ROWS, COLUMNS, AT_ONCE, PAIRS = 2_048, 8_192, 256, 1 << 16
#: Products of blocks differ from sums in order by less than this, roundings to nine places by no more.
SLACK = 2e-9


def matrix(t: pa.Table, name: str = "embedding") -> np.ndarray:
    a = t.column(name).combine_chunks()
    return a.flatten().to_numpy(zero_copy_only=False).reshape(len(a), -1)


def nine(x: np.ndarray) -> np.ndarray:
    """Rounded to nine places, halves away from zero, as the engines do."""
    return np.copysign(np.floor(np.abs(x) * 1e9 + 0.5) / 1e9, x)


def cosines(x: np.ndarray, y: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Rounded cosines of the rows i of x and j of y, summed in the order of the components, so that no block's shape tells on them."""
    out = np.empty(len(i))
    for at in range(0, len(i), PAIRS):
        p = slice(at, at + PAIRS)
        out[p] = np.cumsum(x[i[p]] * y[j[p]], axis=1)[:, -1]
    return nine(out)


def places(names: pa.Array) -> np.ndarray:
    """The place of each name in their order."""
    order = np.empty(len(names), dtype=np.int64)
    order[np.asarray(pc.sort_indices(names))] = np.arange(len(names))
    return order


def leading(s: np.ndarray, k: int):
    """(row, column) of the k largest of each row of s, and of those that rounding may bring among them."""
    least = np.partition(s, s.shape[1] - k, axis=1)[:, s.shape[1] - k] if k < s.shape[1] else np.full(len(s), -np.inf)
    return np.nonzero(s >= (least - SLACK)[:, None])


def firsts(i: np.ndarray, j: np.ndarray, score: np.ndarray, order: np.ndarray, k: int):
    """The k largest scores of each i; equal ones go by the order of their j."""
    o = np.lexsort((order[j], -score, i))
    i, j, score = i[o], j[o], score[o]
    keep = np.arange(len(i)) - np.searchsorted(i, i) < k
    return i[keep], j[keep], score[keep]


def best(x: np.ndarray, y: np.ndarray, names: pa.Array, k: int):
    """(row of x, row of y, cosine) of the k best of each row of x; equal cosines go by name."""
    order, out = places(names), []
    for at in range(0, len(x), AT_ONCE):
        i, j = leading(x[at : at + AT_ONCE] @ y.T, k)
        i, j, cos = firsts(i, j, cosines(x, y, i + at, j), order, k)
        out.append((i + at, j, cos))
    return tuple(np.concatenate(c) for c in zip(*out))


def above(x: np.ndarray, y: np.ndarray, least: float):
    """(row of x, row of y, cosine) of all pairs at the threshold."""
    out = []
    for at in range(0, len(x), AT_ONCE):
        i, j = np.nonzero(x[at : at + AT_ONCE] @ y.T >= least - SLACK)
        cos = cosines(x, y, i + at, j)
        keep = cos >= least
        out.append((i[keep] + at, j[keep], cos[keep]))
    return tuple(np.concatenate(c) for c in zip(*out))


def parts(df: DataFrame, size: int, by: list[str] = []) -> int:
    """Blocks that the largest group of df needs."""
    c = df.groupBy(*by).agg(F.count(F.lit(1)).alias("c")).agg(F.max("c")).first()[0] if by else df.count()
    return max(1, -(-(c or 0) // size))


def own(name: str, n: int):
    return F.pmod(F.xxhash64(name), F.lit(n)).cast("int")


def each(n: int):
    return F.explode(F.sequence(F.lit(0), F.lit(n - 1)))


def products(left: DataFrame, right: DataFrame, run: Callable, schema: str, *, by: list[str] = [], rows: int | None = None, columns: int | None = -1) -> DataFrame:
    """run(left, right) -> Table for every pair of blocks of left(query_id, embedding, ...) and right(node_id, embedding, ...), inside groups of `by`.

    Without columns all of a group's right side is in each of its tasks: for groups whose size is bounded.
    """
    n = parts(left, rows or ROWS, by)
    m = parts(right, COLUMNS if columns == -1 else columns, by) if columns else 1
    empty = to_arrow_schema(StructType.fromDDL(schema)).empty_table()

    def pair(l: pa.Table, r: pa.Table) -> pa.Table:
        return run(l, r) if l.num_rows and r.num_rows else empty

    a = left.withColumn("i", own("query_id", n)).withColumn("j", each(m)).groupBy(*by, "i", "j")
    b = right.withColumn("j", own("node_id", m)).withColumn("i", each(n)).groupBy(*by, "i", "j")
    return a.cogroup(b).applyInArrow(pair, schema)


def picked(t: pa.Table, names: list[str], rows: np.ndarray) -> list:
    return [t.column(n).combine_chunks().take(pa.array(rows)) for n in names]


def topk(queries: DataFrame, nodes: DataFrame, k: int, *, by: list[str] = [], **sizes) -> DataFrame:
    """(query_id, node_id, cos): at least the k best nodes of each query, k of every pair of blocks (and group of `by`)."""

    def run(l: pa.Table, r: pa.Table) -> pa.Table:
        i, j, cos = best(matrix(l), matrix(r), r.column("node_id").combine_chunks(), k)
        return pa.Table.from_arrays([*picked(l, ["query_id"], i), *picked(r, ["node_id"], j), pa.array(cos)], ["query_id", "node_id", "cos"])

    q, n = queries.select(*by, "query_id", "embedding"), nodes.select(*by, "node_id", "embedding")
    return products(q, n, run, "query_id string, node_id string, cos double", by=by, **sizes)


def with_cosine(cands: DataFrame, queries: DataFrame, nodes: DataFrame) -> DataFrame:
    """cands(query_id, node_id, ...) with cos; a task has the candidates of one pair of blocks and its vectors."""
    q, v = queries.select("query_id", "embedding"), nodes.select("node_id", "embedding")
    n, m = parts(q, ROWS), parts(v, COLUMNS)
    names = cands.columns

    def run(c: pa.Table, both: pa.Table) -> pa.Table:
        side = both.column("side").to_numpy()
        c = c.select(names)
        x, y = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        i = pc.index_in(c.column("query_id"), value_set=both.column("id").take(pa.array(x)))
        j = pc.index_in(c.column("node_id"), value_set=both.column("id").take(pa.array(y)))
        found = np.flatnonzero(np.asarray(pc.and_(pc.is_valid(i), pc.is_valid(j))))
        c = c.take(pa.array(found))
        vectors = matrix(both) if both.num_rows else np.zeros((0, 1))
        i, j = (np.asarray(pc.fill_null(p, 0)).astype(np.int64)[found] for p in (i, j))
        return c.append_column("cos", pa.array(cosines(vectors, vectors, x[i], y[j])))

    vectors = q.select(F.lit(0).alias("side"), F.col("query_id").alias("id"), "embedding", own("query_id", n).alias("i"), each(m).alias("j"))
    vectors = vectors.unionByName(v.select(F.lit(1).alias("side"), F.col("node_id").alias("id"), "embedding", own("node_id", m).alias("j"), each(n).alias("i")))
    dealt = cands.withColumn("i", own("query_id", n)).withColumn("j", own("node_id", m))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cands.schema.fields) + ", cos double"
    return dealt.groupBy("i", "j").cogroup(vectors.groupBy("i", "j")).applyInArrow(run, schema)
