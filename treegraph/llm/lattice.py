"""Embedding near-dedup by lattice hashing: projections decoded to E8 points in several tables, neighbouring cells probed."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, materialise, maybe_broadcast, table

#: Tables, E8 blocks in a key, neighbouring cells probed in each table, and the edge of a cell for unit vectors.
TABLES, BLOCKS, PROBES, EDGE, SEED = 8, 2, 8, 1.5, 11
#: Members of a cell compared at a time; larger cells are dealt out as pairs of blocks.
BLOCK = 512


def minimal_vectors() -> np.ndarray:
    """The 240 shortest vectors of E8: two entries of +-1, or all +-1/2 with an even number of minus signs."""
    out = []
    for i, j in combinations(range(8), 2):
        for a in (1.0, -1.0):
            for b in (1.0, -1.0):
                v = np.zeros(8)
                v[i], v[j] = a, b
                out.append(v)
    half = np.array([[0.5 - (k >> i & 1) for i in range(8)] for k in range(256)])
    return np.concatenate([out, half[(half < 0).sum(axis=1) % 2 == 0]])


def nearest_even(x: np.ndarray) -> np.ndarray:
    """Nearest integer points with an even sum: round, and where the sum is odd move the worst coordinate the other way."""
    f = np.rint(x)
    d = x - f
    odd = np.flatnonzero(f.sum(axis=1).astype(np.int64) & 1)
    worst = np.abs(d[odd]).argmax(axis=1)
    f[odd, worst] += np.where(d[odd, worst] >= 0, 1.0, -1.0)
    return f


def decode(x: np.ndarray) -> np.ndarray:
    """Nearest E8 points of rows of 8: the better of the two cosets."""
    a, b = nearest_even(x), nearest_even(x - 0.5) + 0.5
    return np.where((((x - a) ** 2).sum(axis=1) <= ((x - b) ** 2).sum(axis=1))[:, None], a, b)


class Hasher:
    def __init__(self, dim: int):
        rng = np.random.default_rng([SEED, dim])
        self.maps = rng.normal(size=(TABLES, dim, 8 * BLOCKS)) / EDGE
        self.mult = rng.integers(1, 2**62, size=(TABLES, 8 * BLOCKS), dtype=np.int64) * 2 + 1
        self.roots = minimal_vectors()

    def keys(self, x: np.ndarray) -> np.ndarray:
        """(rows, TABLES, 1 + PROBES) cell names of unit vectors, a row's own cell first, then the nearest neighbours."""
        out = np.empty((len(x), TABLES, 1 + PROBES), dtype=np.int64)
        rows = np.arange(len(x))[:, None]
        with np.errstate(over="ignore"):
            for t in range(TABLES):
                p = x @ self.maps[t]
                cells = [decode(p[:, 8 * b : 8 * b + 8]) for b in range(BLOCKS)]
                gain = np.concatenate([(p[:, 8 * b : 8 * b + 8] - cells[b]) @ self.roots.T for b in range(BLOCKS)], axis=1)
                top = np.argpartition(-gain, PROBES, axis=1)[:, :PROBES]
                shift = [np.rint(2 * self.roots).astype(np.int64) @ self.mult[t, 8 * b : 8 * b + 8] for b in range(BLOCKS)]
                own = np.rint(2 * np.concatenate(cells, axis=1)).astype(np.int64) @ self.mult[t] + t * 1_000_003
                out[:, t, 0] = own
                out[:, t, 1:] = own[:, None] + np.concatenate(shift)[top]
        return out


_hashers: dict[int, Hasher] = {}


def unit(column: pa.Array) -> list[np.ndarray | None]:
    """Unit vectors in double precision; None for null, zero, and vectors with null or non-finite components."""
    out = []
    for v in column:
        x = None
        if v.is_valid and not v.values.null_count and len(v.values):
            x = v.values.to_numpy(zero_copy_only=False).astype(np.float64)
            size = np.abs(x).max()
            if np.isfinite(size) and size > 0:
                x = x / size
                x = x / np.sqrt(x @ x)
            else:
                x = None
        out.append(x)
    return out


def cells(rows: DataFrame) -> DataFrame:
    """(rk, dim, unit, keys) of the vectors that can link; keys are TABLES runs of a home cell and its probes."""

    def run(it):
        for batch in it:
            got = unit(batch.column(1))
            dims = np.array([0 if x is None else len(x) for x in got])
            for dim in np.unique(dims[dims > 0]).tolist():
                if dim not in _hashers:
                    _hashers[dim] = Hasher(dim)
                at = np.flatnonzero(dims == dim)
                x = np.array([got[i] for i in at])
                keys = _hashers[dim].keys(x).reshape(len(at), -1)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(pa.array(at)), pa.array(np.full(len(at), dim, dtype=np.int32)), _lists(x), _lists(keys)], ["rk", "dim", "unit", "keys"]
                )

    return rows.select("rk", "vector").mapInArrow(run, "rk long, dim int, unit array<double>, keys array<long>")


def _lists(x: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1) * x.shape[1], pa.int32()), pa.array(x.ravel()))


def compare(key: int, ids: np.ndarray, x: np.ndarray, keys: np.ndarray, part: np.ndarray, threshold: float, weight: np.ndarray):
    """Links of one cell, or of one pair of its blocks: (ids, links, root) of the members that have any; a link counts the other's weight.

    Only pairs at the threshold whose first common cell is this one count, so that no pair is counted twice. part holds each
    member's block, 0 or 1, with -1 for all where a block meets itself.
    """
    home = keys[:, :, 0]
    here = (home == key).any(axis=1)
    good = (x @ x.T >= threshold) & (here[:, None] | here[None, :])
    good &= ids[:, None] < ids[None, :] if part[0] < 0 else (part[:, None] == 0) & (part[None, :] == 1)
    a, b = np.nonzero(good)
    if not len(a):
        return None
    keep = np.zeros(len(a), dtype=bool)
    for s in range(0, len(a), 20_000):
        p, q = a[s : s + 20_000], b[s : s + 20_000]
        big = np.iinfo(np.int64).max
        m1 = np.where((home[p][:, :, None] == keys[q]).any(axis=2), home[p], big).min(axis=1)
        m2 = np.where((home[q][:, :, None] == keys[p]).any(axis=2), home[q], big).min(axis=1)
        keep[s : s + 20_000] = np.minimum(m1, m2) == key
    a, b = a[keep], b[keep]
    if not len(a):
        return None
    near = np.zeros((len(ids), len(ids)), dtype=bool)
    near[a, b] = near[b, a] = True
    links = near @ weight
    root = np.full(len(ids), -1)
    for i in np.flatnonzero(links):
        if root[i] < 0:
            reached = np.zeros(len(ids), dtype=bool)
            reached[i] = True
            edge = reached.copy()
            while edge.any():
                edge = near[edge].any(axis=0) & ~reached
                reached |= edge
            root[reached] = i
    got = np.flatnonzero(links)
    return ids[got], links[got], ids[root[got]]


def link_cells(shares: DataFrame, threshold: float) -> DataFrame:
    """(rk, links, root) from shares(key, dim, bi, bj, own, rk, unit, keys, weight), dealt and sorted by (key, dim, bi, bj)."""

    def run(it):
        held: list = []
        name = None

        def close():
            if len(held) < 2:
                return None
            ids = np.array([h[0] for h in held])
            _, once = np.unique(ids, return_index=True)
            ids = ids[once]
            x, keys = np.array([held[i][1] for i in once]), np.array([held[i][2] for i in once]).reshape(len(once), TABLES, 1 + PROBES)
            same = name[2] == name[3]
            part = np.full(len(once), -1) if same else np.array([int(held[i][3] == name[3]) for i in once])
            return compare(name[0], ids, x, keys, part, threshold, np.array([held[i][4] for i in once], dtype=np.int64))

        found: list = []
        for batch in it:
            names = list(zip(*[batch.column(i).to_pylist() for i in range(4)]))
            own, rk = batch.column(4).to_pylist(), batch.column(5).to_pylist()
            vec, key, weight = batch.column(6), batch.column(7), batch.column(8).to_pylist()
            for i, n in enumerate(names):
                if n != name:
                    found.append(close())
                    held, name = [], n
                held.append((rk[i], vec[i].values.to_numpy(), key[i].values.to_numpy(), own[i], weight[i]))
            done = [f for f in found if f]
            found = []
            if done:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c).astype(np.int64)) for c in zip(*done)], ["rk", "links", "root"])
        if (f := close()) is not None:
            yield pa.RecordBatch.from_arrays([pa.array(np.asarray(c).astype(np.int64)) for c in f], ["rk", "links", "root"])

    return shares.mapInArrow(run, "rk long, links long, root long")


def near_duplicates(vectors: DataFrame, *, id_col: str = "vec_id", vec_col: str = "embedding", threshold: float = 0.95) -> DataFrame:
    """One row per input row: (vec_id, n_links, component_id, kept).

    Links are pairs found with cosine >= threshold in double precision, none below it. Null, zero and non-finite vectors link
    with nothing, nor do vectors of different length. Rows that repeat id and vector are one vector, but each gets its row.
    A component is named by its smallest id that is not null; kept marks its member of that id. Equal vectors are compared
    once, with the number of their ids as weight, so that copies fill no cell. No pair leaves a cell: cells send counts of
    links and one edge a member. An empty table gives an empty result; other columns are ignored.
    """
    one, two = F.xxhash64(F.col(vec_col)), F.xxhash64(F.lit(1), F.col(vec_col))  # together the name of a vector
    rows = vectors.select(one.alias("v1"), two.alias("v2"), F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).alias("vector"))
    ids = rows.select("v1", "v2", "vec_id")
    weights = ids.distinct().groupBy("v1", "v2").agg(F.count(F.lit(1)).alias("weight"), F.min("vec_id").alias("low"))
    distinct = rows.groupBy("v1", "v2").agg(F.first("vector").alias("vector")).join(weights, ["v1", "v2"])
    named = materialise(distinct.select(F.monotonically_increasing_id().alias("rk"), "v1", "v2", "vector", "weight", "low"), "vectors")
    known = materialise(cells(named), "cells")
    share = known.select("rk", "dim", F.posexplode("keys").alias("at", "key")).select("rk", "dim", "key", (F.col("at") % (1 + PROBES) == 0).alias("home"))
    share = share.groupBy("key", "dim", "rk").agg(F.max("home").alias("home"))
    size = share.groupBy("key", "dim").agg(F.count(F.lit(1)).alias("c"), F.max("home").alias("any")).where("c > 1 and any").select("key", "dim", F.ceil(F.col("c") / BLOCK).cast("int").alias("blocks"))
    share = share.join(size, ["key", "dim"])
    own = F.pmod(F.xxhash64("rk", F.lit(1)), F.col("blocks")).cast("int")
    share = share.select("rk", "dim", "key", own.alias("own"), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    share = share.select("key", "dim", F.least("own", "other").alias("bi"), F.greatest("own", "other").alias("bj"), "own", "rk")
    wide = share.join(known.select("rk", "unit", "keys"), "rk").join(named.select("rk", "weight"), "rk").select("key", "dim", "bi", "bj", "own", "rk", "unit", "keys", "weight")
    found = materialise(link_cells(wide.repartition("key", "dim", "bi", "bj").sortWithinPartitions("key", "dim", "bi", "bj"), threshold), "links")
    group = components(found.select(F.col("rk").alias("u"), F.col("root").alias("v")))
    links = found.groupBy("rk").agg(F.sum("links").alias("links"))
    able = known.select("rk", F.lit(True).alias("able"))
    by_vector = named.select("rk", "v1", "v2", "weight", "low").join(able, "rk", "left").join(links, "rk", "left").join(group.select(F.col("node").alias("rk"), "label"), "rk", "left")
    by_vector = by_vector.withColumn("label", F.coalesce("label", "rk"))
    least = by_vector.groupBy("label").agg(F.min("low").alias("least"))
    n = F.when(F.col("able"), F.coalesce("links", F.lit(0)) + F.col("weight") - 1).otherwise(0).cast("long")
    by_vector = by_vector.join(least, "label").select("v1", "v2", n.alias("n_links"), F.when(F.col("able"), F.col("least")).alias("least"))
    out = ids.join(maybe_broadcast(materialise(by_vector, "named")), ["v1", "v2"])
    component = F.coalesce("least", "vec_id")
    return out.select("vec_id", "n_links", component.alias("component_id"), F.coalesce(F.col("vec_id") == component, component.isNull()).alias("kept"))


def op10_lattice_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))


QUERIES = {"op10_lattice_near_dedup": op10_lattice_near_dedup}
ORACLES = {
    "op10_lattice_near_dedup": """
      WITH RECURSIVE v AS (SELECT row_number() OVER () AS r, vec_id, CAST(embedding AS DOUBLE[]) AS e FROM (SELECT DISTINCT vec_id, embedding FROM embeddings)),
      ok AS MATERIALIZED (SELECT r, vec_id, len(e) AS d, list_transform(e, lambda x: x / sqrt(list_dot_product(e, e))) AS u FROM v
        WHERE len(e) > 0 AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_dot_product(e, e) > 0),
      pair AS MATERIALIZED (SELECT a.r AS a, b.r AS b FROM ok a JOIN ok b ON a.r <> b.r AND a.d = b.d WHERE list_dot_product(a.u, b.u) >= 0.95),
      reach(a, b) AS (SELECT r, r FROM v UNION SELECT reach.a, pair.b FROM reach JOIN pair ON pair.a = reach.b),
      comp AS (SELECT reach.a AS r, min(v.vec_id) AS component_id FROM reach JOIN v ON v.r = reach.b GROUP BY reach.a),
      n AS (SELECT a AS r, count(*) AS n_links FROM pair GROUP BY a)
      SELECT e.vec_id, coalesce(n_links, 0) AS n_links, component_id, e.vec_id = component_id AS kept FROM embeddings e JOIN v ON v.vec_id IS NOT DISTINCT FROM e.vec_id AND v.e IS NOT DISTINCT FROM CAST(e.embedding AS DOUBLE[]) JOIN comp USING (r) LEFT JOIN n USING (r)"""
}
