"""Vector expressions on ARRAY<DOUBLE>, and rank fusion expressions. All stay in the JVM."""

from __future__ import annotations

import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType


def col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def dot(a, b) -> Column:
    return F.aggregate(F.zip_with(col(a), col(b), lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)


def norm(a) -> Column:
    return F.sqrt(dot(a, a))


def scale(a, by) -> Column:
    return F.transform(col(a), lambda x: x * by)


def add(a, b) -> Column:
    return F.zip_with(col(a), col(b), lambda x, y: x + y)


def let(value, f) -> Column:
    """f(value), with value evaluated once: an expression that stands inside a lambda is evaluated for every element."""
    return F.transform(F.array(col(value)), f)[0]


def l2_normalise(a) -> Column:
    """a over its length; a zero vector stays."""
    return let(a, lambda v: let(norm(v), lambda n: F.when(n > 0, F.transform(v, lambda x: x / n)).otherwise(v)))


def cosine(a, b) -> Column:
    """Cosine of vectors that are unit already, rounded so that engines agree."""
    return F.round(dot(a, b), 9)


def rounded(a, places: int = 6) -> Column:
    return F.transform(col(a), lambda x: F.round(x, places))


def rrf_term(rank, k: int = 60) -> Column:
    """One list's share of a reciprocal rank fusion; a missing rank adds nothing."""
    return F.coalesce(1.0 / (F.lit(float(k)) + col(rank)), F.lit(0.0))


def damped(mean, n_above) -> Column:
    """A parent's score: the mean of its children, damped by the logarithm of how many reach the threshold."""
    return col(mean) * F.log(1 + col(n_above))


def centroid(df: DataFrame, by: list[str], vec: str = "embedding", out: str = "embedding", unit: bool = True, weight: str | None = None) -> DataFrame:
    """Mean vector of each group: components are averaged as rows, with partial sums, rounded to 6 places, then normalised.

    A row counts `weight` times, where one is given.
    """
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    mean = F.sum(F.col("x") * F.col("__w")) / F.sum("__w") if weight else F.avg("x")
    parts = df.select(*by, w.alias("__w"), F.posexplode(vec).alias("at", "x")).groupBy(*by, "at").agg(mean.alias("x"))
    packed = parts.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("at", F.round("x", 6).alias("x")))).alias("p"))
    mean = F.transform("p", lambda s: s["x"])
    return packed.select(*by, (l2_normalise(mean) if unit else mean).alias(out))


def hash_embed(df: DataFrame, by: list[str], tokens: str, d: int = 64, out: str = "embedding") -> DataFrame:
    """A deterministic stand-in for an embedding model: signed token hashes summed into d places, normalised."""
    t = df.select(*by, F.explode(tokens).alias("t")).withColumn("h", F.xxhash64("t"))
    sign = F.when(F.pmod(F.shiftright("h", 20), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    sums = t.groupBy(*by, F.pmod("h", F.lit(d)).cast("int").alias("at")).agg(F.sum(sign).alias("x"))
    m = sums.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("at", "x"))).alias("m"))
    dense = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0.0)))
    return m.select(*by, l2_normalise(dense).alias(out))


@F.arrow_udf(ArrayType(DoubleType()))
def embed_text(texts: pa.Array) -> pa.Array:
    """The shape of an embedding model behind a function of batches: here signed token hashes, 64 places, unit length; null stays null."""
    out = []
    for text in texts.to_pylist():
        v = np.zeros(64)
        for token in re.findall(r"[^\W_]+", (text or "").lower()):
            h = zlib.crc32(token.encode())
            v[h & 63] += 1.0 if h >> 6 & 1 else -1.0
        n = np.sqrt(v @ v)
        out.append(None if text is None else (v / n if n else v).tolist())
    return pa.array(out, pa.list_(pa.float64()))


@F.arrow_udf(ArrayType(DoubleType()))
def signed_sums(hashes: pa.Array) -> pa.Array:
    """hash_embed of rows that are groups already: from the hashes of a row's tokens; zero without tokens."""
    n = np.asarray(hashes.value_lengths().fill_null(0)).astype(np.int64)
    h = hashes.flatten().to_numpy(zero_copy_only=False)
    x = np.bincount(np.repeat(np.arange(len(n)), n) * 64 + (h & 63), weights=1.0 - 2.0 * ((h >> 20) & 1), minlength=64 * len(n)).astype(float).reshape(-1, 64)  # counts of nothing are integers
    size = np.sqrt((x * x).sum(axis=1, keepdims=True))
    x = np.divide(x, size, out=np.zeros_like(x), where=size > 0)
    return pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1) * 64, pa.int32()), pa.array(x.ravel()))
