"""Ranks, fusion, diversity and child aggregation. A run is (query_id, node_id, score, rank)."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V


def rank_within(df: DataFrame, score: str, out: str, by: str = "query_id", ties: str = "min") -> DataFrame:
    """Rank of score inside each query, highest first; equal scores share the least rank (min), have no gaps (dense) or go by node (row)."""
    w = Window.partitionBy(by).orderBy(F.desc(F.round(score, 9)))
    f = {"min": F.rank(), "dense": F.dense_rank(), "row": F.row_number()}[ties]
    w = w if ties != "row" else Window.partitionBy(by).orderBy(F.desc(F.round(score, 9)), "node_id")
    return df.withColumn(out, f.over(w))


def cut(df: DataFrame, k: int, score: str = "score") -> DataFrame:
    """The first k of each query by score, then node: the plan keeps k a partition before the shuffle."""
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "node_id")  # of the rounded score
    return df.select("query_id", "node_id", F.round(score, 9).alias("score")).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def rrf(runs: list[DataFrame], k: int = 60) -> DataFrame:
    """Reciprocal rank fusion of runs: the sum of 1 / (k + rank) over the lists that hold a node."""
    one = [r.select("query_id", "node_id", V.rrf_term("rank", k).alias("t")) for r in runs]
    both = one[0]
    for r in one[1:]:
        both = both.unionByName(r)
    return both.groupBy("query_id", "node_id").agg(F.sum("t").alias("score"))


def rrf_columns(df: DataFrame, scores: list[str], k: int = 60) -> DataFrame:
    """Fusion of several scores of the same rows: their ranks share one partitioning, the sum is row by row."""
    total = F.lit(0.0)
    for i, s in enumerate(scores):
        df = rank_within(df, s, f"__r{i}")
        total = total + V.rrf_term(f"__r{i}", k)
    return df.withColumn("score", total).drop(*[f"__r{i}" for i in range(len(scores))])


def mmr(run: DataFrame, vectors: DataFrame, k: int, lam: float = 0.7, pool: int = 50) -> DataFrame:
    """Maximal marginal relevance over the first `pool` of each query: relevance scaled to its best, greedy, at most k picks.

    With lam = 1 the order stays. Pools are bounded, so one query's group fits a task.
    """
    few = cut(run, pool).join(vectors.select("node_id", "embedding"), "node_id")

    def pick(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("rank").reset_index(drop=True)
        x = np.array(g["embedding"].tolist(), dtype=float)
        rel = g["score"].to_numpy() / max(g["score"].max(), 1e-300)
        sim, worst, left, out = x @ x.T, np.zeros(len(g)), list(range(len(g))), []
        while left and len(out) < k:
            value = [round(lam * rel[i] - (1 - lam) * (worst[i] if out else 0.0), 9) for i in left]
            i = left.pop(int(np.argmax(value)))
            out.append((g["query_id"][i], g["node_id"][i], float(max(value)), len(out) + 1))
            worst = sim[i] if len(out) == 1 else np.maximum(worst, sim[i])
        return pd.DataFrame(out, columns=["query_id", "node_id", "score", "rank"])

    return few.groupBy("query_id").applyInPandas(pick, "query_id string, node_id string, score double, rank int")


def agg_score(children: DataFrame, clip_negative: bool = False) -> DataFrame:
    """(query_id, parent_id, agg_score, n_children, n_above) from (query_id, parent_id, s): mean times ln(1 + children at the median or above).

    The threshold is each parent's own median, so that two aggregations share one shuffle. A negative mean stays as it is
    unless clip_negative sets it to zero.
    """
    w = Window.partitionBy("query_id", "parent_id")
    c = children.withColumn("tau", F.round(F.median("s").over(w), 9))
    out = c.groupBy("query_id", "parent_id").agg(F.avg("s").alias("mean"), F.count(F.lit(1)).alias("n_children"), F.count_if(F.col("s") >= F.col("tau")).alias("n_above"))
    mean = F.greatest("mean", F.lit(0.0)) if clip_negative else F.col("mean")
    return out.select("query_id", "parent_id", F.round(V.damped(mean, "n_above"), 9).alias("agg_score"), "n_children", "n_above")
