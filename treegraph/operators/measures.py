"""Accuracy measures: gain, recall, precision and reciprocal rank, by method, direction and cutoff."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.strategy import small

KS = (1, 3, 5, 10)


def per_query(runs: DataFrame, qrels: DataFrame, queries: DataFrame, ks=KS, *, rel_min: int = 1, gain: str = "linear", denominator: str = "k") -> DataFrame:
    """(method, query_id, direction, k, ndcg, recall, precision, mrr); queries without a relevant node are left out.

    One join with the labels and one aggregation serve all cutoffs. gain is linear or exp; precision divides by k or by the
    number of nodes returned.
    """
    g = (lambda c: F.col(c).cast("double")) if gain == "linear" else (lambda c: F.pow(F.lit(2.0), F.col(c)) - 1)
    spark = runs.sparkSession
    cut = spark.createDataFrame([(k,) for k in ks], "k int")
    ideal = qrels.where("grade > 0").withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("grade"), "node_id")))
    ideal = ideal.crossJoin(F.broadcast(cut)).groupBy("query_id", "k").agg(F.sum(F.when(F.col("r") <= F.col("k"), g("grade") / F.log2(F.col("r") + 1)).otherwise(0.0)).alias("idcg"), F.count_if(F.col("grade") >= rel_min).alias("n_rel")).where("n_rel > 0")
    hit = runs.join(small(qrels), ["query_id", "node_id"], "left").withColumn("grade", F.coalesce("grade", F.lit(0)))
    hit = hit.crossJoin(F.broadcast(cut)).where(F.col("rank") <= F.col("k"))
    rel = F.col("grade") >= rel_min
    got = hit.groupBy("method", "query_id", "k").agg(F.sum(g("grade") / F.log2(F.col("rank") + 1)).alias("dcg"), F.count_if(rel).alias("found"), F.min(F.when(rel, F.col("rank"))).alias("first"), F.count(F.lit(1)).alias("returned"))
    base = runs.select("method").distinct().crossJoin(F.broadcast(ideal)).join(small(queries.select("query_id", "direction")), "query_id")
    m = base.join(got, ["method", "query_id", "k"], "left")
    below = F.col("k") if denominator == "k" else F.greatest(F.coalesce("returned", F.lit(0)), F.lit(1))
    zero = F.lit(0.0)
    return m.select("method", "query_id", "direction", "k", F.coalesce(F.col("dcg") / F.col("idcg"), zero).alias("ndcg"), F.coalesce(F.col("found") / F.col("n_rel"), zero).alias("recall"), F.coalesce(F.col("found") / below, zero).alias("precision"), F.coalesce(1.0 / F.col("first"), zero).alias("mrr"))


def _means(df: DataFrame, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(*[F.round(F.avg(c), 6).alias(c) for c in ("ndcg", "recall", "precision", "mrr")], F.count(F.lit(1)).alias("n_queries"))


def overall(pq: DataFrame, k: int = 10) -> DataFrame:
    return _means(pq.where(F.col("k") == k), "method")


def by_cutoff(pq: DataFrame) -> DataFrame:
    return _means(pq, "method", "k")


def by_direction(pq: DataFrame, k: int = 10) -> DataFrame:
    d = pq.where(F.col("k") == k).groupBy("method").pivot("direction", ["TD", "HZ", "BU", "NT", "CS"]).agg(F.avg("ndcg"))
    return d.select("method", *[F.round(c, 6).alias(c) for c in ("TD", "HZ", "BU", "NT", "CS")])


def deltas(metrics: DataFrame, baseline: str = "b1_vector") -> DataFrame:
    """Order of the methods by gain and their difference from the baseline, in points."""
    b = metrics.where(F.col("method") == baseline).select(F.col("ndcg").alias("b"))
    r = F.row_number().over(Window.orderBy(F.desc("ndcg"), "method"))  # a dozen rows
    return metrics.crossJoin(F.broadcast(b)).select("method", "ndcg", r.alias("place"), F.round((F.col("ndcg") - F.col("b")) * 100, 4).alias("points"))
