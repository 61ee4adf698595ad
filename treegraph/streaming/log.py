"""Streams over the event log: each a streaming frame with its batch twin, which queries() exposes."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..sources.tables import load


def micros(column: str):
    return F.unix_micros(F.col(column).cast("timestamp"))


def read_events(spark: SparkSession, folder: str, schema, files: int = 1) -> DataFrame:
    """Event files as they arrive, so many a batch, with ten minutes for late rows."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "10 minutes")


def tumbling(e: DataFrame) -> DataFrame:
    return e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(micros("window.start").alias("start"), "event_type", "n")


def sliding(e: DataFrame) -> DataFrame:
    return e.groupBy(F.window("ts", "1 hour", "15 minutes"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(micros("window.start").alias("start"), "event_type", "n")


def sessions(e: DataFrame) -> DataFrame:
    return e.groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", micros("session_window.start").alias("start"), "n")


def first_requests(e: DataFrame) -> DataFrame:
    """Repeated requests of a user within the watermark count once (streams only)."""
    return e.dropDuplicatesWithinWatermark(["user_id", "event_type"])


def retrieve(e: DataFrame, nodes: DataFrame, k: int = 3) -> DataFrame:
    """Stateless: each event's own vector, then its best nodes from a static table that fits a broadcast."""
    from ..plans.strategy import small

    asked = e.select("event_id", "ts", F.from_json("props", "k int").getField("k").alias("num"))
    near = small(nodes.select("num", "best"))
    return asked.join(near, "num").select("event_id", F.explode(F.slice("best", 1, k)).alias("node_id"))


def interval_join(e: DataFrame) -> DataFrame:
    """Purchases within an hour after a view of the same user; both sides keep an hour of state."""
    v = e.where("event_type = 'view'").select(F.col("user_id").alias("vu"), F.col("ts").alias("vt"), F.col("event_id").alias("view_id"))
    p = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id"))
    return p.join(v, F.expr("user_id = vu AND ts >= vt AND ts <= vt + INTERVAL 1 HOUR")).select("view_id", "purchase_id")


def construct(batch: DataFrame, batch_id: int, folder: str, tau: float = 0.9) -> None:
    """foreachBatch: near-equal sentences of a micro-batch become one, and those that earlier batches have point to theirs.

    Writes (sentence, canonical) of the batch; a batch that runs again replaces its own, and reads only earlier ones.
    """
    from ..functions import vectors as V
    from ..operators.construct import dedup_batch

    spark = batch.sparkSession
    rows = batch.select("sentence").where("sentence is not null").distinct()
    tokens = rows.select(F.col("sentence").alias("node_id"), F.lit(batch_id).cast("long").alias("batch_id"), F.filter(F.split(F.lower("sentence"), r"[^\p{L}\p{N}]+"), lambda w: w != "").alias("t"))
    vectors = tokens.select("node_id", "batch_id").join(V.hash_embed(tokens, ["node_id", "batch_id"], "t"), ["node_id", "batch_id"], "left").withColumn("embedding", F.coalesce("embedding", F.array_repeat(F.lit(0.0), 64)))
    own = dedup_batch(vectors, tau).select(F.col("node_id").alias("sentence"), F.col("canonical_id").alias("canonical"))
    if batch_id:
        before = spark.read.schema("sentence string, canonical string").parquet(*[f"{folder}/batch-{i}" for i in range(batch_id)])
        before = before.groupBy("sentence").agg(F.min("canonical").alias("known"))
        own = own.join(before.withColumnRenamed("sentence", "canonical"), "canonical", "left").select("sentence", F.coalesce("known", "canonical").alias("canonical"))
    own.write.mode("overwrite").parquet(f"{folder}/batch-{batch_id}")


def requests(e: DataFrame) -> DataFrame:
    """Requests of the log as queries: (event_id, ts, user_id, num), num the vector that each asks for."""
    return e.select("event_id", "ts", "user_id", F.from_json("props", "k int").getField("k").alias("num"))


def first_of_day(e: DataFrame) -> DataFrame:
    """The batch twin of first_requests, a day long: the first event of each user and type on each day."""
    first = e.groupBy("user_id", "event_type", F.to_date("ts").alias("day")).agg(F.min(F.struct("ts", "event_id")).alias("f"))
    return first.select("user_id", "event_type", F.date_format("day", "yyyy-MM-dd").alias("day"), F.col("f.event_id").alias("event_id"))


def best_nodes(spark: SparkSession, d: str, k: int = 3) -> DataFrame:
    """(num, best): the k nearest other content nodes of every stated vector (ids below 100, as the log asks for), stored."""
    from ..operators import search
    from ..sources.graphs import GRAPH_TABLES, graph_e
    from ..sources.stored import stored

    def build() -> DataFrame:
        g = graph_e(spark, d)
        asked = load(spark, d, "events").select(F.from_json("props", "k int").getField("k").cast("long").alias("num")).distinct()
        q = g.content.join(F.broadcast(asked), "num", "left_semi").select(F.col("num").cast("string").alias("query_id"), "embedding")  # at most a hundred
        top = search.vector_topk(q, g.content, k + 1).where(F.col("node_id") != F.concat(F.lit("v:"), "query_id"))
        return top.groupBy("query_id").agg(F.slice(F.transform(F.array_sort(F.collect_list(F.struct("rank", "node_id"))), lambda x: x["node_id"]), 1, k).alias("best")).select(F.col("query_id").cast("int").alias("num"), "best")

    return stored(spark, d, "best_nodes", (*GRAPH_TABLES, "events"), build)


def reciprocal_ranks(e: DataFrame, best: DataFrame) -> DataFrame:
    """(user_id, ts, event_id, rr): 1 / rank of what the user asks for among the best nodes of the user's request before, else 0."""
    from ..plans.strategy import small

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    r = requests(e).withColumn("before", F.lag("num").over(w)).where("before is not null")
    hit = r.join(small(best.withColumnRenamed("num", "before")), "before", "left")
    at = F.array_position("best", F.concat(F.lit("v:"), F.col("num").cast("string")))
    return hit.select("user_id", "ts", "event_id", F.when(F.coalesce(at, F.lit(0)) > 0, 1.0 / at).when(F.col("before") == F.col("num"), 1.0).otherwise(0.0).alias("rr"))


def running_mrr(e: DataFrame, best: DataFrame) -> DataFrame:
    """The batch twin of the stateful stream: requests after the first of each user and their mean reciprocal rank."""
    return reciprocal_ranks(e, best).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("rr"), 6).alias("mrr"))


def running_mrr_stream(e: DataFrame, best: DataFrame) -> DataFrame:
    """(user_id, n, mrr) of each user as requests arrive: one row of state a user, dropped after a day without requests.

    The best nodes of the vectors asked for travel with the function (some hundred short lists).
    """
    known = {r["num"]: list(r["best"]) for r in best.collect()}

    def step(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        n, total, last = state.get if state.exists else (0, 0.0, -1)
        rows = sorted((t, i, k) for f in frames for t, i, k in zip(f["ts"], f["event_id"], f["num"]))
        for _, _, num in rows:
            if last >= 0:
                found = known.get(last, [])
                n, total = n + 1, total + (1.0 / (found.index(f"v:{num}") + 1) if f"v:{num}" in found else 1.0 if num == last else 0.0)
            last = int(num)
        state.update((n, total, last))
        state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs(), int(rows[-1][0].timestamp() * 1000)) + 86_400_000)
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "mrr": [round(total / n, 6) if n else 0.0]})

    asked = requests(e).where("num is not null")
    return asked.groupBy("user_id").applyInPandasWithState(step, "user_id long, n long, mrr double", "n long, total double, last long", "update", "EventTimeTimeout")


def late_rows(e: DataFrame, minutes: int = 10) -> DataFrame:
    """The batch twin of the audit: rows, in the order of ids as they arrive, behind the watermark of the rows before them."""
    w = Window.orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)  # one task: an audit of a log of bounded size
    seen = e.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("t"), "event_id").withColumn("most", F.max("t").over(w))
    return seen.agg(F.count(F.lit(1)).alias("rows"), F.count_if(F.col("t") < F.col("most") - minutes * 60_000_000).alias("late"))


def dropped_by_watermark(query) -> int:
    """Rows that the stateful operators of a finished stream dropped as too late, from its progress reports."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def run_to_end(stream: DataFrame, name: str, checkpoint: str, mode: str = "append") -> DataFrame:
    """Process what is there and stop; the result is a memory table."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


QUERIES = {
    "st_tumbling": lambda s, d: tumbling(load(s, d, "events")),
    "st_sliding": lambda s, d: sliding(load(s, d, "events")),
    "st_session": lambda s, d: sessions(load(s, d, "events")),
    "st_interval_join": lambda s, d: interval_join(load(s, d, "events")),
    "st_dedup": lambda s, d: first_of_day(load(s, d, "events")),
    "st_retrieve": lambda s, d: retrieve(load(s, d, "events"), best_nodes(s, d)),
    "st_running_mrr": lambda s, d: running_mrr(load(s, d, "events"), best_nodes(s, d)),
    "st_late": lambda s, d: late_rows(load(s, d, "events")),
}
_BEST = """e AS MATERIALIZED (SELECT vec_id AS num, CAST(embedding AS DOUBLE[]) AS v FROM embeddings), u AS MATERIALIZED (SELECT num, list_transform(v, lambda x: x / sqrt(list_dot_product(v, v))) AS v FROM e),
  ask AS MATERIALIZED (SELECT event_id, ts, user_id, CAST(json_extract(props, '$.k') AS INTEGER) AS num FROM events),
  top AS MATERIALIZED (SELECT a.num, 'v:' || b.num AS node_id, row_number() OVER (PARTITION BY a.num ORDER BY round(list_dot_product(a.v, b.v), 9) DESC, 'v:' || b.num) AS k FROM u a JOIN u b ON a.num <> b.num WHERE a.num IN (SELECT num FROM ask) QUALIFY k <= 3)"""
ORACLES = {
    "st_tumbling": "SELECT epoch_us(date_trunc('hour', ts)) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "st_sliding": "SELECT (epoch_us(ts) // 900000000 - i) * 900000000 AS start, event_type, count(*) AS n FROM events, generate_series(0, 3) AS g(i) GROUP BY 1, 2",
    "st_session": """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
      h AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, epoch_us(min(ts)) AS start, count(*) AS n FROM h GROUP BY user_id, k""",
    "st_dedup": "SELECT user_id, event_type, strftime(ts, '%Y-%m-%d') AS day, min((ts, event_id))[2] AS event_id FROM events GROUP BY 1, 2, 3",
    "st_retrieve": f"WITH {_BEST} SELECT event_id, node_id FROM ask JOIN top USING (num)",
    "st_running_mrr": f"""WITH {_BEST}, p AS (SELECT *, lag(num) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before FROM ask)
      SELECT user_id, count(*) AS n, round(avg(CASE WHEN k IS NOT NULL THEN 1.0 / k WHEN before = p.num THEN 1.0 ELSE 0.0 END), 6) AS mrr FROM p LEFT JOIN top ON top.num = before AND top.node_id = 'v:' || p.num WHERE before IS NOT NULL GROUP BY user_id""",
    "st_late": "SELECT count(*) AS rows, count(*) FILTER (ts < most - INTERVAL 10 MINUTE) AS late FROM (SELECT ts, max(ts) OVER (ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS most FROM events)",
    "st_interval_join": "SELECT v.event_id AS view_id, p.event_id AS purchase_id FROM events v JOIN events p ON v.user_id = p.user_id AND p.ts >= v.ts AND p.ts <= v.ts + INTERVAL 1 HOUR WHERE v.event_type = 'view' AND p.event_type = 'purchase'",
}
