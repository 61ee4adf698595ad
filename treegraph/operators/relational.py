"""The relational operators around the methods, each a query with its oracle: joins, aggregates, windows, sets, functions."""

from __future__ import annotations

import re
import uuid

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType

from ..sources.tables import load

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def op(sql: str | None = None):
    """Register a query under its function's name, with the SQL that gives the same rows."""

    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def T(spark: SparkSession, d: str, name: str, *cols: str) -> DataFrame:
    t = load(spark, d, name)
    return t.select(*cols) if cols else t


D = F.col


def dbl(c):
    return F.col(c).cast("double")


# Scans, projections, filters


@op("SELECT l_orderkey, CAST(l_quantity AS DOUBLE) AS qty FROM lineitem WHERE l_quantity >= 45")
def scan_parquet(s, d):
    return T(s, d, "lineitem", "l_orderkey", "l_quantity").where("l_quantity >= 45").select("l_orderkey", dbl("l_quantity").alias("qty"))


@op("SELECT l_orderkey, l_linenumber, round(CAST(l_extendedprice AS DOUBLE) * (1 - CAST(l_discount AS DOUBLE)), 4) AS revenue FROM lineitem")
def project_revenue(s, d):
    return T(s, d, "lineitem").select("l_orderkey", "l_linenumber", F.round(dbl("l_extendedprice") * (1 - dbl("l_discount")), 4).alias("revenue"))


@op("SELECT o_orderkey, o_custkey FROM orders WHERE o_orderkey BETWEEN 100 AND 5000 AND o_orderstatus IN ('F', 'O')")
def filter_orders(s, d):
    return T(s, d, "orders").where(D("o_orderkey").between(100, 5000) & D("o_orderstatus").isin("F", "O")).select("o_orderkey", "o_custkey")


@op("SELECT doc_id FROM documents WHERE regexp_matches(text, '[0-9]{3}') AND contains(text, 'the') AND lang LIKE 'e%'")
def filter_text(s, d):
    return T(s, d, "documents").where(D("text").rlike("[0-9]{3}") & D("text").contains("the") & D("lang").like("e%")).select("doc_id")


@op("SELECT d.doc_id, coalesce(l.quality, -1) AS quality, l.toxic IS NOT DISTINCT FROM 1 AS toxic, CASE WHEN l.quality = 0 THEN 'low' WHEN l.quality = 1 THEN 'high' ELSE 'none' END AS class FROM documents d LEFT JOIN labels l USING (doc_id)")
def null_safe(s, d):
    j = T(s, d, "documents", "doc_id").join(T(s, d, "labels"), "doc_id", "left")
    return j.select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality"), D("toxic").eqNullSafe(1).alias("toxic"), F.when(D("quality") == 0, "low").when(D("quality") == 1, "high").otherwise("none").alias("class"))


@op("SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k FROM events")
def parse_llm_json(s, d):
    return T(s, d, "events").select("event_id", F.from_json("props", "k int").getField("k").alias("k"))


@op("SELECT CAST(json_extract(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def variant_props(s, d):
    return T(s, d, "events").select(F.variant_get(F.parse_json("props"), "$.k", "int").alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@op()
def pages_tree(s, d):
    from ..sources.tables import page_lines

    return page_lines(T(s, d, "pages"))


# Joins


@op("SELECT n_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast(s, d):
    return T(s, d, "customer").join(F.broadcast(T(s, d, "nation")), D("c_nationkey") == D("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("customers"))


@op("SELECT o_orderkey, l_linenumber, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def join_merge(s, d):
    return T(s, d, "orders").join(T(s, d, "lineitem").hint("merge"), D("o_orderkey") == D("l_orderkey")).select("o_orderkey", "l_linenumber", "l_partkey")


@op("SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def join_shuffle_hash(s, d):
    return T(s, d, "lineitem").join(T(s, d, "part").hint("shuffle_hash"), D("l_partkey") == D("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT vec_id, n_chars FROM embeddings LEFT JOIN documents ON vec_id = doc_id")
def join_left(s, d):
    return T(s, d, "embeddings", "vec_id").join(T(s, d, "documents", "doc_id", "n_chars"), D("vec_id") == D("doc_id"), "left").select("vec_id", "n_chars")


@op("SELECT p_partkey, s_suppkey FROM part FULL JOIN supplier ON p_partkey * 3 = s_suppkey * 7")
def join_full(s, d):
    return T(s, d, "part", "p_partkey").join(T(s, d, "supplier", "s_suppkey"), D("p_partkey") * 3 == D("s_suppkey") * 7, "full")


@op("SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_semi(s, d):
    return T(s, d, "orders", "o_orderkey").join(T(s, d, "lineitem", "l_orderkey"), D("o_orderkey") == D("l_orderkey"), "left_semi")


@op("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def join_anti(s, d):
    return T(s, d, "orders", "o_orderkey").join(T(s, d, "lineitem", "l_orderkey"), D("o_orderkey") == D("l_orderkey"), "left_anti")


@op("SELECT a.n_nationkey AS a, b.r_regionkey AS b FROM nation a CROSS JOIN region b")
def join_cross(s, d):
    return T(s, d, "nation").crossJoin(F.broadcast(T(s, d, "region"))).select(D("n_nationkey").alias("a"), D("r_regionkey").alias("b"))


@op("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey < b.n_regionkey AND a.n_nationkey <> b.n_nationkey")
def join_theta(s, d):
    n = T(s, d, "nation", "n_nationkey", "n_regionkey")
    m = n.toDF("b", "rb")
    return n.join(F.broadcast(m), (D("n_regionkey") < D("rb")) & (D("n_nationkey") != D("b"))).select(D("n_nationkey").alias("a"), "b")


@op("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_range(s, d):
    """Each row meets its own hour and the next one: an equi-join on the hour, then the bounds."""
    e = T(s, d, "events").select("event_id", "user_id", "ts", F.floor(F.unix_micros(D("ts").cast("timestamp")) / 3_600_000_000).alias("h"))
    a = e.select(D("event_id").alias("a"), "user_id", D("ts").alias("ta"), F.explode(F.array("h", D("h") + 1)).alias("h"))
    return a.join(e, ["user_id", "h"]).where((D("ts") > D("ta")) & (D("ts") <= D("ta") + F.expr("INTERVAL 1 HOUR"))).select("a", D("event_id").alias("b"))


@op("""SELECT p.event_id AS event_id, (SELECT max(v.ts) FROM events v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts) AS viewed FROM events p WHERE p.event_type = 'purchase'""")
def join_asof(s, d):
    """The latest view of the same user at or before each purchase: one shuffle, a running last value."""
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    e = T(s, d, "events").where("event_type in ('view', 'purchase')").withColumn("viewed", F.max(F.when(D("event_type") == "view", D("ts"))).over(w))
    return e.where("event_type = 'purchase'").select("event_id", "viewed")


@op("SELECT a.l_partkey AS a, b.l_partkey AS b, count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL HAVING count(*) > 1")
def join_self(s, d):
    x = T(s, d, "lineitem", "l_orderkey", "l_partkey")
    y = x.toDF("l_orderkey", "b")
    return x.join(y, "l_orderkey").where(D("l_partkey") < D("b")).groupBy(D("l_partkey").alias("a"), "b").agg(F.count(F.lit(1)).alias("n")).where("n > 1")


@op("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM customer JOIN orders ON c_custkey = o_custkey) WHERE k <= 2")
def join_lateral(s, d):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    best = T(s, d, "orders", "o_custkey", "o_orderkey", "o_totalprice").withColumn("k", F.row_number().over(w)).where("k <= 2")
    return T(s, d, "customer", "c_custkey").join(best, D("c_custkey") == D("o_custkey")).select("c_custkey", "o_orderkey")


@op("SELECT r_name, count(DISTINCT l_partkey) AS parts FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY r_name")
def join_chain(s, d):
    x = T(s, d, "lineitem", "l_orderkey", "l_partkey").join(T(s, d, "orders", "o_orderkey", "o_custkey"), D("l_orderkey") == D("o_orderkey"))
    x = x.join(T(s, d, "customer", "c_custkey", "c_nationkey"), D("o_custkey") == D("c_custkey")).join(F.broadcast(T(s, d, "nation")), D("c_nationkey") == D("n_nationkey"))
    return x.join(F.broadcast(T(s, d, "region")), D("n_regionkey") == D("r_regionkey")).groupBy("r_name").agg(F.countDistinct("l_partkey").alias("parts"))


# Aggregates


@op("SELECT l_returnflag, count(*) AS n, round(avg(CAST(l_quantity AS DOUBLE)), 6) AS mean, CAST(min(l_quantity) AS DOUBLE) AS low, CAST(max(l_quantity) AS DOUBLE) AS high FROM lineitem GROUP BY l_returnflag")
def agg_basic(s, d):
    q = dbl("l_quantity")
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(q), 6).alias("mean"), F.min(q).alias("low"), F.max(q).alias("high"))


@op("SELECT n_regionkey, array_to_string(list_sort(list_distinct(list(n_name))), ',') AS names FROM nation GROUP BY n_regionkey")
def agg_collect(s, d):
    return T(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_set("n_name")), ",").alias("names"))


@op("SELECT count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem")
def agg_distinct(s, d):
    return T(s, d, "lineitem").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


@op()
def agg_approx_distinct(s, d):
    return T(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


@op("SELECT l_returnflag, median(CAST(l_quantity AS DOUBLE)) AS mid, quantile_cont(CAST(l_quantity AS DOUBLE), 0.9) AS p90 FROM lineitem GROUP BY l_returnflag")
def agg_median(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.median(dbl("l_quantity")).alias("mid"), F.percentile(dbl("l_quantity"), F.lit(0.9)).alias("p90"))


@op("SELECT CAST(q AS DOUBLE) AS q, close FROM (VALUES (0.1, true), (0.5, true), (0.9, true)) AS v(q, close)")
def agg_kll(s, d):
    """Quantiles from a KLL sketch of all prices, and whether their true ranks are within 2 % of those asked for."""
    x = T(s, d, "lineitem").select(dbl("l_extendedprice").alias("x"))
    sketch = x.agg(F.kll_sketch_agg_double("x").alias("k"))
    got = sketch.select(F.explode(F.array(*[F.struct(F.lit(q).alias("q"), F.kll_sketch_get_quantile_double("k", F.lit(q)).alias("v")) for q in (0.1, 0.5, 0.9)])).alias("g")).select("g.*")
    rank = x.crossJoin(F.broadcast(got)).groupBy("q").agg(F.avg((D("x") <= D("v")).cast("int")).alias("r"), F.avg((D("x") < D("v")).cast("int")).alias("l"))  # three rows
    return rank.select("q", ((D("l") <= D("q") + 0.02) & (D("r") >= D("q") - 0.02)).alias("close"))


@op("SELECT o_custkey, count(*) FILTER (o_totalprice > 100000) AS dear FROM orders GROUP BY o_custkey")
def agg_count_if(s, d):
    return T(s, d, "orders").groupBy("o_custkey").agg(F.count_if(D("o_totalprice") > 100000).alias("dear"))


@op("SELECT label, arg_max(vec_id, vec_id % 97 * 100000 + vec_id) AS top FROM embeddings GROUP BY label")
def agg_max_by(s, d):
    return T(s, d, "embeddings").groupBy("label").agg(F.max_by("vec_id", D("vec_id") % 97 * 100000 + D("vec_id")).alias("top"))


@op("SELECT lang, source, count(*) AS n FROM documents GROUP BY GROUPING SETS ((lang), (source), ())")
def agg_grouping_sets(s, d):
    return T(s, d, "documents", "lang", "source").groupingSets([["lang"], ["source"], []], "lang", "source").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def agg_rollup(s, d):
    j = T(s, d, "customer").join(F.broadcast(T(s, d, "nation")), D("c_nationkey") == D("n_nationkey")).join(F.broadcast(T(s, d, "region")), D("n_regionkey") == D("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def agg_cube(s, d):
    return T(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@op("SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def agg_pivot(s, d):
    p = T(s, d, "documents", "source", "lang").groupBy("source").pivot("lang", ["en", "fr"]).agg(F.count(F.lit(1)))
    return p.select("source", *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("en", "fr")])


@op("SELECT doc_id, 'quality' AS name, quality AS value FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def agg_unpivot(s, d):
    return T(s, d, "labels").unpivot("doc_id", ["quality", "toxic"], "name", "value")


@op("SELECT n_regionkey, string_agg(n_name, ';' ORDER BY n_name) AS names FROM nation GROUP BY n_regionkey")
def agg_listagg(s, d):
    s_ = T(s, d, "nation")
    s_.createOrReplaceTempView("__nation")
    return s.sql("SELECT n_regionkey, listagg(n_name, ';') WITHIN GROUP (ORDER BY n_name) AS names FROM __nation GROUP BY n_regionkey")


@op("SELECT label, i - 1 AS place, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS x FROM embeddings, generate_series(1, 64) AS t(i) GROUP BY label, i")
def agg_centroid(s, d):
    e = T(s, d, "embeddings").select("label", F.posexplode(D("embedding").cast("array<double>")).alias("at", "x"))
    return e.groupBy("label", D("at").cast("long").alias("place")).agg(F.round(F.avg("x"), 6).alias("x"))


@op("SELECT l_returnflag, round(stddev_samp(CAST(l_quantity AS DOUBLE)), 6) AS sd, round(corr(CAST(l_quantity AS DOUBLE), CAST(l_extendedprice AS DOUBLE)), 6) AS r FROM lineitem GROUP BY l_returnflag")
def agg_stats(s, d):
    return T(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev(dbl("l_quantity")), 6).alias("sd"), F.round(F.corr(dbl("l_quantity"), dbl("l_extendedprice")), 6).alias("r"))


# Windows

_BY_USER = "OVER (PARTITION BY user_id ORDER BY ts, event_id)"


def _user():
    return Window.partitionBy("user_id").orderBy("ts", "event_id")


@op("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_rank(s, d):
    w, v = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"), Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return T(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"))


@op("SELECT doc_id, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd, ntile(10) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS nt FROM documents WINDOW w AS (PARTITION BY lang ORDER BY n_chars)")
def win_dist(s, d):
    w = Window.partitionBy("lang").orderBy("n_chars")
    return T(s, d, "documents", "doc_id", "lang", "n_chars").select("doc_id", F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"), F.ntile(10).over(Window.partitionBy("lang").orderBy("n_chars", "doc_id")).alias("nt"))


@op(f"SELECT event_id, lag(event_type) {_BY_USER} AS before, lead(event_type) {_BY_USER} AS after FROM events")
def win_lag(s, d):
    return T(s, d, "events").select("event_id", F.lag("event_type").over(_user()).alias("before"), F.lead("event_type").over(_user()).alias("after"))


@op("SELECT event_id, first_value(event_id) OVER w AS first, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER w AS seen FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)")
def win_first_last(s, d):
    w = _user().rowsBetween(Window.unboundedPreceding, 0)
    return T(s, d, "events").select("event_id", F.first("event_id").over(w).alias("first"), F.last(F.when(D("event_type") == "view", D("event_id")), ignorenulls=True).over(w).alias("seen"))


@op("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running FROM events")
def win_running(s, d):
    return T(s, d, "events").select("event_id", F.round(F.sum("value").over(_user().rowsBetween(Window.unboundedPreceding, 0)), 4).alias("running"))


@op("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 4) AS mean FROM events")
def win_rows(s, d):
    return T(s, d, "events").select("event_id", F.round(F.avg("value").over(_user().rowsBetween(-2, 2)), 4).alias("mean"))


@op("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def win_range(s, d):
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return T(s, d, "events").withColumn("us", F.unix_micros(D("ts").cast("timestamp"))).select("event_id", F.count(F.lit(1)).over(w).alias("n"))


@op("SELECT lang, count(*) AS n, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM documents GROUP BY lang")
def win_share(s, d):
    c = T(s, d, "documents", "lang").groupBy("lang").agg(F.count(F.lit(1)).alias("n"))
    return c.select("lang", "n", F.round(D("n") / F.sum("n").over(Window.partitionBy()), 6).alias("share"))


@op("SELECT l_orderkey, l_linenumber, l_partkey, median(CAST(l_quantity AS DOUBLE)) OVER (PARTITION BY l_orderkey) AS mid FROM lineitem")
def win_median(s, d):
    return T(s, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", F.median(dbl("l_quantity")).over(Window.partitionBy("l_orderkey")).alias("mid"))


# Sorts, limits, sets


@op("SELECT o_orderkey, CAST(o_totalprice AS DOUBLE) AS price FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
def sort_topn(s, d):
    return T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey", dbl("o_totalprice").alias("price"))


@op("SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20")
def sort_offset(s, d):
    return T(s, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(20).limit(10).select("o_orderkey")


@op("SELECT l_suppkey, l_orderkey, l_linenumber, l_partkey FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_suppkey ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey) <= 3")
def topk_per_key(s, d):
    w = Window.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber", "l_partkey")
    return T(s, d, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber", "l_partkey", "l_extendedprice").withColumn("k", F.row_number().over(w)).where("k <= 3").drop("k", "l_extendedprice")


_BUYERS, _NATIONS = "(SELECT c_nationkey AS x FROM customer)", "(SELECT s_nationkey AS x FROM supplier)"


def _sides(s, d):
    return T(s, d, "customer").select(D("c_nationkey").alias("x")), T(s, d, "supplier").select(D("s_nationkey").alias("x"))


for _name, _sql, _f in (
    ("set_union", "UNION ALL", lambda a, b: a.unionByName(b)),
    ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)),
    ("set_intersect_all", "INTERSECT ALL", lambda a, b: a.intersectAll(b)),
    ("set_except", "EXCEPT", lambda a, b: a.subtract(b)),
    ("set_except_all", "EXCEPT ALL", lambda a, b: a.exceptAll(b)),
):
    QUERIES[_name] = lambda s, d, f=_f: f(*_sides(s, d))
    ORACLES[_name] = f"SELECT x FROM {_BUYERS} {_sql} SELECT x FROM {_NATIONS}"


@op("SELECT DISTINCT l_linestatus, l_returnflag FROM lineitem")
def set_distinct(s, d):
    return T(s, d, "lineitem").dropDuplicates(["l_linestatus", "l_returnflag"]).select("l_linestatus", "l_returnflag")


# Functions


@op("SELECT p_partkey, upper(p_brand) AS a, split_part(p_type, ' ', 1) AS b, replace(p_type, ' ', '_') AS c, reverse(p_brand) AS d, length(p_name) AS e FROM part")
def fn_string(s, d):
    return T(s, d, "part").select("p_partkey", F.upper("p_brand").alias("a"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("b"), F.regexp_replace("p_type", " ", "_").alias("c"), F.reverse("p_brand").alias("d"), F.length("p_name").cast("long").alias("e"))


@op("SELECT a.n_name AS a, b.n_name AS b, levenshtein(a.n_name, b.n_name) AS d FROM nation a JOIN nation b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey")
def fn_fuzzy(s, d):
    n = T(s, d, "nation", "n_nationkey", "n_regionkey", "n_name")
    return n.join(F.broadcast(n.toDF("k", "n_regionkey", "b")), "n_regionkey").where("n_nationkey < k").select(D("n_name").alias("a"), "b", F.levenshtein("n_name", "b").cast("long").alias("d"))


@op("SELECT doc_id, md5(text) AS m, sha256(text) AS s FROM documents")
def fn_hash(s, d):
    return T(s, d, "documents").select("doc_id", F.md5("text").alias("m"), F.sha2("text", 256).alias("s"))


@op("SELECT event_id, CAST(date_trunc('hour', ts) AS VARCHAR) AS h, CAST(extract(dow FROM ts) AS INTEGER) AS dow, epoch_us(ts) AS us FROM events")
def fn_date(s, d):
    return T(s, d, "events").select("event_id", F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH:mm:ss").alias("h"), (F.dayofweek("ts") - 1).alias("dow"), F.unix_micros(D("ts").cast("timestamp")).alias("us"))


@op("SELECT event_id, round(ln(1 + abs(value)), 6) AS a, round(sqrt(abs(value)), 6) AS b, greatest(value, 0) AS c, floor(value)::BIGINT AS d FROM events")
def fn_math(s, d):
    v = D("value")
    return T(s, d, "events").select("event_id", F.round(F.log(1 + F.abs(v)), 6).alias("a"), F.round(F.sqrt(F.abs(v)), 6).alias("b"), F.greatest(v, F.lit(0.0)).alias("c"), F.floor(v).alias("d"))


@op("SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x)), 6) AS sq, round(list_max(CAST(embedding AS DOUBLE[])), 6) AS top FROM embeddings")
def fn_array(s, d):
    e = D("embedding").cast("array<double>")
    return T(s, d, "embeddings").select("vec_id", F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("pos"), F.round(F.aggregate(e, F.lit(0.0), lambda a, x: a + x * x), 6).alias("sq"), F.round(F.array_max(e), 6).alias("top"))


@op("SELECT n_regionkey, count(*) AS n, max(n_nationkey) AS top FROM nation GROUP BY n_regionkey")
def fn_map(s, d):
    m = T(s, d, "nation").groupBy("n_regionkey").agg(F.map_from_entries(F.collect_list(F.struct("n_name", "n_nationkey"))).alias("m"))
    return m.select("n_regionkey", F.size(F.map_keys("m")).cast("long").alias("n"), F.array_max(F.map_values("m")).alias("top"))


@op("SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def fn_json(s, d):
    return T(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@op("SELECT event_id, try_cast(event_type AS INTEGER) AS a, CASE WHEN value = 0 THEN NULL ELSE round(1 / value, 6) END AS b FROM events")
def fn_cond(s, d):
    return T(s, d, "events").select("event_id", D("event_type").try_cast("int").alias("a"), F.round(F.try_divide(F.lit(1.0), "value"), 6).alias("b"))


@op("SELECT vec_id, round(sqrt(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[]))), 6) AS n FROM embeddings")
def fn_vector(s, d):
    from ..functions.vectors import norm

    return T(s, d, "embeddings").select("vec_id", F.round(norm(D("embedding").cast("array<double>")), 6).alias("n"))


SQL_FUNCTIONS = (
    "rrf_term(r BIGINT, k INT) RETURNS DOUBLE RETURN coalesce(1D / (k + r), 0D)",
    "agg_parent(mean DOUBLE, n BIGINT) RETURNS DOUBLE RETURN mean * ln(1 + n)",
    "cosine_sim(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x) "
    "/ sqrt(aggregate(a, 0D, (s, x) -> s + x * x) * aggregate(b, 0D, (s, x) -> s + x * x))",
)


def register_functions(s) -> None:
    """SQL users get fusion terms, parent scores and cosines as functions that the optimizer inlines."""
    for f in SQL_FUNCTIONS:
        s.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {f}")


@op("""WITH e AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings), f AS (SELECT label, min(vec_id) AS k FROM e GROUP BY label)
  SELECT e.vec_id, round(list_dot_product(e.v, x.v) / sqrt(list_dot_product(e.v, e.v) * list_dot_product(x.v, x.v)), 6) AS cos, round(1.0 / (60 + e.vec_id), 9) AS term,
    round((list_dot_product(e.v, x.v) / sqrt(list_dot_product(e.v, e.v) * list_dot_product(x.v, x.v))) * ln(1 + e.label), 6) + 0.0 AS damped FROM e JOIN f USING (label) JOIN e x ON x.vec_id = f.k""")
def udf_sql(s, d):
    """The three functions over every vector and the first one of its label."""
    register_functions(s)
    e = T(s, d, "embeddings").select("vec_id", "label", D("embedding").cast("array<double>").alias("v"))
    first = e.groupBy("label").agg(F.min_by("v", "vec_id").alias("f"))
    x = e.join(F.broadcast(first), "label").select("vec_id", "label", F.expr("cosine_sim(v, f)").alias("c"))  # a vector a label
    return x.select("vec_id", F.round("c", 6).alias("cos"), F.round(F.expr("rrf_term(vec_id, 60)"), 9).alias("term"), (F.round(F.expr("agg_parent(c, CAST(label AS BIGINT))"), 6) + 0.0).alias("damped"))


# Python functions, where expressions would not do


@F.pandas_udf(ArrayType(DoubleType()))
def vec_mean(v: pd.Series) -> list:
    """The mean of a group's vectors; null and empty ones don't count, a group of such alone gives null."""
    kept = [x for x in v if x is not None and len(x)]
    return np.mean(np.stack(kept), axis=0).tolist() if kept else None


@op("SELECT label, i - 1 AS place, round(avg(CAST(embedding[i] AS DOUBLE)), 6) AS x FROM embeddings, generate_series(1, 64) AS t(i) GROUP BY label, i")
def udaf_vec_mean(s, d):
    g = T(s, d, "embeddings").groupBy("label").agg(vec_mean(D("embedding").cast("array<double>")).alias("m"))
    return g.select("label", F.posexplode("m").alias("place", "x")).select("label", D("place").cast("long").alias("place"), F.round("x", 6).alias("x"))


@F.udtf(returnType="level int, ord int, body string")
class split_nodes:
    """Layout nodes of a text: level 0 the text's first line, 1 its lines, 2 the sentences of each."""

    def eval(self, text: str):
        lines = (text or "").split("\n")
        yield 0, 0, lines[0]
        at = 0
        for i, line in enumerate(lines):
            yield 1, i, line
            for x in re.split(r"(?<=[.!?]) ", line):
                if x.strip(" "):
                    yield 2, at, x.strip(" ")
                    at += 1


@op(r"""WITH l AS (SELECT doc_id, unnest(generate_series(1, len(string_split(text, chr(10))))) AS i, string_split(text, chr(10)) AS ls FROM documents),
  s AS (SELECT doc_id, i, unnest(generate_series(1, len(p))) AS j, p FROM (SELECT doc_id, i, string_split(regexp_replace(ls[i], '([.!?]) ', '\1' || chr(1), 'g'), chr(1)) AS p FROM l))
  SELECT 0 AS level, count(*) AS n, CAST(sum(length(coalesce(ls[1], ''))) AS BIGINT) AS chars FROM l WHERE i = 1 UNION ALL SELECT 1, count(*), CAST(sum(length(ls[i])) AS BIGINT) FROM l
  UNION ALL SELECT 2, count(*), CAST(sum(length(trim(p[j]))) AS BIGINT) FROM s WHERE trim(p[j]) <> ''""")
def udtf_split(s, d):
    s.udtf.register("split_nodes", split_nodes)
    T(s, d, "documents").select("doc_id", "text").createOrReplaceTempView("__layout")
    n = s.sql("SELECT d.doc_id, n.level, n.body FROM __layout d, LATERAL split_nodes(d.text) n")
    return n.groupBy("level").agg(F.count(F.lit(1)).alias("n"), F.sum(F.length("body")).alias("chars"))


@op()
def udf_embed(s, d):
    """A pluggable embedder as an Arrow function: here signed hashes of the tokens of every conversation turn."""
    from ..functions.vectors import embed_text

    return T(s, d, "conversations").select("conv_id", "turn", embed_text("text").alias("embedding"))


@op("SELECT a.vec_id, b.vec_id AS other FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id AND a.vec_id % 20 = 0 WHERE round(list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) / sqrt(list_dot_product(CAST(a.embedding AS DOUBLE[]), CAST(a.embedding AS DOUBLE[])) * list_dot_product(CAST(b.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[]))), 9) >= 0.3")
def filter_cosine(s, d):
    """Vectors at a cosine of 0.3 or more to each of the stated queries (ids divisible by 20), others dropped."""
    from ..functions import vectors as V
    from . import blocks

    e = T(s, d, "embeddings").where("embedding is not null").select("vec_id", V.l2_normalise(D("embedding").cast("array<double>")).alias("embedding"))
    q = e.where("vec_id % 20 = 0").withColumnRenamed("vec_id", "query_id")

    def run(l, r):
        i, j, _ = blocks.above(blocks.matrix(l), blocks.matrix(r), 0.3)
        return pa.Table.from_arrays([*blocks.picked(l, ["query_id"], i), *blocks.picked(r, ["node_id"], j)], ["vec_id", "other"])

    return blocks.products(q, e.withColumnRenamed("vec_id", "node_id"), run, "vec_id long, other long").where(D("vec_id") != D("other"))


@op("""WITH RECURSIVE w AS (SELECT 'r' || r_regionkey AS node, 0 AS depth, 'r' || r_regionkey AS root FROM region UNION ALL SELECT e.child, depth + 1, root FROM w JOIN
  (SELECT 'r' || n_regionkey AS parent, 'n' || n_nationkey AS child FROM nation UNION ALL SELECT 'n' || c_nationkey, 'c' || c_custkey FROM customer UNION ALL SELECT 'c' || o_custkey, 'o' || o_orderkey FROM orders) e ON e.parent = w.node)
  SELECT root, depth, count(*) AS n FROM w GROUP BY root, depth""")
def recursive_descend(s, d):
    """The subtree of every region without a closure table, by a recursive query: one round a level."""
    edges = [("nation", "r", "n_regionkey", "n", "n_nationkey"), ("customer", "n", "c_nationkey", "c", "c_custkey"), ("orders", "c", "o_custkey", "o", "o_orderkey")]
    e = [T(s, d, t).select(F.concat(F.lit(a), D(x).cast("string")).alias("parent"), F.concat(F.lit(b), D(y).cast("string")).alias("child")) for t, a, x, b, y in edges]
    e[0].unionByName(e[1]).unionByName(e[2]).createOrReplaceTempView("__edges")
    T(s, d, "region").select(F.concat(F.lit("r"), D("r_regionkey").cast("string")).alias("node")).createOrReplaceTempView("__roots")
    return s.sql("""WITH RECURSIVE walk(node, depth, root) AS (SELECT node, 0, node FROM __roots UNION ALL SELECT e.child, depth + 1, root FROM walk JOIN __edges e ON e.parent = walk.node)
      SELECT root, depth, count(*) AS n FROM walk GROUP BY root, depth""")


# Sinks read back


def _round(form):
    def run(s, d):
        from ..sources.stored import shared_root
        from ..sources.tables import roundtrip

        return roundtrip(T(s, d, "nation").select("n_nationkey", "n_name", "n_regionkey"), f"{shared_root(s)}/roundtrip-{uuid.uuid4().hex}", form)

    return run


for _form in ("csv", "json", "orc"):
    QUERIES[f"roundtrip_{_form}"] = _round(_form)
    ORACLES[f"roundtrip_{_form}"] = "SELECT n_nationkey, n_name, n_regionkey FROM nation"


@op("SELECT l_orderkey, l_linenumber, l_partkey, row_number() OVER (PARTITION BY l_suppkey % 4 ORDER BY l_suppkey, l_orderkey, l_linenumber, l_partkey) AS place FROM lineitem")
def sort_local(s, d):
    """Rows dealt by a key and sorted inside the parts, as a bucketed write needs them; the window needs no other sort."""
    x = T(s, d, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber", "l_partkey").withColumn("part", D("l_suppkey") % 4)
    dealt = x.repartition("part").sortWithinPartitions("part", "l_suppkey", "l_orderkey", "l_linenumber", "l_partkey")
    w = Window.partitionBy("part").orderBy("l_suppkey", "l_orderkey", "l_linenumber", "l_partkey")
    return dealt.select("l_orderkey", "l_linenumber", "l_partkey", F.row_number().over(w).cast("long").alias("place"))
