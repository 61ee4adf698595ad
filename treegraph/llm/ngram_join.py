"""N-gram Jaccard join: documents linked by word shingles, with prefixes that adapt to what their candidates would cost."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import setjoin as J
from .common import components, materialise, maybe_broadcast, table, union_all, unused

#: Largest number of shared prefix tokens that a document may ask for.
MOST_MATCHES = 8


def similar_groups(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", width: int = 5, percent: int = 80) -> DataFrame:
    """One row per input row: (rk, doc_id, n_shingles, component_id, first).

    Two documents link when the Jaccard similarity of their sets of width-word shingles is at least percent / 100; a
    component is what links reach, named by its smallest id; first marks its member of that id. Documents of fewer words
    have one shingle, their words; null, empty and wordless texts have none, link with nothing and are first. rk is a hash
    of id and text: rows that repeat both count as one document but each gets its row; equal sets are linked without
    comparison. A null id names a component only if all its ids are null. Other columns are ignored. An empty table gives
    an empty result.
    """
    rows = J.with_row_key(docs, id_col, text_col)
    members, kept, sets, prefixes = J.prepared(rows, width=width, percent=percent, by_line=False, most=MOST_MATCHES)
    first = materialise(J.verified(J.star(prefixes, percent), sets, percent), "links")
    group = components(first.toDF("u", "v"))
    known = prefixes.join(group.select(F.col("node").alias("s"), "label"), "s", "left").withColumn("label", F.coalesce("label", "s"))
    known = J.postings(known, "label")
    mixed = known.groupBy("token").agg((F.min("label") != F.max("label")).alias("mixed")).where("mixed").select("token")
    known = materialise(J.with_prefix(known.join(mixed, "token", "left_semi"), prefixes), "postings")
    a, b = J.side(known, "a", "label"), J.side(known, "b", "label")
    second = materialise(J.verified(J.across(a, b, F.col("labela") < F.col("labelb"), percent), sets, percent), "links")
    group = components(union_all([first, second]).toDF("u", "v"))
    lead = F.min(F.struct(F.col("id").isNull().alias("none"), "id", "rk")).alias("lead")
    linked = group.select(F.col("node").alias("s"), "label").join(kept, "s").select("s1", "s2", "label")
    by_set = materialise(members.where("n > 0").groupBy("s1", "s2").agg(lead).join(linked, ["s1", "s2"], "left"), "sets-named")
    smallest = by_set.where("label is not null").groupBy("label").agg(F.min("lead").alias("least"))
    lead = F.coalesce("least", "lead")
    by_set = by_set.join(smallest, "label", "left").select("s1", "s2", lead["id"].alias("component_id"), lead["rk"].alias("lead_rk"))
    empty = F.col("n") == 0
    return members.join(by_set, ["s1", "s2"], "left").select(
        "rk",
        F.col("id").alias("doc_id"),
        F.col("n").cast("long").alias("n_shingles"),
        F.when(empty, F.col("id")).otherwise(F.col("component_id")).alias("component_id"),
        F.when(empty, True).otherwise((F.col("rk") == F.col("lead_rk")) & F.col("id").eqNullSafe(F.col("component_id"))).alias("first"),
    )


def keep_first(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The rows of docs, all columns, that are the first of their group; of rows that repeat id and text one stays."""
    groups = materialise(similar_groups(docs, id_col=id_col, text_col=text_col, **options).select("rk", "doc_id", "first"), "groups")
    rk, r, id_ = unused(docs, "__rk", "__r", "__id")
    same = (F.col(rk) == F.col(r)) & F.col(id_col).cast("long").eqNullSafe(F.col(id_))
    name = groups.select(F.col("rk").alias(r), F.col("doc_id").alias(id_), "first")
    gone = name.where(~F.col("first")).select(r, id_).distinct()
    more = materialise(name.groupBy(r, id_).count().where("count > 1").select(r, id_), "repeated")
    kept = docs.withColumn(rk, J.row_key(id_col, text_col)).join(maybe_broadcast(gone), same, "left_anti")
    if not more.isEmpty():
        more = maybe_broadcast(more)
        kept = kept.join(more, same, "left_anti").unionByName(kept.join(more, same, "left_semi").dropDuplicates([rk, id_col]))
    return kept.drop(rk)


def op9_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_groups(table(spark, sf_dir, "documents")).select("doc_id", "n_shingles", "component_id")


QUERIES = {"op9_ngram_jaccard_join": op9_ngram_jaccard_join}
ORACLES = {
    "op9_ngram_jaccard_join": r"""
      WITH RECURSIVE d AS MATERIALIZED (SELECT doc_id, row_number() OVER () AS r, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents),
      s AS MATERIALIZED (SELECT DISTINCT r, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(generate_series(1, len(w) - 4), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g FROM d),
      n AS MATERIALIZED (SELECT r, count(*) AS n FROM s GROUP BY r),
      p AS (SELECT a.r AS a, b.r AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.r <> b.r GROUP BY a.r, b.r),
      l AS MATERIALIZED (SELECT a, b FROM p JOIN n x ON x.r = a JOIN n y ON y.r = b WHERE 100 * c >= 80 * (x.n + y.n - c)),
      reach(a, b) AS (SELECT r, r FROM d UNION SELECT reach.a, l.b FROM reach JOIN l ON l.a = reach.b),
      comp AS (SELECT reach.a AS r, min(d.doc_id) AS component_id FROM reach JOIN d ON d.r = reach.b GROUP BY reach.a)
      SELECT doc_id, coalesce(n, 0) AS n_shingles, component_id FROM d JOIN comp USING (r) LEFT JOIN n USING (r)"""
}
