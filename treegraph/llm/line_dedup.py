"""Line dedup: an exact set-similarity join of lines; a line goes when an earlier one is the same or similar."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import setjoin as J
from .common import materialise, table, unused

#: Lines of fewer words are left alone: only those without a word. A line of a word or two is one whole-line token.
MIN_WORDS = 1


def removed_lines(rows: DataFrame, *, width: int = 5, percent: int = 80, min_words: int = MIN_WORDS) -> DataFrame:
    """(rk, id, lines): the numbers of the lines to remove from each row of rows(rk, id, text) that loses any.

    Lines are what stands between line feeds; their tokens are shingles of width words, or the whole line if it has fewer.
    Tokens are ordered by rarity; prefix, length and positional filters choose candidates, whole sets decide. A line goes if
    some line before it, by (id, row, line number), nulls first, has a Jaccard similarity of percent / 100 or more.
    """
    members, kept, sets, prefixes = J.prepared(rows, width=width, percent=percent, by_line=True, most=1, min_words=min_words)
    first = materialise(J.verified(J.star(prefixes, percent), sets, percent).select(F.col("a").alias("s")).distinct(), "late")
    later = J.postings(prefixes.join(first, "s", "left_anti"))
    earlier = J.postings(prefixes).join(later.select("token").distinct(), "token", "left_semi")
    a, b = J.side(J.with_prefix(later, prefixes), "a"), J.side(J.with_prefix(earlier, prefixes), "b")
    more = J.verified(J.across(a, b, F.col("firstb") < F.col("firsta"), percent), sets, percent).select(F.col("a").alias("s"))
    late = materialise(first.union(more).distinct().join(kept, "s").select("s1", "s2", F.lit(True).alias("late")), "late")
    repeated = members.where("n > 0").groupBy("s1", "s2").agg(F.min(J.place()).alias("first"), F.count(F.lit(1)).alias("c"))
    marks = repeated.join(late, ["s1", "s2"], "left").where("c > 1 or late")
    hit = members.where("n > 0").join(marks, ["s1", "s2"]).where(F.col("late").isNotNull() | (F.col("first") != J.place()))
    return hit.groupBy("rk", "id").agg(F.array_sort(F.collect_set("line")).alias("lines"))


@F.arrow_udf(T.StringType())
def without(texts: pa.Array, lines: pa.Array) -> pa.Array:
    """Texts without the lines of these numbers; null where there is nothing to remove."""
    out = []
    for text, gone in zip(texts, lines):
        if text.is_valid:
            gone = set(gone.values.to_pylist())
            out.append("\n".join([x for i, x in enumerate(text.as_py().split("\n")) if i not in gone]))
        else:
            out.append(None)
    return pa.array(out, pa.string())


def dedup_lines(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """Every input row with all its columns, text_col without its removed lines, and n_lines and n_removed.

    The lines that stay are joined by line feeds; a text that loses all of them becomes empty. A null text stays null (no
    lines); an empty one has one, empty. Rows that repeat id and text are one document, so that they keep the same lines.
    Blank lines and lines of fewer than min_words words stay. Columns named n_lines or n_removed are replaced.
    """
    gone = materialise(removed_lines(J.with_row_key(docs, id_col, text_col), **options), "removed")
    own = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    rk, id_, lines, r = unused(docs, "__rk", "__id", "__lines", "__r")
    tagged = docs.select(*own, J.row_key(id_col, text_col).alias(rk)).join(gone.toDF(r, id_, lines), (F.col(rk) == F.col(r)) & F.col(id_col).cast("long").eqNullSafe(F.col(id_)), "left")
    old = F.col(text_col)
    new = F.coalesce(without(F.when(F.col(lines).isNotNull(), old), F.col(lines)), old)
    n = F.when(old.isNull(), 0).otherwise(F.length(old) - F.length(F.replace(old, F.lit("\n"), F.lit(""))) + 1).cast("int")
    return tagged.select(*[new.alias(c) if c == text_col else F.col(c) for c in own], n.alias("n_lines"), F.coalesce(F.size(lines), F.lit(0)).alias("n_removed"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text")).select("doc_id", "n_lines", "n_removed", "text")


QUERIES = {"op8_line_dedup": op8_line_dedup}
ORACLES = {
    "op8_line_dedup": r"""
      WITH l AS (SELECT doc_id, unnest(generate_series(1, len(string_split(text, chr(10))))) AS i, unnest(string_split(text, chr(10))) AS line FROM documents WHERE text IS NOT NULL),
      d AS MATERIALIZED (SELECT *, row_number() OVER (ORDER BY doc_id NULLS FIRST, i) AS r, list_filter(regexp_split_to_array(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM l),
      s AS MATERIALIZED (SELECT DISTINCT r, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_transform(generate_series(1, len(w) - 4), lambda i: array_to_string(w[i:i + 4], ' ')) END) AS g FROM d),
      n AS MATERIALIZED (SELECT r, count(*) AS n FROM s GROUP BY r),
      p AS (SELECT a.r AS a, b.r AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.r < b.r GROUP BY a.r, b.r),
      gone AS MATERIALIZED (SELECT DISTINCT b AS r FROM p JOIN n x ON x.r = a JOIN n y ON y.r = b WHERE 100 * c >= 80 * (x.n + y.n - c)),
      kept AS (SELECT doc_id, CAST(count(*) AS INTEGER) AS n_lines, CAST(count(gone.r) AS INTEGER) AS n_removed, coalesce(array_to_string(list(line ORDER BY i) FILTER (gone.r IS NULL), chr(10)), '') AS text FROM d LEFT JOIN gone USING (r) GROUP BY doc_id)
      SELECT doc_id, n_lines, n_removed, text FROM kept UNION ALL SELECT doc_id, 0, 0, NULL FROM documents WHERE text IS NULL"""
}
