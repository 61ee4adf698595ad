"""Benchmark decontamination by spaced seeds, in DataFrame expressions only.

A seed is a fixed mask over consecutive tokens; its hash reads the tokens under the ones and ignores those under the zeros,
so that substitutions there do no harm. Test and training hashes are joined; around each hit the item and the document are
compared token by token on the hit's diagonal.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_ROWS, materialise, table, unused

#: Masks by the least number of compared tokens that they serve. Each group hits every overlap of that many tokens
#: or more that AGREE_PERCENT lets pass: any 4 substitutions in 20 tokens, 3 in 15, 2 in 10, 1 in 8 leave some mask's tokens whole.
MASKS = {15: ("1101111", "11101000011", "1111011"), 10: ("110111", "11001011", "110100011"), 8: ("1111101", "1101111", "10110111")}
#: An overlap is a run of so many aligned tokens (all of the item or the document if it has fewer), of which so many percent agree.
WINDOW, AGREE_PERCENT = 20, 80
#: Items of fewer tokens match word for word alone, those of fewer than ALONE only documents that hold nothing else.
SHORTEST, ALONE = 8, 4
#: Distinct anchor words up to which their set is part of the plan (some MB); beyond it every position is hashed.
ANCHORS = 100_000
#: Parts into which the rows of a hash are dealt where the seeds are too many to be broadcast.
SALTS = 32


def tokens(text: Column) -> Column:
    """Runs of letters and digits, lower-cased; null and wordless texts give an empty array."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def ones(mask: str) -> list[int]:
    return [i for i, c in enumerate(mask) if c == "1"]


def seed_hash(words: Column, start: Column, mask_id: int, mask: str) -> Column:
    return F.xxhash64(F.lit(mask_id), *[F.get(words, start + i) for i in ones(mask)])


def shapes() -> list[tuple[int, str, int, int]]:
    """(number, mask, least, most): masks and the numbers of compared tokens that they serve; those of short items read all of them."""
    out, most = [], 1 << 30
    for least in sorted(MASKS, reverse=True):
        out += [(100 * least + k, m, least, most) for k, m in enumerate(MASKS[least])]
        most = least - 1
    return out + [(n, "1" * n, n, n) for n in range(1, SHORTEST)]


def seed_of(mask_id: int, mask: str):
    def one(i: Column) -> Column:
        words = F.array(*[F.get("item", i + k) for k in ones(mask)])
        longest = F.array_max(F.transform(words, lambda w: F.struct(F.length(w).alias("n"), w.alias("w"))))["w"]
        return F.struct(seed_hash(F.col("item"), i, mask_id, mask).alias("hash"), i.alias("at"), longest.alias("anchor"), F.lit(mask_id).alias("mask"))

    return one


def back_by(k: int):
    return lambda i: i - k


def test_seeds(items: DataFrame) -> DataFrame:
    """(hash, item_id, item, at, anchor, mask, whole) for items(item_id, item): at the seed's first token, anchor its longest word.

    An item of SHORTEST tokens or more has the seeds of its own number of tokens, which whole marks, and those of fewer, for
    documents that are shorter than it.
    """
    size = F.size("item")
    parts = []
    for mask_id, mask, least, most in shapes():
        fits = size >= least if least >= SHORTEST else size == least
        starts = F.when(fits, F.sequence(F.lit(0), size - len(mask))).otherwise(F.array().cast("array<int>"))
        parts.append(F.transform(F.transform(starts, seed_of(mask_id, mask)), lambda s: s.withField("whole", size <= most)))  # noqa: B023
    return items.select("item_id", "item", F.explode(F.flatten(F.array(*parts))).alias("s")).select("item_id", "item", "s.*")


def overlaps(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """(rk, doc_id, item_id, doc_start, agreeing, compared): the best diagonal of each document and item that overlap.

    compared is WINDOW, or the number of the item's or the document's tokens if that is less; doc_start is the document token
    against the item's first; agreeing of the best compared tokens in a row are equal, AGREE_PERCENT or more. No such overlap
    is missed. Items of fewer than SHORTEST tokens match word for word, those of fewer than ALONE only a document that is
    nothing else; a document of fewer than SHORTEST tokens matches only such items. Null and wordless items and texts match
    nothing. rk and the id name a row; rows that repeat id and text are one. Repeated items count once per item id and text.
    """
    items = materialise(benchmark.select(F.col(item_col).cast("long").alias("item_id"), tokens(F.col(item_text_col)).alias("item")).where(F.size("item") > 0).distinct(), "items")
    seeds = materialise(test_seeds(items), "seeds")
    n_seeds = seeds.count()
    bounded = n_seeds <= BROADCAST_ROWS
    # the masks that documents of WINDOW tokens or more need: those of the numbers of tokens that the items have
    present = {r[0] for r in seeds.where("whole").select("mask").distinct().collect()}
    anchors = [r[0] for r in seeds.where("whole").select("anchor").distinct().limit(ANCHORS + 1).collect()]
    rows = docs.select(F.xxhash64(F.col(id_col), F.col(text_col)).alias("rk"), F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    words = rows.select("rk", "doc_id", tokens(F.col("text")).alias("words"))
    size = F.size("words")
    long, every = size >= WINDOW, F.sequence(F.lit(0), size - 1)
    none = F.array().cast("array<int>")

    def at_starts(starts: Column, mask_id: int, mask: str) -> Column:
        good = F.filter(starts, lambda i: (i >= 0) & (i + len(mask) <= F.size("words")))
        return F.transform(good, lambda i: F.struct(i.alias("start"), seed_hash(F.col("words"), i, mask_id, mask).alias("hash")))

    # No filter on words or on what is made of them: it would be pushed below, where words are split anew for each look.
    if len(anchors) <= ANCHORS:  # every hit covers its seed's anchor: only windows that hold one can match
        words = words.withColumn("found", F.filter(every, lambda i: F.get("words", i).isin(anchors)) if anchors else none)
        near = lambda m: F.array_distinct(F.flatten(F.array(*[F.transform("found", back_by(k)) for k in ones(m)])))
    else:
        near = lambda m: every
    hashes = []
    for mask_id, mask, least, _ in shapes():
        short = ~long & (size >= least if least >= ALONE else size == least) & (size > 0)
        wanted = F.when(long, near(mask)) if mask_id in present and least >= ALONE else F.when(long, none)
        hashes.append(at_starts(wanted.when(short, every).otherwise(none), mask_id, mask))
    train = words.select("rk", "doc_id", F.explode_outer(F.flatten(F.array(*hashes))).alias("h")).where(F.col("h").isNotNull()).select("rk", "doc_id", "h.start", "h.hash")
    test = seeds.select("hash", "item_id", "at").distinct()
    if bounded:
        hits = train.join(F.broadcast(test), "hash")
    else:  # a hash that a third of all documents have is dealt out
        train = train.withColumn("salt", F.pmod(F.xxhash64("rk", "start"), F.lit(SALTS)).cast("int"))
        hits = train.join(test.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["hash", "salt"])
    hits = materialise(hits.select("rk", "doc_id", "item_id", (F.col("start") - F.col("at")).alias("doc_start")).distinct(), "hits")
    few = hits.select("rk").distinct()
    few = F.broadcast(few) if hits.count() <= BROADCAST_ROWS else few
    again = rows.join(few, "rk", "left_semi").select("rk", "doc_id", tokens(F.col("text")).alias("words")).dropDuplicates(["rk", "doc_id"])
    both = hits.withColumnRenamed("doc_id", "d").join(again.withColumnRenamed("rk", "r"), (F.col("rk") == F.col("r")) & F.col("d").eqNullSafe(F.col("doc_id"))).drop("r", "d")
    both = both.join(F.broadcast(items) if bounded else items, "item_id")
    n, size = F.size("item"), F.size("words")
    equal = F.transform("item", lambda w, i: F.coalesce((F.get("words", F.col("doc_start") + i) == w) & (F.col("doc_start") + i >= 0), F.lit(False)).cast("int"))
    compared = F.when(n < SHORTEST, n).otherwise(F.least(n, size, F.lit(WINDOW)))
    run = F.least(F.col("compared"), n)
    best = F.array_max(F.transform(F.sequence(F.lit(0), n - run), lambda i: F.aggregate(F.slice("equal", i + 1, run), F.lit(0), lambda a, x: a + x)))
    both = both.where((n < SHORTEST) | (size >= SHORTEST)).where((n >= ALONE) | (size == n))
    both = both.select("rk", "doc_id", "item_id", "doc_start", compared.alias("compared"), equal.alias("equal"), "item")
    top = F.max(F.struct(best.alias("agreeing"), (-F.col("doc_start")).alias("back"))).alias("top")
    both = both.groupBy("rk", "doc_id", "item_id", "compared").agg(top)
    enough = F.when(F.col("compared") < SHORTEST, 100).otherwise(AGREE_PERCENT)
    return both.where(F.col("top.agreeing") * 100 >= F.col("compared") * enough).select("rk", "doc_id", "item_id", (-F.col("top.back")).alias("doc_start"), "top.agreeing", "compared")


def contaminated(docs: DataFrame, benchmark: DataFrame, **columns) -> DataFrame:
    """One row per document that holds a passage of an item: (rk, doc_id, n_items, items, overlap)."""
    found = overlaps(docs, benchmark, **columns)
    return found.groupBy("rk", "doc_id").agg(F.countDistinct("item_id").alias("n_items"), F.array_join(F.array_sort(F.collect_set("item_id")), ",").alias("items"), F.max(F.col("agreeing") / F.col("compared")).alias("overlap"))


def remove_contaminated(docs: DataFrame, benchmark: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", **columns) -> DataFrame:
    """The rows of docs, all columns, but those that hold a passage of an item."""
    rk, r, id_ = unused(docs, "__rk", "__r", "__id")
    bad = materialise(contaminated(docs, benchmark, id_col=id_col, text_col=text_col, **columns).select(F.col("rk").alias(r), F.col("doc_id").alias(id_)), "contaminated")
    bad = F.broadcast(bad) if bad.count() <= BROADCAST_ROWS else bad
    same = (F.col(rk) == F.col(r)) & F.col(id_col).cast("long").eqNullSafe(F.col(id_))
    return docs.withColumn(rk, F.xxhash64(F.col(id_col), F.col(text_col))).join(bad, same, "left_anti").drop(rk)


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).select("doc_id", "n_items", "items", F.round("overlap", 6).alias("overlap"))


QUERIES = {"op6_decontamination": op6_decontamination}
#: Every overlap holds three equal tokens in a row, or is of a short item: all diagonals of those are compared.
ORACLES = {
    "op6_decontamination": r"""
      WITH cut AS (SELECT regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+') AS w, * EXCLUDE (text), text FROM (SELECT DISTINCT doc_id, text FROM documents)),
      d AS MATERIALIZED (SELECT doc_id, list_filter(w, lambda x: x <> '') AS w, row_number() OVER () AS r FROM cut),
      it AS MATERIALIZED (SELECT DISTINCT item_id, list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS w FROM benchmark),
      items AS MATERIALIZED (SELECT item_id, w, row_number() OVER () AS q FROM it WHERE len(w) > 0),
      dg AS MATERIALIZED (SELECT r, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT r, w, unnest(generate_series(1, len(w) - 2)) AS i FROM d WHERE len(w) > 2)),
      ig AS MATERIALIZED (SELECT q, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] AS g FROM (SELECT q, w, unnest(generate_series(1, len(w) - 2)) AS i FROM items WHERE len(w) > 2)),
      ds AS (SELECT r, w, unnest(generate_series(1, len(w))) AS i FROM d), short AS (SELECT q, w FROM items WHERE len(w) < 3),
      diag AS (SELECT DISTINCT r, q, dg.i - ig.i AS s FROM dg JOIN ig USING (g) UNION SELECT r, q, ds.i - 1 FROM ds JOIN short ON ds.w[ds.i] = short.w[1]),
      x AS (SELECT r, q, doc_id, item_id, len(items.w) AS n, len(d.w) AS m, list_transform(generate_series(1, len(items.w)), lambda j: CASE WHEN j + s >= 1 AND j + s <= len(d.w) AND d.w[CASE WHEN j + s >= 1 THEN j + s ELSE 1 END] = items.w[j] THEN 1 ELSE 0 END) AS eq FROM diag JOIN d USING (r) JOIN items USING (q)),
      y AS (SELECT *, CASE WHEN n < 8 THEN n ELSE least(n, m, 20) END AS compared FROM x WHERE (n < 8 OR m >= 8) AND (n >= 4 OR m = n)),
      z AS (SELECT r, doc_id, item_id, compared, max(list_max(list_transform(generate_series(1, n - least(compared, n) + 1), lambda i: list_sum(eq[i:i + least(compared, n) - 1])))) AS agreeing FROM y GROUP BY ALL),
      hit AS (SELECT * FROM z WHERE agreeing * 100 >= compared * CASE WHEN compared < 8 THEN 100 ELSE 80 END)
      SELECT doc_id, count(DISTINCT item_id) AS n_items, array_to_string(list_sort(list_distinct(list(item_id))), ',') AS items, round(max(agreeing / compared), 6) AS overlap FROM hit GROUP BY r, doc_id"""
}
