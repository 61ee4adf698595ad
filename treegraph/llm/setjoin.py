"""The exact set-similarity join behind line dedup and the n-gram Jaccard join.

Three lossless steps over distinct token sets (equal sets are one, named by a 128-bit sum of scrambled tokens):

1. Every set shows its first tokens in hash order, a prefix long enough that any partner at the threshold must share a
   stated number of them. Sets whose prefix holds fewer tokens that any other set shows as well have no partner and go.
2. The few that stay show all their tokens; counted document frequencies give the rarity order, and prefixes in that order
   (see `rare_prefixes`) become the postings.
3. Postings give candidates, which intersect their whole sets. To keep a group of thousands of near copies from turning
   into all its pairs, the members of a posting list meet its first member before they meet each other (`star`, `across`).
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import shingles as S
from .common import BROADCAST_ROWS, drop_table, materialise

#: Share of extra tokens in the prefixes of step 1: one more needed match for each so many tokens of a set.
EXTRA = 16
#: Members of a posting list that one task compares with all others; longer lists are dealt out in parts.
BLOCK = 1_024


def must_share(n, percent: int):
    """Tokens that a partner at the threshold shares at least with a set of n."""
    return -(-(percent * n) // 100)


def row_key(id_col: str, text_col: str) -> Column:
    """A 64-bit hash of a row's id and text; with the id beside it, the name of the row: only rows of one id could be confused."""
    return F.xxhash64(F.col(id_col), F.col(text_col))


def with_row_key(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(rk, id, text): rk and id name a row; rows that repeat id and text are one document."""
    return docs.select(row_key(id_col, text_col).alias("rk"), F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))


def signatures(rows: DataFrame, *, width: int, percent: int, by_line: bool, min_words: int = 1, full: bool = False) -> DataFrame:
    """(rk, id, line, n, s1, s2, head): each item's set size and name, and its first tokens in hash order (all if full).

    Items of fewer than min_words words count as empty.
    """

    def run(it):
        for batch in it:
            for at, x in S.batches(batch.column(2), width, by_line):
                n = np.where(x.words >= min_words, x.size, 0)
                if full:
                    length = n
                else:
                    length = np.minimum(n, n - must_share(n, percent) + 1 + n // EXTRA) * (n > 0)
                offsets, values = S.take_heads(x, length, full)
                pick = pa.array(at + x.row)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(pick), batch.column(1).take(pick), pa.array(x.line, pa.int32()), pa.array(n, pa.int32()), pa.array(x.s1), pa.array(x.s2), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(values))],
                    ["rk", "id", "line", "n", "s1", "s2", "head"],
                )

    return rows.select("rk", "id", "text").mapInArrow(run, "rk long, id long, line int, n int, s1 long, s2 long, head array<long>")


def place(id_: str = "id") -> Column:
    """The order of items: by id (nulls first), then row, then line."""
    return F.struct(F.col(id_).isNotNull().alias("has_id"), F.coalesce(F.col(id_), F.lit(0)).alias("id"), F.col("rk"), F.col("line"))


def representatives(sig: DataFrame) -> DataFrame:
    """One row per distinct set: (s1, s2, n, head, first), first the place of its earliest item."""
    return sig.where("n > 0").groupBy("s1", "s2").agg(F.min(place()).alias("first"), F.first("n").alias("n"), F.first("head").alias("head"))


def with_frequency(token: DataFrame, owner: str) -> DataFrame:
    """Rows of token(token, owner, ...) whose token has more than one row, with the number df of its rows.

    One shuffle by token serves the count and the join. A set shows a token once and many tokens, so that no token has more
    than a small share of the rows. Counting owner keeps both sides' columns, and so their exchange, the same.
    """
    dealt = token.where(F.col(owner).isNotNull() & F.col("token").isNotNull()).repartition("token")
    df = dealt.groupBy("token").agg(F.count(owner).alias("df")).where("df > 1")
    return dealt.join(df.hint("shuffle_hash"), "token")


def survivors(reps: DataFrame, percent: int) -> DataFrame:
    """Step 1: (s, s1, s2, n, first) of the sets whose hash-order prefix is shared enough to leave room for a partner.

    The frame is to be written before it is used: s numbers its rows. Heads show the first bits of tokens, so that tokens may
    seem to be shared that are not: more sets stay, none is lost.
    """
    token = reps.select("s1", F.explode("head").alias("token"))  # sets of one s1 are counted together: at worst too many stay
    seen = with_frequency(token, "s1").groupBy("s1").agg(F.count(F.lit(1)).alias("shared"))
    least = 1 + F.floor(F.ceil(F.col("n") * percent / 100) / EXTRA)  # what the smallest possible partner asks for
    own = reps.select("s1", "s2", "n", "first").join(seen, "s1").where(F.col("shared") >= least)
    return own.select(F.monotonically_increasing_id().alias("s"), "s1", "s2", "n", "first")


def whole_sets(rows: DataFrame, kept: DataFrame, *, width: int, percent: int, by_line: bool) -> DataFrame:
    """(s, n, first, tokens) of the sets in kept, all bits of their tokens."""
    few = kept.count() <= BROADCAST_ROWS  # some 60 bytes a row
    hint = F.broadcast if few else (lambda d: d)
    holders = kept.select(F.col("first.rk").alias("rk")).distinct()
    sig = signatures(rows.join(hint(holders), "rk", "left_semi"), width=width, percent=percent, by_line=by_line, full=True)
    named = kept.select("s", "s1", "s2", "first")
    sig = sig.join(hint(named), ["s1", "s2"]).where(place() == F.col("first"))
    return sig.select("s", "n", "first", F.col("head").alias("tokens")).dropDuplicates(["s"])


def rare_prefixes(sets: DataFrame, percent: int, most: int = 1) -> DataFrame:
    """Step 2: (s, n, first, need, alone, prefix), prefixes in rarity order (document frequency, then token).

    need is how many prefix tokens a candidate must share: the number l whose prefix of n - must_share + l tokens has the
    least estimated cost, the postings it writes plus the comparison of the at most postings / l sets met l times.
    With most = 1 it is plain prefix filtering. The alone tokens that no other set has come first and are left out of prefix.
    Sets whose first prefix holds no shared token are left out: they have no partner. prefix has the tokens and, of each, the
    parts into which its posting list is dealt.
    """
    seen = with_frequency(sets.select("s", F.explode("tokens").alias("token")), "s")
    rare = seen.groupBy("s").agg(F.array_sort(F.collect_list(F.struct("df", "token"))).alias("rare")).join(sets.select("s", "n", "first"), "s")
    spare = (F.col("n") - F.ceil(F.col("n") * percent / 100)).cast("int")
    rare = rare.withColumns({"alone": (F.col("n") - F.size("rare")).cast("int"), "spare": spare})
    rare = rare.where(F.col("spare") + 1 > F.col("alone"))  # else the first prefix holds no shared token
    until = lambda l: F.greatest(F.lit(0), F.col("spare") + l - F.col("alone"))

    def cost(l: Column) -> Column:
        met = F.aggregate(F.slice("rare", F.lit(1), until(l)), F.lit(0.0), lambda a, x: a + x["df"] - 1)
        return F.struct((met * (1 + F.col("n") / 8 / l)).alias("cost"), l.alias("l"))

    need = F.lit(1) if most == 1 else F.array_min(F.transform(F.sequence(F.lit(1), F.lit(most)), cost))["l"].cast("int")
    rare = rare.withColumn("need", need)
    rare = rare.withColumn("prefix", F.transform(F.slice("rare", F.lit(1), until(F.col("need"))), lambda x: F.struct(x["token"].alias("token"), F.ceil(x["df"] / BLOCK).cast("int").alias("parts"))))
    return rare.select("s", "n", "first", "need", "alone", "prefix")


def postings(prefixes: DataFrame, *more: str) -> DataFrame:
    """(token, parts, s, n, first, pos, need) of every prefix token; pos counts from 1 over all tokens of the set."""
    out = prefixes.select("s", "n", "first", "need", "alone", *more, F.posexplode("prefix").alias("k", "t"))
    return out.select("t.token", "t.parts", "s", "n", "first", (F.col("alone") + F.col("k") + 1).alias("pos"), "need", *more)


def with_prefix(rows: DataFrame, prefixes: DataFrame) -> DataFrame:
    """Postings with their set's prefix, which travels only with those that are left to compare."""
    return rows.join(prefixes.select("s", "prefix"), "s")


def lengths_fit(a: str, b: str, percent: int) -> Column:
    return (F.col(a) * percent <= F.col(b) * 100) & (F.col(b) * percent <= F.col(a) * 100)


def overlap_needed(a: str, b: str, percent: int) -> Column:
    return F.ceil((F.col(a) + F.col(b)) * percent / (100 + percent))


def verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose whole sets reach the threshold."""
    one = sets.select(F.col("s").alias("a"), F.col("tokens").alias("ta"), F.col("n").alias("na"))
    two = sets.select(F.col("s").alias("b"), F.col("tokens").alias("tb"), F.col("n").alias("nb"))
    both = pairs.join(one, "a").join(two, "b").withColumn("o", F.size(F.array_intersect("ta", "tb")))
    return both.where(F.col("o") * 100 >= (F.col("na") + F.col("nb") - F.col("o")) * percent).select("a", "b")


def star(prefixes: DataFrame, percent: int) -> DataFrame:
    """Candidates (a, b): b the earliest set of a posting list, a any later one of fitting length."""
    rows = postings(prefixes)
    head = rows.groupBy("token").agg(F.min(F.struct("first", "s", "n")).alias("h"), F.count(F.lit(1)).alias("c")).where("c > 1").select("token", F.col("h.s").alias("b"), F.col("h.n").alias("nb"))
    return rows.join(head, "token").where("s <> b").where(lengths_fit("n", "nb", percent)).select(F.col("s").alias("a"), "b").distinct()


def across(left: DataFrame, right: DataFrame, condition: Column, percent: int) -> DataFrame:
    """Candidates (a, b) of two posting tables (columns suffixed a and b), each pair once, where its first shared prefix token is.

    Besides length, what is left behind the positions of that token and the number of shared prefix tokens must leave room
    for the overlap that the threshold asks for. need of the one that needs fewer is a bound for both.
    """
    met = F.array_intersect("prefixa", "prefixb")
    asked = overlap_needed("na", "nb", percent)
    room = 1 + F.least(F.col("na") - F.col("posa"), F.col("nb") - F.col("posb"))
    behind = F.greatest(*[F.ceil(F.col(n) * percent / 100) - F.col(need) for n, need in (("na", "needa"), ("nb", "needb"))])
    fits = condition & lengths_fit("na", "nb", percent) & (room >= asked)
    fits &= (F.get(met, F.lit(0))["token"] == F.col("right_token")) & (F.size(met) >= F.least("needa", "needb")) & (F.size(met) + behind >= asked)
    left = left.withColumn("part", F.pmod(F.xxhash64("a"), F.col("parts")).cast("int")).drop("parts")
    right = right.withColumn("right_part", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).drop("parts").withColumnRenamed("token", "right_token")
    return left.join(right, (F.col("token") == F.col("right_token")) & (F.col("part") == F.col("right_part")) & fits).select("a", "b")


def side(rows: DataFrame, tag: str, *more: str) -> DataFrame:
    return rows.select("token", "parts", F.col("s").alias(tag), *[F.col(c).alias(c + tag) for c in ("n", "first", "pos", "need", "prefix", *more)])


def prepared(rows: DataFrame, *, width: int, percent: int, by_line: bool, most: int, min_words: int = 1) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(members, kept, sets, prefixes) as written tables; members: (rk, id, line, n, s1, s2) of every item, kept: s by (s1, s2)."""
    sig = materialise(signatures(rows, width=width, percent=percent, by_line=by_line, min_words=min_words), "signatures")
    members = materialise(sig.drop("head"), "members")
    reps = materialise(representatives(sig), "representatives")
    drop_table(sig)
    kept = materialise(survivors(reps, percent), "survivors")
    drop_table(reps)
    sets = materialise(whole_sets(rows, kept, width=width, percent=percent, by_line=by_line), "sets")
    prefixes = materialise(rare_prefixes(sets, percent, most), "prefixes")
    return members, kept.select("s", "s1", "s2"), sets, prefixes
