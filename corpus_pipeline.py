"""A cleaning pipeline over documents: five stages, each written as Parquet and read again as the next one's documents.

Null and wordless texts have no language and go in the first stage. Rows that repeat id and text are one document: their lines
stay alike and one of them is kept. Columns beside those named pass through the filtering stages unchanged; an empty table
gives an empty result with the same columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from treegraph.llm import bpe, decontaminate, language, line_dedup, ngram_join
from treegraph.llm.common import materialise, table

#: A document that takes so many times the phrases of ordinary text of its language is in none of the learned ones.
STRANGE = 3.0


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without a letter or in no learned language; fill in a null lang by the prediction."""
    found = language.identify(docs, language.fit(docs)).where((F.col("lang_pred") != language.UNKNOWN) & (F.col("strange") < STRANGE))
    return found.select(*[F.coalesce("lang", "lang_pred").alias("lang") if c == "lang" else F.col(c) for c in docs.columns])


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Remove lines that repeat earlier ones; a document left without a word goes. n_chars is counted anew."""
    clean = line_dedup.dedup_lines(docs).where(F.col("text").rlike(r"\S"))
    return clean.select(*[F.length("text").cast("long").alias(c) if c == "n_chars" else F.col(c) for c in docs.columns])


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the first document of each group linked by word shingles."""
    return ngram_join.keep_first(docs)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents that hold a passage of a benchmark item."""
    return decontaminate.remove_contaminated(docs, table(spark, sf_dir, "benchmark"))


def tokenise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of each text, their number, and whether decoding gives the text back."""
    coded = bpe.decode_ids(bpe.encode_texts(docs))
    same = F.col("decoded") == F.coalesce("text", F.lit("")).cast("binary")
    return coded.select("doc_id", "lang", "source", "n_chars", F.size("ids").cast("long").alias("n_tokens"), "ids", same.alias("round_trip"))


STAGES = [
    ("language ID", identify_language),
    ("line dedup", drop_repeated_lines),
    ("n-gram Jaccard join", drop_near_copies),
    ("benchmark decontamination", drop_contaminated),
    ("byte-level BPE", tokenise),
]

ORACLE_SQL = None  # cross-parsing has no SQL; tests/llm/test_pipeline.py holds the other stages against brute force and the whole against planted rows


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; what each keeps is written and read again."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
