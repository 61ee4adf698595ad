"""Sources and sinks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table by name; columns and filters that are used reach the Parquet scan."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: An answer of a query writer; rows that don't parse keep their text in _corrupt_record.
ANSWER = "query string, relevant array<struct<node_id:string,grade:int>>, direction string, confidence double, _corrupt_record string"


def parse_answers(df: DataFrame, payload: str = "payload") -> DataFrame:
    return df.withColumn("answer", F.from_json(payload, ANSWER, {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_corrupt_record"}))


def words(text: Column | str) -> Column:
    """Lower-cased runs of letters and digits."""
    text = F.col(text) if isinstance(text, str) else text
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def write_graph(nodes: DataFrame, path: str) -> None:
    """Nodes by tier and kind, so that a search of one level reads only its files."""
    nodes.write.mode("overwrite").partitionBy("tier", "kind").parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by key: later joins on key need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def roundtrip(df: DataFrame, path: str, form: str) -> DataFrame:
    """Write as csv, json or orc and read back with the same schema."""
    options = {"header": "true"} if form == "csv" else {}
    df.write.mode("overwrite").options(**options).format(form).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(form).load(path)


def page_lines(pages: DataFrame) -> DataFrame:
    """(page_id, host, ord, line) of the paragraphs of web pages, scripts, styles and comments removed first."""
    bare = F.regexp_replace("html", r"(?is)<(script|style)\b.*?</\1>|<!--.*?-->", " ")
    parts = F.split(bare, r"(?i)</?(?:p|h1|li|div|article)\b[^>]*>")
    text = F.trim(F.regexp_replace(F.regexp_replace("line", r"<[^>]*>", " "), r"\s+", " "))
    out = pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.posexplode(parts).alias("ord", "line"))
    return out.withColumn("line", text).where("line <> ''")
