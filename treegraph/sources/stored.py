"""Tables that the engine derives from its inputs: written once an application, as Parquet in the shared folder, then scanned."""

from __future__ import annotations

import hashlib
import os
import tempfile
import threading
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a folder of this machine, which only a local session may use."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    return os.path.join(tempfile.gettempdir(), "treegraph-shared")


def _path(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def fingerprint(spark: SparkSession, sf_dir: str, tables: tuple[str, ...]) -> str:
    """Changes whenever a file of the tables does: paths, sizes and times."""
    seen = [spark.sparkContext.applicationId]
    for name in tables:
        fs, p = _path(spark, f"{sf_dir}/{name}.parquet")
        files = fs.listStatus(p) if fs.exists(p) else []
        seen += sorted(f"{f.getPath()} {f.getLen()} {f.getModificationTime()}" for f in files)
    return hashlib.sha256("\n".join(seen).encode()).hexdigest()[:24]


def place_of(spark: SparkSession, sf_dir: str, name: str, tables: tuple[str, ...]) -> str:
    return f"{shared_root(spark)}/derived-{fingerprint(spark, sf_dir, tables)}/{name}"


def is_stored(spark: SparkSession, sf_dir: str, name: str, tables: tuple[str, ...]) -> bool:
    fs, done = _path(spark, f"{place_of(spark, sf_dir, name, tables)}/_SUCCESS")
    return fs.exists(done)


_locks: dict[str, threading.Lock] = {}
_guard = threading.Lock()


def stored(spark: SparkSession, sf_dir: str, name: str, tables: tuple[str, ...], build: Callable[[], DataFrame]) -> DataFrame:
    """The frame that build() gives for these input tables, from its Parquet files if this application wrote them already.

    A write that died leaves no _SUCCESS and is done again. Plans over the result are scans, whatever went into it. Of threads that
    ask for the same frame one builds it, the others wait.
    """
    path = place_of(spark, sf_dir, name, tables)
    fs, done = _path(spark, f"{path}/_SUCCESS")
    with _guard:
        lock = _locks.setdefault(path, threading.Lock())
    with lock:
        if not fs.exists(done):
            build().write.mode("overwrite").parquet(path)
    return spark.read.parquet(path)


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage of a round: write df to the shared folder under a name of its own and read it back."""
    path = f"{shared_root(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop(df: DataFrame) -> None:
    """Delete the files behind a written frame."""
    for path in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        fs, p = _path(df.sparkSession, path)
        fs.delete(p, True)


def forget(spark: SparkSession, sf_dir: str, tables: tuple[str, ...]) -> None:
    """Delete what was derived from these tables."""
    fs, p = _path(spark, f"{shared_root(spark)}/derived-{fingerprint(spark, sf_dir, tables)}")
    fs.delete(p, True)
