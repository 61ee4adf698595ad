"""Quality classifier: random Fourier features over document statistics, ridge scores, isotonic calibration."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, remainder, table

#: About so many labelled rows, chosen by a hash of the id, are learned from; a quarter of them calibrates.
SAMPLE_ROWS = 40_000
FEATURES, RIDGE, SEED, PARTS = 512, 1e-3, 7, 16

_byte = np.arange(256)
_CLASSES = {
    "lower": (_byte >= 97) & (_byte <= 122),
    "upper": (_byte >= 65) & (_byte <= 90),
    "digit": (_byte >= 48) & (_byte <= 57),
    "high": _byte >= 128,
    "blank": (_byte == 32) | (_byte == 9),
    "feed": (_byte == 10) | (_byte == 13),
    "stop": np.isin(_byte, [ord(c) for c in ".,;:"]),
    "cry": np.isin(_byte, [ord(c) for c in "!?"]),
    "mark": np.isin(_byte, [ord(c) for c in "#$%&*+=<>@^_~|\\/{}[]"]),
    "quote": np.isin(_byte, [ord(c) for c in "'\"()-"]),
    "control": (_byte < 32) & ~np.isin(_byte, [9, 10, 13]),
}
NAMES = [*_CLASSES, "log_bytes", "log_words", "word_length", "word_spread", "distinct", "top_word", "distinct_lines", "line_words", "ended", "long_word", "capitals"]
_MATRIX = np.array(list(_CLASSES.values()), dtype=np.float64).T


def statistics(text: str | None) -> np.ndarray:
    """What is known of a whole text: shares of kinds of bytes, lengths, repetition. A null text is empty."""
    raw = (text or "").encode("utf-8", "replace")
    out = np.zeros(len(NAMES))
    if not raw:
        return out
    shares = np.bincount(np.frombuffer(raw, dtype=np.uint8), minlength=256) @ _MATRIX / len(raw)
    k = len(_CLASSES)
    out[:k] = np.sqrt(shares)
    out[k] = np.log1p(len(raw))
    words = raw.split()
    if words:
        sizes = np.fromiter(map(len, words), dtype=np.float64, count=len(words))
        counts: dict[bytes, int] = {}
        for w in words:
            counts[w] = counts.get(w, 0) + 1
        lines = [x for x in raw.split(b"\n") if x.strip()]
        ended = sum(x.rstrip()[-1:] in b".!?" for x in lines) / len(lines)
        upper = sum(w[:1].isupper() for w in words) / len(words)
        out[k + 1 :] = [np.log1p(len(words)), np.log1p(sizes.mean()), np.log1p(sizes.std()), len(counts) / len(words) ** 0.9, max(counts.values()) / len(words), len(set(lines)) / len(lines), np.log1p(len(words) / len(lines)), ended, np.log1p(sizes.max()), upper]
    return out


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the array stats in place of the text."""

    @F.arrow_udf("array<double>")
    def run(texts: pa.Array) -> pa.Array:
        return pa.array([statistics(t.as_py()).tolist() for t in texts], pa.list_(pa.float64()))

    return docs.withColumn("stats", run(F.col(text_col))).drop(text_col)


def _matrix(column: pa.Array) -> np.ndarray:
    return np.array(column.to_pylist(), dtype=np.float64).reshape(len(column), -1)


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    omega: np.ndarray
    phase: np.ndarray
    weight: np.ndarray
    knots: np.ndarray
    levels: np.ndarray

    def features(self, x: np.ndarray) -> np.ndarray:
        z = np.cos(np.clip((x - self.mean) / self.scale, -8, 8) @ self.omega + self.phase) * np.sqrt(2 / len(self.phase))
        return np.concatenate([z, np.ones((len(x), 1))], axis=1)

    def raw(self, x: np.ndarray) -> np.ndarray:
        return self.features(x) @ self.weight

    def score(self, x: np.ndarray) -> np.ndarray:
        return np.clip(np.interp(self.raw(x), self.knots, self.levels), 0, 1)


def isotonic(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Pooled adjacent violators: knots (means of x in a pool) and levels (means of y), both ascending."""
    order = np.argsort(x, kind="stable")
    pools: list[list[float]] = []  # sum of x, sum of y, number
    for a, b in zip(x[order].tolist(), y[order].tolist()):
        pools.append([a, b, 1])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            last = pools.pop()
            pools[-1] = [p + q for p, q in zip(pools[-1], last)]
    return np.array([p[0] / p[2] for p in pools]), np.array([p[1] / p[2] for p in pools])


def _partials(rows: DataFrame, per_batch, width: int) -> np.ndarray:
    """Sum over partitions of what per_batch(x, y) gives, a flat array of width numbers; each partition sends one row."""

    def run(it):
        total = np.zeros(width)
        for b in it:
            if b.num_rows:
                total += per_batch(_matrix(b.column(0)), np.array(b.column(1).to_pylist(), dtype=np.float64))
        yield pa.RecordBatch.from_arrays([pa.array([total.tolist()], pa.list_(pa.float64()))], ["v"])

    parts = rows.select("stats", "y").coalesce(PARTS).mapInArrow(run, "v array<double>").collect()
    return np.sum([r[0] for r in parts], axis=0) if parts else np.zeros(width)


def fit(labelled: DataFrame) -> Model | None:
    """Learn from labelled(stats, y, h), y 0 or 1 and h a hash that deals rows to learning and calibration; None without rows."""
    learn, tune = labelled.where(F.pmod("h", F.lit(4)) != 0), labelled.where(F.pmod("h", F.lit(4)) == 0)
    d = len(NAMES)
    m = _partials(learn, lambda x, y: np.concatenate([[len(x), y.sum()], x.sum(0), (x * x).sum(0)]), 2 + 2 * d)
    n = m[0]
    if not n:
        return None
    mean = m[2 : 2 + d] / n
    scale = np.sqrt(np.maximum(m[2 + d :] / n - mean**2, 1e-6))
    rng = np.random.default_rng(SEED)
    model = Model(mean, scale, rng.normal(size=(d, FEATURES)) / np.sqrt(d), rng.uniform(0, 2 * np.pi, FEATURES), np.zeros(FEATURES + 1), np.zeros(1), np.array([m[1] / n]))
    k = FEATURES + 1

    def normal(x: np.ndarray, y: np.ndarray) -> np.ndarray:
        z = model.features(x)
        return np.concatenate([(z.T @ z).ravel(), z.T @ y])

    s = _partials(learn, normal, k * k + k)
    gram = s[: k * k].reshape(k, k) / n
    model.weight = np.linalg.solve(gram + RIDGE * np.eye(k), s[k * k :] / n)
    rows = tune.select("stats", "y").collect()  # bounded by SAMPLE_ROWS
    if rows:
        x = np.array([r[0] for r in rows])
        model.knots, model.levels = isotonic(model.raw(x), np.array([float(r[1]) for r in rows]))
    return model


def score_quality(docs: DataFrame, labels: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", learn_from=None, sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """(id_col, score, predicted) for every row of docs: the chance of label 1 by its whole text alone.

    learn_from is a condition on id_col for rows that may be learned from (default: all). Labels that are null or whose
    document is missing are left out; a document with several labels counts with each. Null and empty texts have all
    statistics 0 and are scored like any other. Without any label every score is 0.5. Rows that repeat are scored alike.
    """
    stats = materialise(with_statistics(docs.select(F.col(id_col), F.col(text_col))), "statistics")
    known = labels.select(F.col(id_col), F.col(label_col).cast("double").alias("y")).where(F.col("y").isNotNull())
    if learn_from is not None:
        known = known.where(learn_from)
    known = known.withColumn("h", F.xxhash64(F.col(id_col)))
    total = known.count()
    if total > sample_rows:
        known = known.where(F.pmod(F.floor(F.col("h") / 8), F.lit(1_000_000)) < int(1_000_000 * sample_rows / total))
    sample = materialise(stats.join(known, id_col), "labelled") if total else None
    model = fit(sample) if total else None
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def score(column: pa.Array) -> pa.Array:
        m = shared.value
        return pa.array(np.full(len(column), 0.5) if m is None else m.score(_matrix(column)) if len(column) else np.zeros(0))

    scored = stats.select(id_col, score("stats").alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = remainder(F.col("doc_id"), 3) == 1
    out = score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), learn_from=~held)
    return out.select("doc_id", held.alias("held_out"), "score", "predicted")


QUERIES = {"op1_quality": op1_quality}
ORACLES: dict[str, str] = {}
