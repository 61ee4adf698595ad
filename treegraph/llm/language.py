"""Language ID by cross-parsing: how few longest matches with a language's sample text cover a document."""

from __future__ import annotations

import math
import sys
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import remainder, table, unused

#: The sample per language: at most so many documents, of each at most so many characters (a window at a place chosen by hash), and so many together.
SAMPLE_DOCS, SAMPLE_DOC_CHARS, SAMPLE_CHARS = 48, 8_000, 24_000
#: Documents are parsed in stretches of so many characters at once; where a phrase runs over the end of one, its parse is mended.
STRETCH = 1_024
#: Transitions are looked up in a table of states times letters up to so many entries, else among sorted ones. Results are the same.
DENSE = 16 << 20
UNKNOWN = "und"
_FOLD: list[np.ndarray] = []


def fold_table() -> np.ndarray:
    """Code point to lower-case letter, or to a space if it is no letter; built once per process."""
    if not _FOLD:
        t = np.full(sys.maxunicode + 1, 32, dtype=np.uint32)
        for c in range(0x30000):
            ch = chr(c)
            if ch.isalpha():
                low = ch.lower()
                t[c] = ord(low) if len(low) == 1 else c
        _FOLD.append(t)
    return _FOLD[0]


def folded(text: str) -> np.ndarray:
    """Code points of the text, lower-cased, with each run of other than letters as one space."""
    c = fold_table()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), dtype=np.uint32)]
    gap = c == 32
    keep = ~gap
    keep[1:] |= gap[1:] & ~gap[:-1]
    return c[keep]


def suffix_automaton(codes: np.ndarray) -> list[dict[int, int]]:
    """Transitions of the smallest automaton of all substrings, by state; state 0 is none, state 1 the start."""
    step: list[dict[int, int]] = [{}, {}]
    link, depth = [0, 0], [0, 0]
    last = 1
    for c in codes.tolist():
        new = len(step)
        step.append({})
        depth.append(depth[last] + 1)
        link.append(1)
        p = last
        while p and c not in step[p]:
            step[p][c] = new
            p = link[p]
        if p:
            q = step[p][c]
            if depth[p] + 1 == depth[q]:
                link[new] = q
            else:
                twin = len(step)
                step.append(dict(step[q]))
                depth.append(depth[p] + 1)
                link.append(link[q])
                while p and step[p].get(c) == q:
                    step[p][c] = twin
                    p = link[p]
                link[q] = link[new] = twin
        last = new
    return step


@dataclass
class Model:
    languages: list[str]
    alphabet: np.ndarray  # sorted code points; code 0 is any other
    arcs: np.ndarray  # of all automata behind each other: state times letters plus code, ascending; at most three a character
    ends: np.ndarray  # the state that each arc leads to
    states: int
    start: np.ndarray  # each language's first state
    rate: np.ndarray  # phrases a character that a language's own text takes
    size: int  # characters behind an automaton

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "dense"}  # a worker makes its own

    def codes(self, points: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.alphabet, points), len(self.alphabet) - 1)
        return np.where(self.alphabet[at] == points, at + 1, 0).astype(np.int64)

    def walk(self):
        """(states, codes) -> the states after these letters, 0 where there is none. States are times the number of letters."""
        letters = len(self.alphabet) + 1
        if self.states * letters <= DENSE:
            if "dense" not in self.__dict__:
                self.dense = np.zeros(self.states * letters, dtype=np.int32)
                self.dense[self.arcs] = self.ends * letters
            return lambda state, code: self.dense.take(state + code)
        ends = self.ends * letters

        def look(state, code):
            key = state + code
            at = np.minimum(np.searchsorted(self.arcs, key), len(self.arcs) - 1)
            return np.where(self.arcs[at] == key, ends[at], 0)

        return look

    def phrases(self, texts: list[np.ndarray]) -> np.ndarray:
        """Phrases of each text (folded code points) for each language: (texts, languages).

        A phrase is the longest match from where the last one ended. Stretches are parsed side by side as if a phrase began
        at each; then the phrase that runs over the start of a stretch goes on until both parses begin a phrase at the same
        place, from where they agree, and the count is put right.
        """
        sizes = np.array([len(t) for t in texts], dtype=np.int64)
        out = np.zeros((len(texts), len(self.languages)))
        if not sizes.sum():
            return out
        codes = self.codes(np.concatenate(texts))
        per = -(-sizes // STRETCH)
        owner = np.repeat(np.arange(len(texts)), per)
        nth = np.arange(len(owner)) - np.repeat(np.cumsum(per) - per, per)
        begin = np.repeat(np.cumsum(sizes) - sizes, per) + nth * STRETCH
        length = np.minimum(STRETCH, np.repeat(sizes, per) - nth * STRETCH)
        order = np.argsort(-length, kind="stable")
        active = np.searchsorted(-length[order], -np.arange(length.max()), "left")  # stretches longer than t
        letters, step, sorted_begin = len(self.alphabet) + 1, self.walk(), begin[order]
        kind = np.int32 if self.states * letters <= DENSE else np.int64
        codes = codes.astype(kind)
        for k in range(len(self.languages)):
            # a phrase that begins with a letter; after an unknown one it is 0, so that the next begins another
            again = step(np.full(letters, self.start[k] * letters, dtype=kind), np.arange(letters, dtype=kind))
            now = np.full(len(owner), self.start[k] * letters, dtype=kind)
            fresh = np.zeros(len(codes), dtype=bool)  # a phrase begins here
            fresh[begin] = True
            for t, m in enumerate(active.tolist()):
                place = sorted_begin[:m] + t
                c = codes[place]
                to = step(now[:m], c)
                dead = np.flatnonzero(to == 0)
                if len(dead):
                    to[dead] = again[c[dead]]
                    if t:
                        fresh[place[dead]] = True
                now[:m] = to
            state = np.empty_like(now)
            state[order] = now
            count = np.add.reduceat(fresh.astype(np.int64), begin)
            # the phrase from before each stretch goes on into it
            late = np.flatnonzero(nth > 0)
            carried = state[late - 1]
            while len(late):
                go, more = np.arange(len(late)), np.zeros(len(late), dtype=np.int64)
                for t in range(STRETCH):
                    inside = t < length[late[go]]
                    go = go[inside]
                    if not len(go):
                        break
                    place = begin[late[go]] + t
                    c = codes[place]
                    to = step(carried[go], c)
                    dead = to == 0
                    to = np.where(dead, again[c], to)
                    same = dead & fresh[place]
                    more[go] += np.where(same, 0, dead.astype(np.int64) - fresh[place])
                    fresh[place] = dead  # what is true now
                    carried[go] = to
                    go = go[~same]
                count[late] += more
                state[late[go]] = carried[go]
                # where the parses never met, the next stretch was entered in another state than thought
                moved = late[go] + 1
                moved = moved[moved < len(owner)]
                late = moved[nth[moved] > 0]
                carried = state[late - 1]
            out[:, k] = np.bincount(owner, weights=count, minlength=len(texts))
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], np.ndarray, np.ndarray]:
        """Languages, scores, and how many times the language's own rate of phrases the text takes."""
        points = [folded(t) if t else np.zeros(0, dtype=np.uint32) for t in texts]
        letters = np.array([int(np.count_nonzero(p != 32)) for p in points])
        if not self.languages:
            return [UNKNOWN] * len(texts), np.zeros(len(texts)), np.zeros(len(texts))
        normal = self.phrases(points) / self.rate
        best = normal.argmin(axis=1)
        low = normal.min(axis=1)
        bits = (normal - low[:, None]) * self.rate.mean() * math.log2(self.size + 2)
        score = np.where(letters > 0, 1 / np.exp2(-np.minimum(bits, 900)).sum(axis=1), 0.0)
        strange = low / np.maximum(1, [len(p) for p in points])
        return [self.languages[b] if n else UNKNOWN for b, n in zip(best, letters)], score, strange


def learn(texts: dict[str, list[str]]) -> Model:
    """One automaton per language over whole sample texts; what no longer fits sets the language's own phrase rate."""
    parts, rest = {}, {}
    for lang in sorted(texts):
        points = [p for p in map(folded, texts[lang]) if np.count_nonzero(p != 32)]
        if not points:
            continue
        held, taken, room = points[-max(1, len(points) // 4) :] if len(points) > 1 else points, [], SAMPLE_CHARS
        for p in points[: max(1, len(points) - len(held))]:
            if len(p) < room or not taken:
                taken.append(p[:SAMPLE_CHARS])
                room -= len(p) + 1
        parts[lang], rest[lang] = np.concatenate([np.append(p, 32) for p in taken]), held
    languages = list(parts)
    none = np.zeros(0, dtype=np.int64)
    if not languages:
        return Model([], np.zeros(1, dtype=np.uint32), none, none, 0, none, np.ones(0), 0)
    size = min(len(p) for p in parts.values())  # the same amount of text for each language
    alphabet = np.unique(np.concatenate([p for p in parts.values()]))
    letters = len(alphabet) + 1
    model = Model(languages, alphabet, none, none, 0, none, np.ones(len(languages)), size)
    arcs, ends, starts, at = [], [], [], 0
    for lang in languages:
        step = suffix_automaton(model.codes(parts[lang]))
        arcs.append(np.array([(at + s) * letters + c for s, x in enumerate(step) for c in x], dtype=np.int64))
        ends.append(np.array([at + to for x in step for to in x.values()], dtype=np.int64))
        starts.append(at + 1)
        at += len(step)
    arcs, ends = np.concatenate(arcs), np.concatenate(ends)
    order = np.argsort(arcs)
    model.arcs, model.ends, model.states, model.start = arcs[order], ends[order], at, np.array(starts, dtype=np.int64)
    for k, lang in enumerate(languages):
        model.rate[k] = model.phrases(rest[lang])[:, k].sum() / max(1, sum(map(len, rest[lang])))
    return model


def fit(labelled: DataFrame, *, text_col: str = "text", lang_col: str = "lang", id_col: str = "doc_id", docs: int = SAMPLE_DOCS) -> Model:
    """Learn from a bounded sample of the labelled rows: per language the docs first in the order of a hash of their id and text.

    Of a long text a window of SAMPLE_DOC_CHARS characters is taken, at a place by its hash. Rows without a text or a language
    teach nothing; equal rows count once each; a table without labelled rows gives a model of no languages.
    """
    h = F.xxhash64(F.col(id_col), F.col(text_col))
    rows = labelled.select(F.col(text_col).alias("text"), F.col(lang_col).cast("string").alias("lang"), h.alias("h")).where(F.col("lang").isNotNull() & F.col("text").isNotNull())
    room = F.greatest(F.length("text") - SAMPLE_DOC_CHARS, F.lit(0))
    window = F.substring("text", (F.pmod(F.col("h"), room + 1) + 1).cast("int"), F.lit(SAMPLE_DOC_CHARS))
    # each task keeps its own first rows before they move; then the first of all
    first = F.slice(F.array_sort(F.collect_list(F.struct("h", "window"))), 1, docs)
    part = rows.select("lang", "h", window.alias("window")).withColumn("p", F.spark_partition_id())
    w = Window.partitionBy("lang", "p").orderBy("h", "window")
    few = part.withColumn("k", F.row_number().over(w)).where(F.col("k") <= docs)
    found = {r["lang"]: [x["window"] for x in r["first"]] for r in few.groupBy("lang").agg(first.alias("first")).collect()}
    return learn(found)


def identify(docs: DataFrame, model: Model, *, text_col: str = "text") -> DataFrame:
    """docs with lang_pred, score (0 to 1) and strange added (columns of these names are replaced).

    strange is the normalised number of phrases a character: about 1 for ordinary text of the language. A null text or one
    without a letter gives und, 0 and 0. Whole texts are parsed; equal texts get equal results; of languages that need equally
    few phrases the first by name wins. Other columns stay as they are; an empty table gives an empty result.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("struct<lang_pred:string,score:double,strange:double>")
    def parse(column: pa.Array) -> pa.Array:
        m, texts = shared.value, column.to_pylist()
        langs, scores, strange, at = [], [], [], 0
        while at < len(texts):
            to, room = at, 1 << 20
            while to < len(texts) and (to == at or room > 0):
                room -= len(texts[to] or "")
                to += 1
            a, b, c = m.predict(texts[at:to])
            langs += a
            scores.append(b)
            strange.append(c)
            at = to
        one = lambda parts: pa.array(np.concatenate(parts) if parts else np.zeros(0), pa.float64())
        return pa.StructArray.from_arrays([pa.array(langs, pa.string()), one(scores), one(strange)], ["lang_pred", "score", "strange"])

    own = [c for c in docs.columns if c not in ("lang_pred", "score", "strange")]
    (name,) = unused(docs, "__p")
    return docs.select(*own, parse(F.col(text_col)).alias(name)).select(*own, f"{name}.*")


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    held = (remainder(F.col("doc_id"), 4) == 2).alias("held_out")
    model = fit(docs.where(remainder(F.col("doc_id"), 4) != 2))
    return identify(docs.select("doc_id", "text", held), model).select("doc_id", "held_out", "lang_pred", "score")


QUERIES = {"op5_language_id": op5_language_id}
ORACLES: dict[str, str] = {}
