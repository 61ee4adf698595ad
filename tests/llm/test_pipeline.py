"""The pipeline and its stages on tables with every awkward case."""

import random

import pytest
import public_tokenizers
import tiktoken
from test_joins import alike, leaks, shingles

import corpus_pipeline
from treegraph.llm import bpe

COLUMNS = "doc_id long, text string, lang string, source string, n_chars long"
KINDS = {"aa": ["th", "er", "on", "an"], "bb": ["lo", "si", "qua", "ré"]}


def prose(rng, kind, n):
    return " ".join("".join(rng.choice(KINDS[kind]) for _ in range(rng.randint(1, 4))) for _ in range(n))


def tables():
    rng = random.Random(9)
    items = [(i, prose(rng, "aa", 30)) for i in range(4)]
    rows = []
    for i in range(80):
        kind = rng.choice(list(KINDS))
        lines = [prose(rng, kind, rng.randint(12, 40)) for _ in range(rng.randint(2, 6))]
        rows.append((i, "\n".join(lines), kind, "web", 0))
    rows += [(100, rows[5][1], rows[5][2], "copy", 0), (101, rows[6][1] + " " + prose(rng, rows[6][2], 1), None, "near", 0)]
    rows += [(110 + i, prose(rng, "aa", 60) + "\n" + items[i][1] + "\n" + prose(rng, "aa", 60), "aa", "leak", 0) for i in range(3)]
    rows += [(120 + i, prose(rng, "bb", 50) + "\nsubscribe to our letter", "bb", "line", 0) for i in range(3)]
    rows += [(130, None, None, None, None), (131, "", "aa", "", 0), (132, " \n\t", None, "", 0), (133, "12 34 !!", "bb", "", 0), (134, "жщ" * 300, None, "other", 0)]
    rows += [rows[0], rows[0], (140, prose(rng, "aa", 4000), "aa", "long", 0)]
    return rows, items


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    rows, items = tables()
    d = tmp_path_factory.mktemp("pipeline")
    spark.createDataFrame([(*r, "x") for r in rows], COLUMNS + ", rk string").write.parquet(str(d / "documents.parquet"))
    spark.createDataFrame(items, "item_id long, text string").write.parquet(str(d / "benchmark.parquet"))
    return str(d)


def by_id(df):
    return sorted((tuple(r) for r in df.select("doc_id", "text").collect()), key=str)


def test_stages_match_brute_force(spark, folder):
    rows, items = tables()
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    stage = dict(corpus_pipeline.STAGES)

    def run(name, before):
        out = spark.createDataFrame(stage[name](spark, before, folder).collect(), before.schema)
        assert out.columns == docs.columns
        return out

    one = run("language ID", docs)
    assert {r.doc_id for r in one.collect()} == {r[0] for r in rows} - {130, 131, 132, 133, 134}
    assert {r.doc_id: r.lang for r in one.collect()}[101] == rows[6][2]

    two = run("line dedup", one)
    earlier, want = [], {}
    for d, t in sorted(set(by_id(one))):
        keep = []
        for line in t.split("\n"):
            s = shingles(line)
            if not any(alike(s, e) for e in earlier):
                keep.append(line)
            if s:
                earlier.append(s)
        want[d] = "\n".join(keep)
    assert {r.doc_id: r.text for r in two.collect()} == {d: t for d, t in want.items() if t.strip()}
    assert all(r.n_chars == len(r.text) for r in two.collect())

    three = run("n-gram Jaccard join", two)
    kept = []
    for d, t in sorted(set(by_id(two))):
        if not any(alike(shingles(t), shingles(x)) for _, x in kept):
            kept.append((d, t))
    assert by_id(three) == sorted(kept, key=str)

    four = run("benchmark decontamination", three)
    bad = {d for d, *_ in leaks([(r.doc_id, r.text) for r in three.collect()], items)}
    assert bad == {110, 111, 112} and {r.doc_id for r in four.collect()} == {r.doc_id for r in three.collect()} - bad

    five = stage["byte-level BPE"](spark, four, folder).collect()
    with open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(f.read()), special_tokens={})
    text = {r.doc_id: r.text for r in four.collect()}
    assert all(r.round_trip and r.ids == enc.encode_ordinary(text[r.doc_id]) and r.n_tokens == len(r.ids) for r in five) and len(five) == len(text)


def test_whole_run(spark, folder, tmp_path):
    got = {r.doc_id: r for r in corpus_pipeline.run(spark, folder).collect()}
    clean = set(range(80)) | {120, 121, 122, 140}
    assert clean <= set(got) and not {100, 101, 110, 111, 112, 130, 131, 132, 133, 134} & set(got)
    none = spark.read.parquet(f"{folder}/documents.parquet").limit(0)
    none.write.parquet(str(tmp_path / "documents.parquet"))
    spark.read.parquet(f"{folder}/benchmark.parquet").write.parquet(str(tmp_path / "benchmark.parquet"))
    empty = corpus_pipeline.run(spark, str(tmp_path))
    assert empty.count() == 0 and "ids" in empty.columns
