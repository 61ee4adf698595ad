"""Learned operators: held-out accuracy, bounds, nulls and empty tables."""

import os
import random

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from treegraph.llm import language, language_model, quality


def prose(rng, syllables, n):
    return " ".join("".join(rng.choice(syllables) for _ in range(rng.randint(1, 4))) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(4)
    kinds = {"aa": ["th", "er", "on", "an"], "bb": ["lo", "si", "qua", "ré"], "cc": ["sch", "ung", "ei", "ü"]}
    rows = [(i, prose(rng, kinds[k], rng.randint(20, 120)), k) for i in range(240) for k in [rng.choice(list(kinds))]]
    rows += [(900, None, "aa"), (901, "", None), (902, "12 34 !!", "bb"), (903, "th" * 5000, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string")


def test_language(spark, docs):
    model = language.fit(docs.where("doc_id < 120"))
    got = {r.doc_id: r for r in language.identify(docs, model).collect()}
    held = [r for r in docs.where("doc_id between 120 and 240").collect()]
    assert sum(got[r.doc_id].lang_pred == r.lang for r in held) >= 0.98 * len(held)
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900, 901, 902)) and got[903].lang_pred == "aa"
    assert all(0 <= r.score <= 1 for r in got.values())
    nothing = language.fit(docs.limit(0))
    assert {r.lang_pred for r in language.identify(docs, nothing).collect()} == {"und"}


def parsed(text, sample):
    """Phrases of a text by longest matches in a sample, one letter at a time."""
    n = at = 0
    while at < len(text):
        k = 1
        while at + k < len(text) and text[at : at + k + 1] in sample:
            k += 1
        at, n = at + k, n + 1
    return n


@pytest.mark.parametrize("dense", [language.DENSE, 0])
def test_phrases_are_longest_matches(monkeypatch, dense):
    rng = random.Random(7)
    monkeypatch.setattr(language, "DENSE", dense)
    monkeypatch.setattr(language, "STRETCH", 16)  # phrases run over the ends of many stretches, some over whole ones
    own = {k: prose(rng, kind, 120) for k, kind in {"aa": ["th", "er", "on"], "bb": ["lo", "si", "qua"]}.items()}
    model = language.learn({k: [v, v[:40]] for k, v in own.items()})
    texts = [own["aa"][5:300], own["bb"][:200] + "xyz" + own["aa"][:100], "th", "q" * 50, prose(rng, ["th", "lo"], 60), own["aa"][:130] * 2]
    got = model.phrases([language.folded(t) for t in texts])
    fold = lambda t: "".join(map(chr, language.folded(t)))
    assert got.tolist() == [[parsed(fold(t), fold(own[k]) + " ") for k in ("aa", "bb")] for t in texts]


def test_language_of_long_texts_alone(spark):
    rng = random.Random(8)
    kinds = {"aa": ["th", "er", "on"], "bb": ["lo", "si", "qua"]}
    rows = [(i, prose(rng, kinds[k], 3000), k, 1.0) for i, k in enumerate(["aa", "bb"] * 4)]
    docs = spark.createDataFrame(rows + rows[:2] + [(None, None, None, None)], "doc_id long, text string, lang string, score double")  # score is replaced
    assert all(len(t) > language.SAMPLE_DOC_CHARS for _, t, _, _ in rows)
    got = language.identify(docs, language.fit(docs)).collect()
    assert len(got) == len(rows) + 3 and all(r.lang_pred == (r.lang or "und") for r in got)
    assert language.identify(docs.limit(0), language.fit(docs)).count() == 0


def test_quality(spark):
    rng = random.Random(5)
    rows = []
    for i in range(600):
        text = prose(rng, ["ab", "cd", "ef", "gh", "ij"], rng.randint(5, 60)).capitalize() + "."
        bad = i % 3 == 0
        rows.append((i, text.replace(" ", " ### ").upper() if bad else text, int(not bad)))
    rows += [(700, None, None), (701, "", None)]
    docs = spark.createDataFrame([r[:2] for r in rows], "doc_id long, text string")
    labels = spark.createDataFrame([(i, q, 0) for i, _, q in rows], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in quality.score_quality(docs, labels, learn_from=F.col("doc_id") % 2 == 0).collect()}
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in got.values())
    odd = [r for r in rows if r[0] % 2 and r[2] is not None]
    assert sum(got[i].predicted == q for i, _, q in odd) >= 0.97 * len(odd)
    assert {r.score for r in quality.score_quality(docs, labels.limit(0)).collect()} == {0.5}


def test_isotonic():
    x, y = quality.isotonic(__import__("numpy").array([1.0, 2, 3, 4]), __import__("numpy").array([0.0, 1, 0, 1]))
    assert y.tolist() == [0.0, 0.5, 1.0] and x.tolist() == [1.0, 2.5, 4.0]


def test_language_model(spark, docs, monkeypatch):
    monkeypatch.setattr(language_model, "STEPS", 30)
    monkeypatch.setattr(language_model, "HEAD_WORDS", 50)  # so that most words are joined
    held = F.col("doc_id") % 7 == 2
    got = {r.doc_id: r for r in language_model.score_texts(docs, ~held).collect()}
    rows = docs.collect()
    from collections import Counter

    c, texts = Counter(), 0
    for r in rows:
        if r.doc_id % 7 != 2:
            c.update(language_model.words(r.text))
            texts += 1
    n, v = sum(c.values()) + texts, len(c) + 1
    for r in rows:
        w = language_model.words(r.text)
        base = sum(np.log10((c[x] + 1) / (n + v + 1)) for x in w) + np.log10((texts + 1) / (n + v + 1))
        g = got[r.doc_id]
        assert (g.n_tokens, g.n_known, g.train_tokens) == (len(w) + 1, sum(c[x] > 0 for x in w) + 1, n)
        assert g.base_score == pytest.approx(base) and g.score < 0
    sub_total = [r.score for r in language_model.score_texts(docs.limit(3), F.lit(False)).collect()]
    assert len(sub_total) == 3 and all(np.isfinite(sub_total))


def test_every_words_count_is_in_the_score(docs, monkeypatch):
    monkeypatch.setattr(language_model, "STEPS", 30)
    got = []
    for head in (100_000, 50):  # all counts broadcast; most of them joined
        monkeypatch.setattr(language_model, "HEAD_WORDS", head)
        got.append({r.doc_id: r.score for r in language_model.score_texts(docs, F.col("doc_id") % 7 != 2).collect()})
    assert got[1] == pytest.approx(got[0], abs=1e-6)


def test_training_reads_whole_texts_of_all_rows(spark, monkeypatch):
    rows = [(i, "one two three " * 200 + f"tail{i} " * 50) for i in range(20)]
    seen = {}
    fit, name = language_model.train, language_model.vocabulary
    monkeypatch.setattr(language_model, "train", lambda ids, windows: seen.update(ids=ids, windows=windows.copy()) or fit(ids, windows))
    monkeypatch.setattr(language_model, "vocabulary", lambda count, first, number, cells, c: seen.update(count=count.copy(), first=first, pairs=c.sum()) or name(count, first, number, cells, c))
    monkeypatch.setattr(language_model, "STEPS", 5)
    language_model.score_texts(spark.createDataFrame(rows, "doc_id long, text string"), F.lit(True)).count()
    n_words = sum(len(t.split()) for _, t in rows)
    count, first = seen["count"], seen["first"]
    assert count[first].sum() == n_words + len(rows) and count[-1] == len(rows)  # a first id a word, an end a text
    assert seen["pairs"] == 2 * count[~first].sum()  # each later id has one before it
    assert len(seen["windows"]) == count.sum()  # a small table: every place of every text
    goals = seen["windows"][:, language_model.STRIDE + 1]
    want = np.bincount(seen["ids"].class_of, weights=count, minlength=language_model.CLASSES)
    assert np.bincount(goals, minlength=language_model.CLASSES).tolist() == want.tolist()


@pytest.fixture(scope="module")
def trained(spark, docs):
    """The model that scoring the documents trains, and the words whose counts it has."""
    kept = {}
    weigh, head = language_model.Model.weigh, language_model.Head.__init__

    def weighed(self, *args):
        weigh(self, *args)
        kept["model"] = self

    def made(self, found, counts, ends):
        head(self, found, counts, ends)
        kept["head"] = self

    patch = pytest.MonkeyPatch()
    patch.setattr(language_model, "STEPS", 60)
    patch.setattr(language_model.Model, "weigh", weighed)
    patch.setattr(language_model.Head, "__init__", made)
    language_model.score_texts(docs, F.lit(True)).count()
    patch.undo()
    return kept["model"], kept["head"]


def test_probabilities_sum_to_one(trained):
    model, head = trained
    with open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        sub = language_model.Subwords(f.read())
    start = [int(x) for x in sub.encoding.encode_ordinary(" ther on lo")]
    every = np.arange(sub.end + 1)
    for before in ([], start):  # all ids, first in a text and after others
        n = len(before) + 1
        ids = np.concatenate([np.tile(np.array(before, dtype=np.int64), (len(every), 1)), every[:, None]], axis=1).ravel()
        own, first = (x[n - 1 :: n] for x in model.log10(ids, np.full(len(every), n)))
        assert 0.999 < (10**own).sum() <= 1 + 1e-6  # classes without an id keep a little
        assert (10 ** own[sub.first]).sum() == pytest.approx(10 ** first[0], abs=1e-3)
    texts = pa.array([w.as_py() for w in head.words], pa.large_binary())  # of all known words, at the start of a text
    c = language_model.cut(texts)
    alone = model.words(*sub.flat(c))
    count = head.of(c.distinct)[c.which]
    p = model.mixed(alone, count)[np.cumsum(c.sizes) - c.sizes]
    end = language_model.cut(pa.array([b""], pa.large_binary()))
    p = np.append(p, model.mixed(model.words(*sub.flat(end)), np.array([head.ends])))
    assert 0.3 < (10**p).sum() <= 1 + 1e-9
    assert model.weight + (model.factor * model.mass).sum() == pytest.approx(1)


def test_long_words_cost_what_they_are(trained):
    model, head = trained
    rng = random.Random(1)
    with open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        sub = language_model.Subwords(f.read())
    scores = []
    for n in (200, 400, 4000):
        c = language_model.cut(pa.array(["".join(rng.choice("abcdefgh0123#") for _ in range(n)).encode()], pa.large_binary()))
        scores.append(model.mixed(model.words(*sub.flat(c)), head.of(c.distinct)[c.which])[0])
    assert scores[0] > 1.5 * scores[1] > 15 * scores[2] / 1.1 and np.isfinite(scores).all()


@pytest.mark.skipif(not os.path.isdir("/root/testdata/sf0.1"), reason="no test data")
def test_held_out_texts_score_above_the_unigram_base(spark):
    got = language_model.op4_lm_scoring(spark, "/root/testdata/sf0.1").where("held_out").agg(F.sum("score").alias("score"), F.sum("base_score").alias("base")).first()
    print("held out", got)
    assert got.score > got.base


def test_words_as_python_splits_them():
    texts = [b"", b" a  B\n", b"\xc3\x89cole \xc2\xa0x\xc2\x85 \x0by", b"no", b"\t"]
    c = language_model.cut(pa.array(texts, pa.large_binary()))
    every = [*c.distinct.to_pylist(), None]
    got, at = [], 0
    for n in c.sizes.tolist():
        got.append([every[i] for i in c.which[at : at + n]])
        at += n
    assert got == [[*t.lower().split(), None] for t in texts]
