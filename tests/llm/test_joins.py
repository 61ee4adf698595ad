"""Line dedup, the n-gram join and decontamination against brute force, on a table with every awkward case."""

import random
import re

import pytest
from pyspark.sql import functions as F

from treegraph.llm import decontaminate, line_dedup, ngram_join

WORD = re.compile(rb"[^\x20\x09-\x0D]+")


def shingles(text, width=5):
    w = WORD.findall((text or "").encode().lower())
    if not w:
        return frozenset()
    return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)])


def alike(a, b):
    return bool(a) and bool(b) and 100 * len(a & b) >= 80 * len(a | b)


def corpus(n=120, seed=3):
    rng = random.Random(seed)
    vocabulary = [f"w{i}" for i in range(400)]
    shared = " ".join(rng.choice(vocabulary) for _ in range(25))
    out = [(0, None), (1, ""), (2, "  \n\t "), (3, "one two"), (4, "One  TWO"), (5, "x"), (6, "ÉCOLE un deux trois quatre cinq"), (7, "école un deux trois quatre cinq")]
    base = [rng.choice(vocabulary) for _ in range(120)]
    for i in range(8, n):
        kind = rng.random()
        if kind < 0.4:  # near copies with more or fewer edits
            w = base[:]
            for _ in range(rng.randint(0, 6)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
        elif kind < 0.7:
            w = [rng.choice(vocabulary) for _ in range(rng.randint(3, 90))] + shared.split()
        else:
            w = [rng.choice(vocabulary) for _ in range(rng.randint(1, 60))]
        lines, at = [], 0
        while at < len(w):
            k = rng.randint(4, 30)
            lines.append(" ".join(w[at : at + k]))
            at += k
        out.append((i, "\n".join(lines)))
    out += [(n, "word " * 3000), (n + 1, "word " * 2999), (None, out[20][1]), (9, out[9][1]), (9, out[9][1])]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "x") for i, t in corpus()]
    return spark.createDataFrame(rows, "doc_id long, text string, rk string")  # rk clashes with an inner name


def test_groups_match_brute_force(docs):
    rows = corpus()
    sets = [shingles(t) for _, t in rows]
    parent = list(range(len(rows)))

    def root(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for a in range(len(rows)):
        for b in range(a):
            if alike(sets[a], sets[b]):
                parent[root(a)] = root(b)
    best = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            best[root(i)] = min(best.get(root(i), d), d)
    want = sorted((d if d is not None else -1, len(s), best[root(i)]) for i, ((d, _), s) in enumerate(zip(rows, sets)))
    got = sorted((r.doc_id if r.doc_id is not None else -1, r.n_shingles, r.component_id) for r in ngram_join.similar_groups(docs).collect())
    assert got == want
    kept = ngram_join.keep_first(docs)
    assert kept.columns == docs.columns
    ids = [r.doc_id for r in kept.collect()]
    assert len(ids) == len(set(ids))
    assert {i for i in ids} == {c for d, n, c in want if n} | {d for d, n, c in want if not n}


def test_empty_tables(spark, docs):
    none = docs.limit(0)
    assert ngram_join.similar_groups(none).count() == 0
    assert line_dedup.dedup_lines(none).count() == 0
    items = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.remove_contaminated(docs, items).count() == docs.count()
    assert decontaminate.contaminated(none, items).count() == 0


def test_lines_match_brute_force(spark):
    rows = [(d, t) for d, t in corpus() if d is not None and d != 9]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    earlier, want = [], {}
    for d, t in sorted(rows, key=lambda r: r[0]):
        keep = []
        for line in (t or "").split("\n"):
            s = shingles(line) if len(WORD.findall(line.encode())) >= line_dedup.MIN_WORDS else frozenset()
            if not any(alike(s, e) for e in earlier):
                keep.append(line)
            if s:
                earlier.append(s)
        want[d] = None if t is None else "\n".join(keep)
    got = {r.doc_id: r.text for r in line_dedup.dedup_lines(table).collect()}
    assert got == want


def test_words_of_one_polynomial_hash_differ(spark):
    """A word by the parity of the bits of each place, and its complement: any polynomial modulo 2^64 takes them for the same."""
    words = ["".join("ab"[(bin(i).count("1") + k) & 1] for i in range(2048)) for k in (0, 1)]
    docs = spark.createDataFrame([(1, words[0]), (2, words[1]), (3, words[0].upper())], "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in ngram_join.similar_groups(docs).collect()}
    assert got == {1: 1, 2: 2, 3: 1}
    assert {r.doc_id for r in ngram_join.keep_first(docs).collect()} == {1, 2}


def test_long_posting_lists_are_dealt_out(spark, monkeypatch):
    from treegraph.llm import setjoin

    monkeypatch.setattr(setjoin, "BLOCK", 64)
    rng = random.Random(2)
    base = [f"b{i}" for i in range(60)]
    rows = []
    for i in range(1500):  # near copies of one text, each with a word of its own
        w = base[:]
        w[rng.randrange(60)] = f"own{i}"
        rows.append((i, " ".join(w)))
    rows += [(1500 + i, " ".join([*base[:6], *[f"x{i}w{k}" for k in range(40)]])) for i in range(1500)]  # only a passage of it
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets = [shingles(t) for _, t in rows]
    parent = list(range(1500))

    def root(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for a in range(1500):
        for b in range(a):
            if root(a) != root(b) and alike(sets[a], sets[b]):
                parent[max(root(a), root(b))] = min(root(a), root(b))
    got = {r.doc_id: r.component_id for r in ngram_join.similar_groups(docs).collect()}
    assert got == {i: root(i) if i < 1500 else i for i in range(3000)}


def test_clashing_columns_nulls_and_repeats(spark):
    rows = [(1, "a b c d e f\nx", 7, "p"), (1, "a b c d e f\nx", 7, "p"), (None, None, None, None), (2, "a b c d e f", 8, "q"), (3, "", 9, "r")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, __rk int, __lines string")
    out = line_dedup.dedup_lines(docs)
    assert out.columns == [*docs.columns, "n_lines", "n_removed"]
    assert sorted((str(r.doc_id), r.text, r.n_removed) for r in out.collect()) == [("1", "a b c d e f\nx", 0), ("1", "a b c d e f\nx", 0), ("2", "", 1), ("3", "", 0), ("None", None, 0)]
    kept = ngram_join.keep_first(docs)
    assert kept.columns == docs.columns and sorted(str(r.doc_id) for r in kept.collect()) == ["1", "2", "3", "None"]


TOKEN = re.compile(r"[^\W_]+")


def leaks(docs, items):
    """(doc, item, agreeing, compared) by comparing all diagonals."""
    out = set()
    for d, text in docs:
        w = TOKEN.findall((text or "").lower())
        for i, passage in items:
            x = TOKEN.findall((passage or "").lower())
            if not w or not x or len(x) >= 8 > len(w) or len(x) < 4 and len(x) != len(w):
                continue
            c = len(x) if len(x) < 8 else min(len(x), len(w), 20)
            best = 0
            for s in range(-len(x) + 1, len(w)):
                eq = [0 <= j + s < len(w) and w[j + s] == x[j] for j in range(len(x))]
                best = max(best, max(sum(eq[k : k + c]) for k in range(len(x) - c + 1)))
            if best * 100 >= c * (100 if c < 8 else 80):
                out.add((d, i, best, c))
    return out


def leak_tables():
    rng = random.Random(1)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 9)))
    items = [(i, " ".join(word() for _ in range(n))) for i, n in enumerate([1, 2, 3, 4, 5, 7, 8, 9, 10, 11, 12, 13, 14, 15, 16, 17, 18, 19, 20, 21, 30, 45])] + [(40, None), (41, ""), (3, "an other one of id three")]
    rows = [(0, None), (1, ""), (2, "." * 50)]
    for i in range(3, 400):
        text = [word() for _ in range(rng.choice([0, 3, 9, 60]))]
        item = rng.choice([t for _, t in items if t]).split()
        if rng.random() < 0.3:
            item = item[rng.randrange(len(item)) :]
        for k in rng.sample(range(len(item)), min(len(item), rng.choice([0, len(item) // 5, len(item) // 4]))):
            item[k] = word()
        at = rng.randint(0, len(text))
        text[at:at] = [x.upper() + "," if rng.random() < 0.3 else x for x in item]
        rows.append((i, " ".join(text)))
    return rows + rows[50:53] + [(60, "other text"), (None, rows[60][1])], items


@pytest.mark.parametrize("broadcast", [True, False])
def test_leaks_match_brute_force(spark, monkeypatch, broadcast):
    if not broadcast:
        monkeypatch.setattr(decontaminate, "BROADCAST_ROWS", 10)
        monkeypatch.setattr(decontaminate, "ANCHORS", 10)
    rows, items = leak_tables()
    docs = spark.createDataFrame([(*r, 0, "x") for r in rows], "doc_id long, text string, __rk int, words string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = leaks(sorted(set(rows), key=str), items)
    found = decontaminate.overlaps(docs, bench).select("doc_id", "item_id", "agreeing", "compared").collect()
    assert sorted(map(tuple, found), key=str) == sorted(want, key=str) and len(want) > 100
    kept = decontaminate.remove_contaminated(docs, bench)
    bad = {d for d, *_ in want}
    assert kept.columns == docs.columns
    assert sorted((r.doc_id for r in kept.collect()), key=str) == sorted((d for d, t in rows if not (d in bad and any(x[0] == d for x in leaks([(d, t)], items)))), key=str)
    plan = decontaminate.contaminated(docs, bench)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_masks_miss_no_overlap():
    from itertools import combinations

    for least, masks in decontaminate.MASKS.items():
        for n in {least, 20 if least == 15 else least}:
            may = n - -(-n * decontaminate.AGREE_PERCENT // 100)
            for gone in combinations(range(n), may):
                assert any(all(s + k not in gone for k in decontaminate.ones(m)) for m in masks for s in range(n - len(m) + 1))


def test_leak_query_equals_its_sql(spark):
    import duckdb

    sf = "/root/testdata/sf0.001"
    sql = decontaminate.ORACLES["op6_decontamination"].replace("FROM documents", f"FROM '{sf}/documents.parquet'").replace("FROM benchmark", f"FROM '{sf}/benchmark.parquet'")
    got = sorted(map(tuple, decontaminate.op6_decontamination(spark, sf).collect()))
    assert got == sorted(duckdb.sql(sql).fetchall()) and got


def test_short_lines_that_repeat_go(spark):
    table = spark.createDataFrame([(1, "Les.\n\nErheed. Titionly."), (2, "les.\n\nother"), (3, "Erheed. Titionly.\nLes.")], "doc_id long, text string")
    got = {r.doc_id: (r.text, r.n_removed) for r in line_dedup.dedup_lines(table).collect()}
    assert got == {1: ("Les.\n\nErheed. Titionly.", 0), 2: ("\nother", 1), 3: ("", 2)}
