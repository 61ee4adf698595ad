"""Byte-level BPE against tiktoken, the extractor, archives and the lattice on awkward input."""

import random

import numpy as np
import pytest
import public_tokenizers
import tiktoken

from treegraph.llm import bpe, lattice, main_text, warc


def test_ids_equal_tiktoken(spark):
    with open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        ranks = bpe.read_ranks(f.read())
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    rng = random.Random(1)
    al = "ab é日'st 1\n\t  .🙂%\x00　"
    texts = ["", " ", "a  b", "don't 'll x", "日本語 🙂", "a\r\nb ", "<|endoftext|>", "x" * 5000] + ["".join(rng.choice(al) for _ in range(rng.randint(0, 40))) for _ in range(400)]
    df = spark.createDataFrame([(i, t, [1]) for i, t in enumerate(texts)] + [(-1, None, None)], "doc_id long, text string, ids array<int>")
    rows = {r.doc_id: r for r in bpe.decode_ids(bpe.encode_texts(df)).collect()}
    assert rows[-1].ids == [] and bytes(rows[-1].decoded) == b""
    for i, t in enumerate(texts):
        assert rows[i].ids == enc.encode_ordinary(t) and bytes(rows[i].decoded) == t.encode()


def test_main_text():
    long = "word " * 40
    page = f"""<html><head><title>t</title><style>p{{}}</style></head><body><header>Top</header><nav><ul><li><a>m</a></ul></nav>
    <div class="sidebar-left"><p>{long}{long}</p></div><div id="content"><h1>Head &amp; title</h1><p>{long}<br>x &lt;y&gt;</p><div class="ad">buy {long}</div><p>Short.</p></div>
    <section id="comments"><p>{long}{long}{long}</p></section><form><p>{long}</p></form><footer>&copy;</footer><script>var a="</p>";</script></body>"""
    assert main_text.main_text(page) == f"Head & title\n{long}x <y>\nShort."
    assert main_text.main_text(None) == "" == main_text.main_text("") == main_text.main_text("<p></p>")
    assert main_text.main_text("only text") == "only text"


def test_main_text_keeps_all_of_the_article():
    long, more = "first part " * 20, "second part " * 25
    text = lambda body: main_text.main_text(f"<html><body>{body}</body></html>").split("\n")
    a, b = long.strip(), more.strip()
    assert text(f"<p>{long}</p><aside>buy this now</aside><p>{more}</p>") == [a, b]
    assert text(f'<h1>T</h1><p>{long}</p><div class="ad">buy</div><p>{more}</p>') == ["T", a, b]
    assert text(f"<article><h2>one</h2><p>{long}</p></article><article><p>{more}</p></article>") == ["one", a, b]
    assert text(f'<div class="page has-sidebar"><article><p>{long}</p></article></div>') == [a]
    assert text(f'<div class="search-page"><p>{long}</p></div>') == [a]
    assert text(f'<div class="sidebar"><article><p>{long}</p></article></div>') == [a]  # the frame of the only article
    assert text(f'<article><p>{long}</p></article><section id="comments"><article class="comment"><p>{more}</p></article></section>') == [a]
    assert text(f"<p>{long}</p><p>Short end.</p><div><a href=x>Home</a> <a href=y>About</a></div>") == [a, "Short end."]


def test_main_text_is_linear():
    import time

    took = []
    for n in (20_000, 40_000):
        began = time.process_time()
        assert main_text.main_text("<div>x" * n).count("x") == n
        took.append(time.process_time() - began)
    assert took[1] < 4 * took[0] + 0.5
    big = "<article>" + "<p>some words of a long page</p>" * 160_000 + "</article>"
    assert len(main_text.main_text(big)) == 160_000 * 26 - 1


def test_extract_handles_nulls_repeats_and_no_rows(spark):
    long = "a line that is long enough to be the main text of any page at all, and then some more of it"
    rows = [(1, "u", f"<p>{long}</p>", "x"), (1, "u", f"<p>{long}</p>", "x"), (None, None, None, None), (2, "v", "", "y")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string, text string")  # text is replaced
    got = sorted((str(r.page_id), r.text) for r in main_text.extract(pages).collect())
    assert got == [("1", long), ("1", long), ("2", ""), ("None", "")]
    assert main_text.extract(pages.limit(0)).count() == 0


def test_salvage_recovers_later_records():
    recs = [warc.record("response", i, "u", b"x" * (50 + i), warc.digest(b"x" * (50 + i)), None, None) for i in range(5)]
    zipped = [warc.member(r) for r in recs]
    data = b"".join(zipped)
    assert len(warc.salvage(data).records) == 5 and not warc.salvage(data).gaps
    a = len(zipped[0])
    bad = bytearray(data)
    bad[a + 30] ^= 0xFF
    got = warc.salvage(bytes(bad))
    assert [h["x-page-id"] for _, h, _ in got.records] == ["0", "2", "3", "4"] and got.gaps[0][:2] == (a, len(zipped[1]))
    plain = recs[0] + b"noise" + recs[1][: len(recs[1]) // 2] + recs[2]
    got = warc.salvage(plain)
    assert [h["x-page-id"] for _, h, _ in got.records] == ["0", "2"] and len(got.gaps) == 1
    assert warc.salvage(b"").records == [] and warc.salvage(data[:-5]).gaps


def test_salvage_takes_linear_time():
    import os
    import time

    took = []
    for n in (4_000, 16_000):
        data = b"".join(warc.member(warc.record("response", i, "u", p, warc.digest(p), None, None)) for i in range(n) for p in [os.urandom(700)])
        data = data[:300] + b"\x1f\x8b\x08" * 2_000 + data[300:]
        began = time.process_time()
        got = warc.salvage(data)
        took.append(time.process_time() - began)
        assert len(got.records) == n - 1 and len(got.gaps) == 1
    assert took[1] < 8 * took[0] + 0.5


def test_archives_round_trip(spark, tmp_path):
    rows = [(1, "a", "same"), (2, "b", "same"), (3, None, None), (4, "d", ""), (5, "e", "other é"), (6, "f", "same"), (6, "g", "more"), (None, "h", "same"), (None, "i", "alone"), (5, "e", "other é")]
    pages = spark.createDataFrame([(*r, "x", i) for i, r in enumerate(rows)], "page_id long, url string, html string, __id string, refers_to int")
    files = warc.write_archives(pages, str(tmp_path / "w"))
    got = warc.verified(files, str(tmp_path / "w")).collect()
    key = lambda x: str(x)
    assert sorted(((r.page_id, r.payload_digest, r.record_type, r.refers_to, r.payload_bytes) for r in got), key=key) == sorted(((p, warc.digest((h or "").encode()), "revisit" if to else "response", to, len((h or "").encode())) for (p, _, h), to in zip(rows, [None, 1, None, 3, None, 1, None, 1, None, None])), key=key)
    none = warc.write_archives(pages.limit(0), str(tmp_path / "n"))
    assert warc.verified(none, str(tmp_path / "n")).count() == 0


def test_lost_records_raise(spark, tmp_path):
    pages = spark.createDataFrame([(i, "u", f"text {i} " * 40) for i in range(50)], "page_id long, url string, html string")
    files = warc.write_archives(pages.coalesce(1), str(tmp_path / "w"))
    path = files.first().path
    data = bytearray(open(path, "rb").read())
    data[len(data) // 2] ^= 0xFF
    open(path, "wb").write(data)
    rows = warc.read_archives(files, str(tmp_path / "w")).collect()
    assert sum(r.gap_bytes is not None for r in rows) == 1 and sum(bool(r.checked) for r in rows) == 49
    with pytest.raises(ValueError):
        warc.verified(files, str(tmp_path / "w"))


def test_archive_query_equals_its_sql(spark):
    import duckdb

    sf = "/root/testdata/sf0.001"
    want = duckdb.sql(warc.ORACLES["op3_warc"].replace("FROM pages", f"FROM '{sf}/pages.parquet'")).fetchall()
    assert sorted(map(str, warc.op3_warc(spark, sf).collect())) == sorted(str(r) for r in map(lambda x: __import__("pyspark").sql.Row(page_id=x[0], payload_bytes=x[1], payload_digest=x[2], record_type=x[3], refers_to=x[4]), want))


def test_lattice_points_are_nearest():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(200, 8)) * 2
    p = lattice.decode(x)
    assert np.allclose((2 * p) % 2, ((2 * p) % 2)[:, :1]) and np.allclose(p.sum(axis=1) % 2, 0)
    roots = lattice.minimal_vectors()
    assert len(roots) == 240 and np.allclose((roots**2).sum(axis=1), 2)
    assert (((x - p) ** 2).sum(axis=1)[:, None] <= ((x[:, None] - p[:, None] - roots[None]) ** 2).sum(axis=2) + 1e-9).all()


def test_near_vectors_match_brute_force(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(30, 16))
    rows = []
    for i in range(300):
        v = base[i % 30] + rng.normal(size=16) * rng.choice([0.0, 0.1, 0.25])
        rows.append((i, [float(a) for a in v]))
    rows += [(300, None), (301, [0.0] * 16), (302, [float("nan")] * 16), (303, [None] + [1.0] * 15), (304, [1.0, 2.0]), (305, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {r.vec_id: r for r in lattice.near_duplicates(df).collect()}
    x = np.array([v for _, v in rows[:300]])
    x /= np.linalg.norm(x, axis=1)[:, None]
    near = (x @ x.T >= 0.95) & ~np.eye(300, dtype=bool)
    links = np.array([got[i].n_links for i in range(300)])
    assert (links <= near.sum(axis=1)).all() and links.sum() >= 0.97 * near.sum()
    assert all(got[i].n_links == 0 and got[i].component_id == i and got[i].kept for i in range(300, 306))
    assert lattice.near_duplicates(df.limit(0)).count() == 0


def test_many_equal_vectors_fill_no_cell(spark):
    rng = np.random.default_rng(3)
    a, b = rng.normal(size=16), rng.normal(size=16)
    near = a + rng.normal(size=16) * 0.01
    rows = [(i, a.tolist(), 1) for i in range(3000)] + [(3000, near.tolist(), 2), (3001, b.tolist(), 3), (None, a.tolist(), 4), (5, a.tolist(), 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, rk int")
    got = lattice.near_duplicates(df).collect()
    assert len(got) == len(rows)
    links = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in got}
    assert links[3000] == (3001, 0, False) and links[3001] == (0, 3001, True) and links[7] == (3001, 0, False) and links[0] == (3001, 0, True) and links[None] == (3001, 0, False)
