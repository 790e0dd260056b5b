"""Operators that learn or approximate, against brute force or held-out labels."""

import math
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import pytest

from walkrank.llm import html_extract, quality, topk, vectors

DATA = "/root/testdata/sf0.01"


def test_quality_on_held_out_labels(spark):
    docs, labels = spark.read.parquet(f"{DATA}/documents.parquet"), spark.read.parquet(f"{DATA}/labels.parquet")
    got = quality.classify(docs, labels).join(labels, "doc_id").where("held_out and quality is not null").toPandas()
    good, bad = got[got.quality == 1], got[got.quality == 0]
    assert len(got) > 50 and (good.predicted == 1).mean() > 0.95 and (bad.predicted == 0).mean() > 0.7
    odd = spark.createDataFrame([(1, None, 2.0), (None, "", 2.0), (2, "x" * 100000, 2.0), (2, "x", 2.0)], "doc_id long, text string, score double")
    r = quality.classify(odd, labels).collect()
    assert len(r) == 4 and all(0 <= x.score <= 1 for x in r)
    assert [x.score for x in quality.classify(odd, labels.limit(0)).collect()] == [0.5] * 4
    assert quality.classify(odd.limit(0), labels).count() == 0
    assert quality.keep_good(odd, labels.limit(0)).columns == ["doc_id", "text"]


def brute_topk(rows, k=5):
    ok = {i: [math.floor(256 * float(np.float32(x))) for x in v] for i, v in rows if v and i is not None and all(x is not None and math.isfinite(x) for x in v)}
    out = set()
    for q in ok:
        if q % 50 == 0:
            s = sorted((-sum(a * b for a, b in zip(ok[q], ok[c])), c) for c in ok if c != q and len(ok[c]) == len(ok[q]))[:k]
            out |= {(q, r + 1, c, -x) for r, (x, c) in enumerate(s)}
    return out


def test_topk(spark):
    rng = np.random.default_rng(4)
    rows = [(i, rng.standard_normal(8).round(1).tolist()) for i in range(400)]
    rows += [(1000, None), (1001, [1.0, None] * 4), (1002, [float("nan")] * 8), (1050, [0.0] * 8), (1100, [1.0, 2.0]), (1101, [3.0, 1.0]), (None, [1.0] * 8), (1150, [])]
    df = spark.createDataFrame([(i, v, 1) for i, v in rows], "vec_id long, embedding array<float>, score int")
    got = topk.top_k(df, df.where("vec_id % 50 = 0"), shard_rows=60, block_rows=5)
    assert {tuple(r) for r in got.collect()} == brute_topk(rows)
    assert topk.top_k(df.limit(0), df.limit(0)).count() == 0
    big = spark.createDataFrame([(0, [3e30, 1.0]), (1, [3e30, 1.0]), (2, [-3e30, 1.0])], "vec_id long, embedding array<float>")
    assert [r.vec_id for r in topk.top_k(big, big.where("vec_id = 0")).orderBy("rank").collect()] == [1, 2]


def test_vector_duplicates(spark):
    rng = np.random.default_rng(5)
    base = rng.standard_normal((60, 24))
    v = np.concatenate([base, base[:30] + 0.12 * rng.standard_normal((30, 24)), base[:20] + 0.3 * rng.standard_normal((20, 24)), np.repeat(base[:1], 40, 0) + 0.01 * rng.standard_normal((40, 24)), base[:3]]).astype(np.float32)
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(900, None), (901, [0.0] * 24), (902, [float("inf")] * 24), (903, [1.0, 0.0]), (904, [2.0, 0.0]), (None, v[0].tolist())]
    df = spark.createDataFrame([(i, x, 1) for i, x in rows], "vec_id long, embedding array<float>, kept int")
    for size in (4096, 16):
        got = {r.vec_id: tuple(r)[1:] for r in vectors.near_duplicates(df, block_rows=size).collect()}
        assert len(got) == len(rows)
        u = v.astype(np.float64) / np.linalg.norm(v.astype(np.float64), axis=1)[:, None]
        near = u @ u.T >= 0.95
        np.fill_diagonal(near, False)
        label = np.arange(len(v))
        while True:
            new = np.minimum(label, np.where(near, label[None, :], len(v)).min(axis=1))
            if (new == label).all():
                break
            label = new
        for i in range(len(v)):
            assert got[i] == (near[i].sum(), label[i], label[i] == i), i
        assert got[900] == (0, 900, True) and got[902] == (0, 902, True)
        assert got[903] == (1, 903, True) and got[904] == (1, 903, False) and got[None] == (0, None, False)
    assert vectors.near_duplicates(df.limit(0)).count() == 0


def test_near_pairs_are_whole_and_read_few_windows():
    rng = np.random.default_rng(6)
    for dim in (1, 2, 5, 24, 64, 300):
        x = rng.standard_normal((1100, dim))
        x = np.concatenate([x, x[:300] + rng.uniform(0, 0.4, (300, 1)) * rng.standard_normal((300, dim))])
        x = x / np.linalg.norm(x, axis=1)[:, None] @ vectors.rotation(dim)
        y = x[rng.permutation(len(x))[:700]]
        for other, own in ((y, False), (x, True)):
            near = x @ other.T >= 0.95
            spent = []
            found = [np.stack(p) for p in vectors.near_pairs(x, other, 0.1 + 1e-9, own, spent)]
            i, j = np.concatenate(found, axis=1)
            hit = np.zeros(near.shape, dtype=int)
            np.add.at(hit, (i, j), 1)
            assert hit.max() == 1 and (hit[np.triu(near, 1) if own else near] == 1).all() and not (own and (i >= j).any())
            if dim >= 64:
                # a vector's most telling projections come first: most windows are never read
                assert sum(spent) < 0.4 * dim * len(x) * -(-len(other) // 64) and len(i) < 3 * near.sum()


def test_vectors_keep_their_precision_and_repeated_ids(spark):
    rows = [(1, [1e300, 0.0]), (2, [1e300, 0.0]), (3, [1e-50, 1e-50]), (4, [1e-50, 1e-50]), (5, [-1e-200, 1e-200]), (6, [-2.0, 2.0]), (7, [1.0, 1e-9]), (8, [0.0, -3.0]), (8, [0.0, 3.0]), (9, [1e-30, 1.0])]
    got = sorted(tuple(r) for r in vectors.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect())
    # (1, 2, 7), (3, 4), (5, 6) and one row of id 8 with 9; the other row of id 8 is named alike
    assert got == [(1, 2, 1, True), (2, 2, 1, False), (3, 1, 3, True), (4, 1, 3, False), (5, 1, 5, True), (6, 1, 5, False), (7, 2, 1, False), (8, 0, 8, True), (8, 1, 8, True), (9, 1, 8, False)]


PAGE = """<!DOCTYPE html><html><head><title>T</title><script>var t="</p>";</script></head><body><nav><a href=x>Menu</a></nav><div class="ad">Buy</div>
<article><h1>Head &amp;  line</h1><p><b>One <i>two</i>three.<br><p>Four&nbsp;five.</p><div class="comments"><p>First!</p></div><form><p>Name</p></form></article><footer>&copy; me</footer>"""


def test_html(spark):
    assert html_extract.main_text(html_extract.parse(PAGE), None) == "Head & line\n\nOne twothree.\n\nFour five."
    other = '<body><div id="menu"><p>Menu menu</p></div><div class="post-12"><p>Long main text of this page, as it is.</p><p>More.</p></div><div class="side"><p>S</p></div>'
    short = '<body><div class="intro"><p>A teaser that is longer than the post of this page.</p></div><div class="post-7"><p>Brief.</p></div>'
    rows = [(1, "http://a.org/1", PAGE), (2, "http://b.org/1", other), (3, "http://b.org/2", other.replace("12", "13")), (4, "http://b.org/3", short), (5, "http://c.org", None), (6, None, ""), (7, None, "<p>plain"), (7, None, "<p>plain"), (None, "x", "a < b <unclosed")]
    got = html_extract.extract(spark.createDataFrame([(*r, "t") for r in rows], "page_id long, url string, html string, text string")).collect()
    by = {r.page_id: r.text for r in got}
    assert len(got) == len(rows) and all(r.n_chars == len(r.text) for r in got)
    assert by[2] == "Long main text of this page, as it is.\n\nMore." and by[4] == "Brief." and by[5] == "" and by[6] == "" and by[7] == "plain" and by[None] == "a < b"
    assert html_extract.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_html_paths_are_whole():
    def nested(deep, inner):
        return "<body>" + "".join(f'<div class="a-level-of-the-template-{chr(97 + i)}">' for i in range(deep)) + inner + "</div>" * deep

    article = '<div class="post"><p>The words of this post, which are many.</p></div>'
    deep = nested(20, '<div class="teasers"><p>Other.</p></div>' + article)
    assert html_extract.main_text(html_extract.parse(deep), None) == "The words of this post, which are many."
    twins = '<div class="a b c wide"><p>A long text that should be taken.</p></div><div class="a b c x"><p>Not it.</p></div>'
    assert html_extract.main_text(html_extract.parse("<body>" + twins), None) == "A long text that should be taken."
    assert len(set(html_extract.parse(nested(3000, "<p>x</p>")).paths)) == 3002


def test_html_all_containers_vote(spark):
    # three levels with names of their own in each page; only the host's container around them is shared
    page = lambda a: f'<body><div class="promise"><p>{"A claim of this page, longer than the text. " * (9 if a == "z" else 0)}</p></div><div class="frame"><div id="one-{a}"><div id="two-{a}"><div id="three-{a}"><p>Text of page {a}.</p></div></div></div></div>'
    got = {r.page_id: r.text for r in html_extract.extract(spark.createDataFrame([(i, f"http://h.org/{a}", page(a)) for i, a in enumerate("pqrstuvwxyz")], "page_id long, url string, html string")).collect()}
    assert got == {i: f"Text of page {a}." for i, a in enumerate("pqrstuvwxyz")}


def test_html_figures_and_formulas_are_text():
    page = "<body><article><p>Let <math><mi>x</mi><mo>=</mo><mn>1</mn></math> be.</p><figure><pre>code()</pre><figcaption>A caption.</figcaption></figure><object><p>Instead.</p></object></article>"
    assert html_extract.main_text(html_extract.parse(page), None) == "Let x=1 be.\n\ncode()\n\nA caption.\n\nInstead."


def test_pipeline_stages_against_plain_ones(spark):
    pytest.importorskip("public_tokenizers")
    import corpus_pipeline as cp

    docs = spark.read.parquet(f"{DATA}/documents.parquet").where("doc_id < 300")
    names = [n for n, _ in cp.STAGES]
    assert names == ["quality classifier", "SimHash near-dedup", "mixing sources", "BPE encoding"]
    frames = [docs]
    for _, stage in cp.STAGES:
        frames.append(stage(spark, frames[-1], DATA).cache())
    assert all(f.columns == docs.columns for f in frames[1:-1])
    bad = {r.doc_id for r in quality.classify(docs, spark.read.parquet(f"{DATA}/labels.parquet")).where("predicted = 0").collect()}
    assert {r.doc_id for r in frames[1].collect()} == {r.doc_id for r in docs.collect()} - bad
    assert frames[3].select("doc_id").distinct().count() == frames[2].count() and frames[4].count() == frames[3].count()
