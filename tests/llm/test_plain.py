"""Operators against plain Python: mixing, quality, pages, repeated query ids, hot buckets, and the pipeline's stages one by one."""

import hashlib
import html
import math
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from walkrank.llm import html_extract, mixing, quality, simhash, topk

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def digest(*parts):
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def plain_mix(rows, target, limit, budget, seed=1):
    """[(doc_id, source, tokens, weight, copies)] of rows (doc_id, text, source): an independent bisection, then whole blocks in drawn order."""
    n = [len([w for w in "".join(" " if c in " \t\n\v\f\r" else c for c in t or "").split(" ") if w]) for _, t, _ in rows]
    tokens = Counter()
    for (_, _, s), k in zip(rows, n):
        tokens[s] += k
    some = {s: k for s, k in tokens.items() if k}
    total = sum(some.values())

    def weights(x):
        w = {s: (k / total) ** x for s, k in some.items()}
        return {s: v / sum(w.values()) for s, v in w.items()}

    entropy = lambda p: -sum(v * math.log(v) for v in p.values() if v)
    h1 = entropy(weights(1.0))
    wanted = h1 + target * (math.log(max(1, len(some))) - h1)
    lo, hi = 0.0, 1.0
    for _ in range(40 if len(some) > 1 else 0):
        mid = (lo + hi) / 2
        p = weights(mid)
        if entropy(p) <= wanted and max(p[s] * total / some[s] for s in some) <= limit:
            hi = mid
        else:
            lo = mid
    p = weights(hi if len(some) > 1 else 1.0)
    spend = max(some[s] / p[s] for s in some) if budget == "cover" and some else (0 if budget == "cover" else budget * total)
    out = []
    by = defaultdict(list)
    for i, r in enumerate(rows):
        by[r[2]].append(i)
    copies = {}
    for s, own in by.items():
        name = "-" if s is None else "+" + s
        mine = math.floor(round(p.get(s, 0) * spend, 3))
        passes, part = divmod(mine, tokens[s]) if tokens[s] else (1, 0)
        blocks = max(1, math.ceil(math.sqrt(len(own))))
        ident = lambda i: "" if rows[i][0] is None else str(rows[i][0])
        block = {i: digest(seed, "block", ident(i)) % blocks for i in own}
        order = sorted(set(block.values()), key=lambda b: (digest(seed, "permute", name, b), b))  # noqa: B023
        extra, left = set(), part
        for b in order:
            inside = [i for i in own if block[i] == b]
            size = sum(n[i] for i in inside)
            if part and size <= left:
                left -= size
                extra.update(inside)
                continue
            if part:
                for h in sorted({digest(seed, "order", ident(i)) for i in inside}):
                    same = [i for i in inside if digest(seed, "order", ident(i)) == h]
                    if sum(n[i] for i in same) > left:
                        break
                    left -= sum(n[i] for i in same)
                    extra.update(same)
            break
        for i in own:
            copies[i] = passes + (i in extra)
    for i, (d, _, s) in enumerate(rows):
        out.append((d, s, n[i], round(p.get(s, 0.0), 9), copies[i]))
    return out


def mixed_rows():
    rows = [(i, "w " * (1 + i * 7 % 11) + "é x", "hot" if i % 3 else f"s{i % 5}") for i in range(300)]
    return [*rows, (None, None, None), (601, "a b", None), (3, "w w w w", "s3"), (3, "w w w w", "s3"), (700, "", "s1"), (701, None, "quiet"), (702, "long " * 5000, "s2"), (703, "x", "-")]


@pytest.mark.parametrize("target, limit, budget", [(0.5, 4.0, 1.0), (0.9, 1.5, 2.3), (0.0, 100.0, 1.0), (0.5, 4.0, "cover")])
def test_mixing_is_that_of_an_independent_bisection(spark, target, limit, budget):
    rows = mixed_rows()
    docs = spark.createDataFrame([(*r, 1.0) for r in rows], "doc_id long, text string, source string, weight double").repartition(5)
    got = [tuple(r) for r in mixing.mix(docs, target=target, limit=limit, budget=budget).collect()]
    want = plain_mix(rows, target, limit, budget)
    assert sorted(((*r[:3], r[4]) for r in got), key=str) == sorted(((*r[:3], r[4]) for r in want), key=str)
    assert all(abs(a[3] - b[3]) < 5e-9 for a, b in zip(sorted(got, key=str), sorted(want, key=str)))


def test_quality_votes_are_those_of_plain_neighbours(spark):
    rng = np.random.default_rng(2)
    word = lambda: "".join(rng.choice(list("abcdefgh"), 5))
    good = [" ".join(word() for _ in range(30)) + "." for _ in range(25)]
    bad = ["$$$ !!! " * 10 + word() for _ in range(25)]
    texts = [*good, *bad, good[0], good[0], bad[1], None, "", "x" * 50_000]
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, "null id"), (3, good[7])]
    labels = [(i, 1 if i < 25 else 0) for i in range(52)] + [(60, None), (None, 1), (4, 1)]
    docs = spark.createDataFrame([(*r, 9.0) for r in rows], "doc_id long, text string, quality double")
    marks = spark.createDataFrame([(*x, 1) for x in labels], "doc_id long, quality int, text int")
    got = [(r.doc_id, r.held_out, r.score, r.predicted) for r in quality.classify(docs, marks).collect()]
    held = lambda i: zlib.crc32(("" if i is None else str(i)).encode()) % 5 == 0
    told = {i: v for i, v in labels if i is not None and v is not None and not held(i)}
    taught = [(t, told[i]) for i, t in rows if i in told]
    terms = np.array([quality.term_counts(t).astype(np.float16) for t, _ in taught], float)
    idf = np.log((1 + len(terms)) / (1 + (terms > 0).sum(axis=0))) + 1

    def unit(x):
        return x / np.linalg.norm(x, axis=-1, keepdims=True)

    space = unit((terms * idf).astype(np.float32).astype(float))
    axes = np.linalg.svd(space, full_matrices=False)[2][:64].T
    known = unit(unit(terms * idf) @ axes)
    want = []
    for i, t in rows:
        own = unit(unit(quality.term_counts(t).astype(float) * idf) @ axes)
        c = sorted(((round(float(own @ k), 9), y) for k, (_, y) in zip(known, taught)), reverse=True)
        near = [(x, y) for x, y in c if x >= c[14][0]]
        w = [max(x, 1e-6) ** 8 for x, _ in near]
        want.append((i, held(i), sum(a * y for a, (_, y) in zip(w, near)) / sum(w)))
    assert len(got) == len(want)
    for g, w in zip(sorted(got, key=lambda r: (str(r[0]), r[2])), sorted(want, key=lambda r: (str(r[0]), r[2]))):
        assert g[:2] == w[:2] and abs(g[2] - w[2]) < 1e-5 and g[3] == (g[2] >= 0.3)
    again = [(r.doc_id, r.held_out, r.score, r.predicted) for r in quality.classify(docs.repartition(7), marks).collect()]
    assert sorted(again, key=str) == sorted(got, key=str)


def made_page(rng, host, k):
    """(html, main text): a page of a host's template, which differs by host, from a generator that knows what the article is."""
    words = lambda n: " ".join("".join(rng.choice(list("abcdefghij"), 6)) for _ in range(n))
    blocks = [f"{words(6)} & co", *(words(int(rng.integers(12, 40))) for _ in range(int(rng.integers(2, 5))))]
    inner = f"<h1>{html.escape(blocks[0])}</h1>" + "".join(f"<p>{b[:20]}<b>{b[20:30]}</b>{b[30:]}\n </p>" for b in blocks[1:])
    frames = [
        f'<body><nav><a href="/">{words(4)}</a></nav><article>{inner}</article><footer>{words(20)}</footer>',
        f'<body><div id="page"><div class="main-menu">{words(30)}</div><div class="post-{k}">{inner}<div class="comments">{words(60)}</div></div><div class="sidebar">{words(50)}</div></div>',
        f'<table><tr><td class="nav-left">{words(30)}</td><td class="story"><div class="text">{inner}</div></td><td><ul class="related-links">{words(40)}</ul></td></tr></table><div class="cookie-notice">{words(70)}</div>',
        f'<body><main><div id="a{k}"><section class="entry">{inner}<form>{words(9)}</form><span class="ad">{words(5)}</span></section></div><aside>{words(40)}</aside></main>',
    ]
    return frames[host % 4], "\n\n".join(blocks)


def test_pages_whose_hosts_differ(spark):
    rng = np.random.default_rng(8)
    made = [(k, host, *made_page(rng, host, k)) for k, host in enumerate(h for h in range(8) for _ in range(6))]
    rows = [(k, f"https://www.h{host}.example/{k}", page, 1) for k, host, page, _ in made]
    got = html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string, path int").repartition(3)).collect()
    assert {r.page_id: r.text for r in got} == {k: text for k, _, _, text in made}


def test_names_are_told_by_whole_words():
    bad = ["ad", "ad-banner", "shareButtons", "site-footer", "sidebar-right", "related_posts", "comment-list", "cookie-notice x", "AD2", "article-footer"]
    good = ["market-share", "legal-analysis", "social-science", "menuet", "post", "adage", "research", "article-header", "search-for-truth", ""]
    assert [html_extract._boilerplate(n) for n in bad] == [True] * len(bad)
    assert [html_extract._boilerplate(n) for n in good] == [False] * len(good)
    page = '<body><article><p>One <span class="ad">Buy <span>now</span></span>two<a class="share-links" href=x>Tweet</a>.</p><div class="market-share"><p>Shares of markets.</p></div></article>'
    assert html_extract.main_text(html_extract.parse(page), None) == "One two.\n\nShares of markets."
    lead = '<body><div class="post"><div class="intro"><p>The lead of it.</p></div><div class="post-content"><p>' + "The long text. " * 20 + "</p></div></div><div><p>Else.</p></div>"
    assert html_extract.main_text(html_extract.parse(lead), None) == "The lead of it.\n\n" + ("The long text. " * 20).strip()
    deep = "<div>" * 2000 + "<p>" + "word " * 200_000
    assert len(html_extract.main_text(html_extract.parse(deep), None)) == 5 * 200_000 - 1


def test_topk_of_repeated_ids(spark):
    rng = np.random.default_rng(6)
    rows = [(i // 2, rng.standard_normal(4).round(1).tolist()) for i in range(300)] + [(50, [1.0, 2.0, 3.0, 4.0])] * 3 + [(51, [1.0, 2.0, 3.0, 4.0])] * 2
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    ints = [(i, tuple(math.floor(256 * float(np.float32(x))) for x in v)) for i, v in rows]
    want = Counter()
    for q in {x for x in ints if x[0] % 50 == 0}:
        s = sorted((-sum(a * b for a, b in zip(q[1], v)), i) for i, v in ints if i != q[0])[:5]
        want.update((q[0], r + 1, i, -x) for r, (x, i) in enumerate(s))
    for size in (1000, 37):
        assert Counter(map(tuple, topk.top_k(df, df.where("vec_id % 50 = 0"), shard_rows=size, block_rows=3).collect())) == want


def test_hot_buckets_are_dealt_again(spark):
    rng = np.random.default_rng(4)
    base = int(rng.integers(0, 1 << 62))
    codes = {base ^ sum(1 << int(b) for b in rng.integers(0, 64, int(rng.integers(0, 9)))) for _ in range(300)}
    codes |= {c ^ (1 << int(rng.integers(0, 64))) for c in list(codes)[:200]}
    signed = [c - (1 << 64) if c >> 63 else c for c in codes]
    pairs = {(a, b) for a in signed for b in signed if a < b and bin((a ^ b) & ((1 << 64) - 1)).count("1") <= 3}

    def joined(links):
        up = {c: c for c in signed}

        def root(x):
            while up[x] != x:
                x = up[x]
            return x

        for a, b in links:
            a, b = root(a), root(b)
            up[max(a, b)] = min(a, b)
        return {c: root(c) for c in signed}

    frame = spark.createDataFrame([(c,) for c in signed], "fp long")
    for hot in (1 << 16, 20, 1):
        got = [tuple(r) for r in simhash.fingerprint_links(frame, hot=hot).collect()]
        assert all((min(p), max(p)) in pairs or joined(pairs)[p[0]] == joined(pairs)[p[1]] for p in got)
        assert joined(got) == joined(pairs), hot


def odd_documents():
    rng = np.random.default_rng(12)
    words = [f"word{i}" for i in range(300)]
    text = lambda n: " ".join(rng.choice(words, n)) + "."
    rows = [(i, text(40), "en", f"s{i % 3}", 1) for i in range(30)]
    rows += [(100 + i, rows[i][1], "fr", "copy", 2) for i in range(8)]
    rows += [(3, "another text of one id " + text(30), "en", "s0", 3), (3, rows[3][1], "en", "s0", 3), (None, None, None, None, None), (None, rows[5][1], None, "s1", 0), (200, "", "de", None, 0), (201, None, "de", "s2", 0), (202, "long " + text(20_000), "en", "s1", 9)]
    return [*rows, rows[0], rows[0]]


def test_pipeline_stage_by_stage(spark, tmp_path):
    public_tokenizers = pytest.importorskip("public_tokenizers")
    import tokenizers

    import corpus_pipeline as cp

    rows = odd_documents()
    labels = [(i, 1) for i in range(30)] + [(100, 1), (202, 1), (500, 0)]
    spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(str(tmp_path / "labels.parquet"))
    spark.createDataFrame(rows, SCHEMA).repartition(3).write.parquet(str(tmp_path / "documents.parquet"))
    docs = spark.read.parquet(str(tmp_path / "documents.parquet"))
    frames = [docs]
    for k, (_, stage) in enumerate(cp.STAGES):
        stage(spark, frames[-1], str(tmp_path)).write.parquet(str(tmp_path / f"stage{k}"))
        frames.append(spark.read.parquet(str(tmp_path / f"stage{k}")))
    assert all(f.columns == docs.columns for f in frames[:-1])
    lists = [[tuple(r) for r in f.collect()] for f in frames]
    key = lambda r: str(r)
    # 1: those that the classifier scores below the threshold go
    scored = {(r.doc_id, r.predicted, r.score) for r in quality.classify(docs, spark.read.parquet(str(tmp_path / "labels.parquet"))).collect()}
    gone = Counter(i for i, p, _ in scored if not p)
    assert set(lists[1]) <= set(lists[0]) and all(Counter(lists[1])[r] in (0, Counter(lists[0])[r]) for r in lists[0])
    assert all(r in lists[1] for r in lists[0] if r[0] not in gone)
    # 2: one of each group
    fp = {r: simhash.fingerprint(r[1]) for r in lists[1]}
    kept, left = [], list(dict.fromkeys(sorted(lists[1], key=key)))
    while left:
        group = [left.pop()]
        for g in group:
            near = [r for r in left if bin(fp[g] ^ fp[r]).count("1") <= 3]
            left = [r for r in left if r not in near]
            group += near
        kept.append(group)
    assert len(lists[2]) == len(kept)
    for r in lists[2]:
        (group,) = (g for g in kept if r in g)
        assert r[0] == min((x[0] for x in group if x[0] is not None), default=None)
    assert any(r[0] == 3 and r[1].startswith("another") for r in lists[2])
    # 3: copies by an independent bisection
    want = plain_mix([(r[0], r[1], r[3]) for r in lists[2]], 0.5, 4.0, "cover")
    assert Counter(lists[3]) == Counter({r: w[4] for r, w in zip(lists[2], want)}) and all(w[4] >= 1 for w in want)
    # 4: the library's ids
    own = tokenizers.Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    own.no_truncation()
    own.no_padding()
    ids = {t: own.encode(t or "", add_special_tokens=False).ids for _, t, *_ in lists[3]}
    assert Counter((r.doc_id, r.source, r.n_tokens, tuple(r.ids)) for r in frames[4].collect()) == Counter((r[0], r[3], len(ids[r[1]]), tuple(ids[r[1]])) for r in lists[3])
    empty = spark.createDataFrame([], SCHEMA)
    for _, stage in cp.STAGES:
        empty = stage(spark, empty, str(tmp_path))
        assert empty.count() == 0
