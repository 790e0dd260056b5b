"""The language model against a plain one, as a distribution, and whatever is hot."""

import math
import tempfile
import zlib
from collections import Counter

import numpy as np
import pandas as pd
import pytest

from walkrank.llm import eftrie, lm, spelling

DATA = "/root/testdata/sf0.01"


def held(i):
    return zlib.crc32(("" if i is None else str(i)).encode()) % 10 == 0


def test_elias_fano():
    rng = np.random.default_rng(0)
    for n, most in ((1, 0), (7, 3), (1000, 40), (900, 10**6), (900, 10**14)):
        v = np.sort(rng.integers(0, most + 1, n))
        assert (eftrie.EliasFano.of(v).at(np.arange(n)) == v).all()


def test_trie_finds_what_it_holds_from_a_mapped_file():
    rng = np.random.default_rng(1)
    triples = sorted(set(map(tuple, rng.integers(0, 40, (3000, 3)).tolist())))
    pairs = sorted({t[:2] for t in triples})
    words = sorted({t[0] for t in triples})
    codes = [np.arange(len(x), dtype=np.uint16) for x in (words, pairs, triples)]
    trie = eftrie.Trie.of([np.array(words), np.array([p[1] for p in pairs]), np.array([t[2] for t in triples])], [np.array([words.index(p[0]) for p in pairs]), np.array([pairs.index(t[:2]) for t in triples])], codes)
    with tempfile.TemporaryFile() as f:
        f.write(trie.pack())
        f.flush()
        trie = eftrie.Trie.open(f)
    asked = rng.integers(0, 45, (5000, 3))
    one = trie.roots(asked[:, 0])
    two = trie.child(0, one, asked[:, 1])
    three = trie.child(1, two, asked[:, 2])
    at = {t: k for k, t in enumerate(triples)}
    assert three.tolist() == [at.get(tuple(t), -1) for t in asked.tolist()]
    empty = eftrie.Trie.unpack(eftrie.Trie.of([np.zeros(0, np.int64)] * 3, [np.zeros(0, np.int64)] * 2, [np.zeros(0, np.uint16)] * 3).pack())
    assert empty.child(0, empty.roots(np.array([1, 2])), np.array([1, 2])).tolist() == [-1, -1]


def plain_spelling(words, order=spelling.ORDER):
    """log10 probability of a word by dictionaries."""
    counts = [Counter() for _ in range(order + 1)]
    marked = lambda w: [int(spelling.GROUP[x]) for x in b" " + w + b"\n"]
    for w in words:
        m = marked(w)
        for n in range(1, order + 1):
            counts[n].update(tuple(m[i - n + 1 : i + 1]) for i in range(max(1, n - 1), len(m)))
    follow = [{} for _ in range(order + 1)]
    for n in range(1, order + 1):
        for g, c in counts[n].items():
            t, k = follow[n].get(g[:-1], (0, 0))
            follow[n][g[:-1]] = t + c, k + 1

    def p(g):
        below = p(g[1:]) if len(g) > 1 else 1 / (spelling.GROUPS - 1)
        if g[:-1] not in follow[len(g)]:
            return below
        total, kinds = follow[len(g)][g[:-1]]
        return (counts[len(g)][g] + kinds * below) / (total + kinds)

    def spell(w):
        m = marked(w)
        return sum(math.log10(p(tuple(m[max(0, i - order + 1) : i + 1]))) + float(spelling.WITHIN[(b" " + w + b"\n")[i]]) for i in range(1, len(m)))

    return spell


def test_spelling_is_a_distribution(spark):
    words = [b"abc", b"abd", b"b", b"cab", b"abcab", b"12", b"\xc3\xa9t\xc3\xa9", b"a.b"]
    model = spelling.train(spark.createDataFrame([(w,) for w in words], "key binary"))
    own = plain_spelling(words)
    probe = [*words, b"zz", b"", b"abcabcab" * 400, b"99\xff"]
    assert np.allclose(model.spell(probe), [own(w) for w in probe], rtol=1e-5, atol=1e-5)
    for n, table in enumerate(model.tables):
        told = np.where(np.arange(len(table)) % spelling.GROUPS == spelling.START, 0.0, 10.0 ** table.astype(float))
        assert np.allclose(told.reshape(-1, spelling.GROUPS).sum(axis=1), 1, atol=1e-4), n
    # bytes that words can hold, and the end
    assert abs(sum(10.0 ** spelling.WITHIN[x] for x in range(256) if x not in (9, 11, 12, 13) and not 65 <= x <= 90) - spelling.GROUPS) < 1e-9


class Plain:
    """The whole model by dictionaries; rows (doc_id, text)."""

    def __init__(self, rows):
        self.c = [Counter() for _ in range(4)]
        for i, t in rows:
            if not held(i):
                w = [lm.EDGE, lm.EDGE, *lm.split(t), lm.EDGE]
                for k in range(2, len(w)):
                    for n in (1, 2, 3):
                        self.c[n][tuple(w[k - n + 1 : k + 1])] += 1
        self.ends = self.c[1][lm.EDGE,]
        self.n = sum(self.c[1].values())
        self.words = {w[0]: c for w, c in self.c[1].items() if w[0] != lm.EDGE}
        self.spell = plain_spelling(self.words)
        self.end_p = (self.ends + 0.5) / (self.n + 1.0)
        self.before = [Counter(), Counter(), Counter()]
        for n in (2, 3):
            for g, c in self.c[n].items():
                self.before[n - 1][g[:-1]] += c
        kinds, once = len(self.words), sum(c == 1 for c in self.words.values())
        self.discount = (once + 0.5) / (kinds + 1.0)
        self.spread = self.discount * max(kinds, 1) / max(1, self.n - self.ends)

    def alone(self, w):
        if w == lm.EDGE:
            return self.end_p
        s = 10.0 ** self.spell(w)
        if self.words:
            s = max(self.words.get(w, 0) - self.discount, 0) / (self.n - self.ends) + self.spread * s
        return s * (1 - self.end_p)

    def p(self, u, v, w, alone=None):
        up = self.c[3][u, v, w] + lm.KAPPA * self.c[2][v, w] + lm.G * (self.alone(w) if alone is None else alone)
        return up / (self.before[2][u, v] + lm.KAPPA * self.before[1][v,] + lm.G)

    def row(self, i, t):
        own = [*lm.split(t), lm.EDGE]
        w = [lm.EDGE, lm.EDGE, *own]
        v = len(self.words) + (1 if self.ends else 0)
        base = sum(math.log10((self.c[1][x,] + 0.1) / (self.n + 0.1 * (v + 1))) for x in own)
        return str(i), held(i), len(own), sum(self.c[1][x,] > 0 for x in own), self.n, base, sum(math.log10(self.p(*w[k - 2 : k + 1])) for k in range(2, len(w)))


def rows_of_documents(n):
    docs = pd.read_parquet(f"{DATA}/documents.parquet").head(n)[["doc_id", "text"]]
    return [*((int(i), t) for i, t in docs.itertuples(index=False)), (5000, None), (5001, ""), (3, docs.text[3]), (3, "other text"), (None, "a b"), (None, "a b"), (0, "unheard-of é世 99")]


def compare(got, rows):
    plain = Plain(rows)
    got = sorted((str(r.doc_id), r.held_out, r.n_tokens, r.n_known, r.train_tokens, r.base_score, r.score) for r in got)
    want = sorted(plain.row(*r) for r in rows)
    assert [g[:5] for g in got] == [w[:5] for w in want]
    assert all(abs(g[5] - w[5]) < 1e-8 * max(1, -w[5]) for g, w in zip(got, want))
    assert all(abs(g[6] - w[6]) < 5e-4 * w[2] + 1e-3 for g, w in zip(got, want)), max(abs(g[6] - w[6]) / w[2] for g, w in zip(got, want))
    return plain


def test_scores_equal_those_of_a_plain_model(spark):
    rows = rows_of_documents(120)
    frame = spark.createDataFrame([(*r, 1.0, 2) for r in rows], "doc_id long, text string, score double, part int")
    plain = compare(lm.score(frame).collect(), rows)
    # what follows a context sums to one: known words, the end, and the rest by spelling
    some = [w for w, _ in Counter(plain.words).most_common(3)]
    for u, v in ((lm.EDGE, lm.EDGE), (lm.EDGE, some[0]), (some[0], some[1]), (b"never", b"seen"), next(g[:2] for g in plain.c[3] if lm.EDGE not in g[:2])):
        known = sum(plain.p(u, v, w) for w in [*plain.words, lm.EDGE])
        rest = plain.spread * (1 - sum(10.0 ** plain.spell(w) for w in plain.words)) * (1 - plain.end_p)
        den = plain.before[2][u, v] + lm.KAPPA * plain.before[1][v,] + lm.G
        # all discounts together are spread, but for what words that occur once lack
        assert abs(known + lm.G * rest / den - 1) < 1e-6


@pytest.mark.parametrize("hot", [3, 40])
def test_no_score_depends_on_what_is_hot_or_on_parts_and_runs(spark, monkeypatch, hot):
    line = "one very common line of the corpus "
    rows = [*rows_of_documents(40), *((7000 + i, line * 30 + f"w{i}") for i in range(30)), (8000, "the " * 5000)]
    monkeypatch.setattr(lm, "HOT_WORDS", hot)
    monkeypatch.setattr(lm, "RUN", 2000)
    frame = spark.createDataFrame(rows, "doc_id long, text string").repartition(3, "doc_id")
    compare(lm.score(frame, part_bytes=4000 if hot == 40 else 1 << 20).collect(), rows)


def test_empty_and_untaught_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string")
    assert lm.score(none).count() == 0
    alone = lm.score(spark.createDataFrame([(None, "x y")], "doc_id long, text string")).collect()
    assert alone[0].train_tokens == 0 and alone[0].n_known == 0 and math.isfinite(alone[0].score)
    long = spark.createDataFrame([(1, "ab " * 300_000), (2, "q" * 100_000), (4, " \t\n ")], "doc_id int, text string")
    got = {r.doc_id: r for r in lm.score(long).collect()}
    assert got[1].n_tokens == 300_001 and got[2].n_tokens == 2 and got[4].n_tokens == 1 and all(math.isfinite(r.score) for r in got.values())


def test_order_of_words_counts(spark):
    ids = iter(i for i in range(1000) if not held(i))
    rows = [(next(ids), "red fox sees blue owl") for _ in range(30)] + [(next(i for i in range(1000) if held(i)), "red fox sees blue owl"), (next(i for i in range(500, 1000) if held(i)), "owl blue sees fox red")]
    got = lm.score(spark.createDataFrame(rows, "doc_id long, text string")).where("held_out").orderBy("doc_id").collect()
    assert abs(got[0].base_score - got[1].base_score) < 1e-9
    assert got[0].score > got[1].score + 3 and got[0].score > got[0].base_score
