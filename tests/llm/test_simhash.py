import numpy as np
import xxhash

from walkrank.llm import simhash
from walkrank.llm.components import components, local_components


def plain(text):
    words = (text or "").encode().lower().split()
    if not words:
        return 0
    shingles = [b" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))]
    h = [xxhash.xxh64_intdigest(s, 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


def groups(nodes, links):
    up = {n: n for n in nodes}

    def root(n):
        while up[n] != n:
            n = up[n]
        return n

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {n: root(n) for n in nodes}


def test_fingerprints():
    for t in (None, "", "One two", "a b c", "the Cat sat\non the\x0bmat again and again", "É é ß " * 40):
        assert simhash.fingerprint(t) == plain(t)


def test_tree_finds_every_link():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 1 << 63, 60, dtype=np.uint64)
    codes = np.unique(np.concatenate([base] + [base ^ (np.uint64(1) << rng.integers(0, 64, 60).astype(np.uint64)) for _ in range(12)]))
    bucket = rng.integers(0, 3, len(codes))
    got = {tuple(sorted(p)) for u, v in simhash.GrayTree(bucket, codes).links(3) for p in zip(u.tolist(), v.tolist())}
    want = {(i, j) for i in range(len(codes)) for j in range(i + 1, len(codes)) if bucket[i] == bucket[j] and bin(int(codes[i]) ^ int(codes[j])).count("1") <= 3}
    assert got == want and len(want) > 50


def test_components(spark):
    rng = np.random.default_rng(2)
    links = [tuple(map(int, x)) for x in rng.integers(0, 300, (260, 2))] + [(i, i + 1) for i in range(1000, 1060)]
    want = {n: c for n, c in groups({n for e in links for n in e}, links).items()}
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert all(want[n] == c for n, c in got.items()) and {n for n, c in want.items() if n != c} <= set(got)
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0
    assert local_components(4, np.array([3, 1]), np.array([1, 0])).tolist() == [0, 0, 2, 0]


def test_groups_are_those_of_brute_force(spark):
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in range(400)]
    texts = [" ".join(rng.choice(words, 120)) for _ in range(25)]
    rows, k = [], 0
    for t in texts:
        for _ in range(4):
            parts = t.split()
            for _ in range(int(rng.integers(0, 3))):
                parts[int(rng.integers(0, len(parts)))] = "zz"
            rows.append((k, " ".join(parts)))
            k += 1
    rows += [(900, None), (901, ""), (5, rows[5][1]), (None, rows[0][1])]
    got = simhash.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(got) == len(rows)
    fp = {i: plain(t) for i, t in rows if i is not None}
    want = groups(fp, [(a, b) for a in fp for b in fp if a < b and bin(fp[a] ^ fp[b]).count("1") <= 3])
    for r in got:
        if r.doc_id is None:
            assert r.component_id == want[0]
        else:
            assert r.fingerprint == f"{fp[r.doc_id]:016x}" and r.component_id == want[r.doc_id]
    kept = simhash.keep_first(spark.createDataFrame([(*r, "s") for r in rows], "doc_id long, text string, fp string"))
    assert kept.columns == ["doc_id", "text", "fp"]
    assert sorted(r.doc_id for r in kept.where("doc_id is not null").collect()) == sorted({c for c in want.values()})
    assert simhash.near_duplicates(spark.createDataFrame([], "doc_id long, text string")).count() == 0
