"""Language-model scoring: a trigram model of words in Elias-Fano tries, one a part of the corpus's n-grams, mapped into memory.

The model pools counts of three orders. With N training tokens, and c() counts in training texts,

    P(w | u v) = (c(u v w) + KAPPA c(v w) + G p(w)) / (c(u v) + KAPPA c(v) + G),

which sums to one over w because each order's counts of successors sum to the count of their context. p(w) is the share of w among
the training words, less a discount; all discounts together (the share of words that occur once, which estimates that of unseen words)
are spread over all words by their spelling (spelling.py); a text ends with the share that ends have among training
tokens. Before a text stand two edges. So every text has a probability, known words or not, and no count is left out, however rare.

As a text's logarithm is a sum, the numerator of a token and the denominator of its successor are both known where the counts of
(u v w), (v w) and w meet, and one exchange both counts and scores:

1. census(): counts of distinct words, and what may be hot.
2. hot(): exact counts of words with over a 2**-20 share, and of pairs and triples that hold over a share of 1 / (16 parts), so their
   number is bounded by shares, not by the corpus. They are broadcast. This is about traffic alone: no score depends on it.
3. deal(): each run of texts sends every distinct triple once, with the places it occurs at, to the part that its word's hash
   names; a hot word's triples are dealt by their pair, a hot pair's by the whole triple, and hot triples are scored at once. So no part holds a
   hot key.
4. answer(): a part counts its triples, writes its trie (word, then the word before, then the one before that; an n-gram is searched for among the
   successors of its context) with quantised log10 probabilities to an unnamed scratch file, maps that, scores the part's triples
   and answers each run with sums per text. Sums are of integers, so no order of tasks changes them.
5. total(): a run's answers are added up. All must be there, and from the same run: else an error is raised.

Words are told apart by 64-bit hashes, as are pairs and triples that may be hot. Words: runs of bytes other than ASCII white space, A-Z lower-cased.
Null texts are empty (one end token). Rows that repeat id and text get the same result each; a null id counts as empty text in the
fold, so it is held out. Extra columns are ignored. Without training rows the base is that of counts of zero and words are spelled by
equal shares.
"""

from __future__ import annotations

import struct
import tempfile
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import chain, count

import numpy as np
import pyarrow as pa
import xxhash
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm import spelling as spellings
from walkrank.llm.common import arrow_map, bucket_of, cut, shuffle_parts, trim
from walkrank.llm.eftrie import SCALE, Trie, code
from walkrank.llm.spelling import Spelling

KAPPA = 0.002
G = 10.0
#: Words with over one share in so many are broadcast.
HOT_WORDS = 1 << 20
#: Bytes of text a part, and tokens a run.
PART_BYTES = 24 << 20
RUN = 1 << 19
#: Stands for a text's end, and as a context for its start; can't be a word.
EDGE = b"\n"
LOW = np.int64(0xFFFFFFFF)


def split(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8").lower().split()


def word_log10(c: np.ndarray, spelled: np.ndarray, kinds: int, once: int, tokens: int) -> np.ndarray:
    """log10 probability of words with training counts c, given that of their spelling."""
    if not tokens:
        return spelled
    discount = (once + 0.5) / (kinds + 1.0)
    spread = np.log10(discount * max(kinds, 1) / tokens)
    known = np.maximum(c - discount, 0) / tokens
    return np.where(c > 0, np.log10(known + 10.0 ** np.maximum(spread + spelled, -300) + 1e-300), spread + spelled)


# --- numbers of tokens, hashes, packed arrays ---


def runs(texts: pa.Array, most: int) -> Iterator[tuple[int, int, list[bytes], np.ndarray, np.ndarray]]:
    """(start, stop, distinct tokens, their numbers along the texts, tokens a text), about `most` tokens at a time; EDGE is 0 and ends a text."""
    start, size = 0, 0
    index: dict[bytes, int] = defaultdict(count().__next__)
    numbers, sizes = [], []
    for i, t in enumerate(texts):
        own = split(t.as_py())
        own.append(EDGE)
        if not numbers:
            index[EDGE]  # noqa: B018
        numbers.append(np.fromiter(map(index.__getitem__, own), np.int32, len(own)))
        sizes.append(len(own))
        size += len(own)
        if size >= most or i == len(texts) - 1:
            words, now, many = list(index), np.concatenate(numbers).astype(np.int64), np.array(sizes, dtype=np.int64)
            numbers, sizes, own = [], [], None
            index = defaultdict(count().__next__)
            yield start, i + 1, words, now, many
            start, size = i + 1, 0


def mixed(x: np.ndarray) -> np.ndarray:
    """64 bits, each of which depends on all bits of x."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh64_intdigest, words), np.uint64, len(words))


def joined(before: np.ndarray, after: np.ndarray) -> np.ndarray:
    """Hash of a sequence from that of its first word and that of the rest."""
    return mixed(before * np.uint64(0x9E3779B97F4A7C15) + after)


def find(table: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """Places of wanted in a sorted table, or -1."""
    if not len(table):
        return np.full(len(wanted), -1, dtype=np.int64)
    at = np.minimum(np.searchsorted(table, wanted), len(table) - 1)
    return np.where(table[at] == wanted, at, -1)


@dataclass
class Grams:
    """Distinct pairs (word, word before) and triples (place of a pair, word before that), sorted; the triple of each token; tokens in the order of their triples."""

    pair_word: np.ndarray
    pair_before: np.ndarray
    triple_pair: np.ndarray
    triple_before: np.ndarray
    triple_of: np.ndarray | None
    by: np.ndarray | None


def numbered(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(a and b of their distinct pairs, sorted; the number of each place's pair; the places in the order of their pairs), of numbers below 2 ** 32."""
    n = len(a)
    if not n:
        return a, b, np.zeros(0, np.int64), np.zeros(0, np.int64)
    low, place = int(b.max()).bit_length(), n.bit_length()
    if int(a.max()).bit_length() + low + place < 64:  # a value holds its place: sorted as it is
        key = (a << low | b) << place | np.arange(n)
        key.sort()
        by = key & ((1 << place) - 1)
        key >>= place
    else:
        key = a << low | b
        by = np.argsort(key, kind="stable")
        key = key[by]
    new = flags(key)
    of = np.empty(n, np.int64)
    of[by] = np.cumsum(new) - 1
    key = key[new]
    return key >> low, key & ((1 << low) - 1), of, by


def grams(words: np.ndarray, before: np.ndarray, earlier: np.ndarray) -> Grams:
    pair_word, pair_before, pair_of, _ = numbered(words, before)
    triple_pair, triple_before, triple_of, by = numbered(pair_of, earlier)
    return Grams(pair_word, pair_before, triple_pair, triple_before, triple_of, by)


def along(now: np.ndarray, sizes: np.ndarray) -> Grams:
    """The grams of texts; EDGE stands before their first token."""
    first = np.cumsum(sizes) - sizes
    before = np.concatenate(([0], now[:-1]))
    before[first] = 0
    earlier = np.concatenate(([0], before[:-1]))
    earlier[first] = 0
    return grams(now, before, earlier)


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays of whole numbers (narrowed, byte planes apart) or floats, compressed."""
    head, body = [struct.pack("<B", len(arrays))], []
    for a in arrays:
        if a.dtype.kind != "f" and a.dtype != np.uint64:
            top = int(a.max()) if len(a) else 0
            a = a.astype(np.uint8 if top < 1 << 8 else np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64)
        head.append(struct.pack("<cq", a.dtype.char.encode(), len(a)))
        body.append(a.view(np.uint8).reshape(-1, a.itemsize).T.tobytes() if len(a) else b"")
    raw = b"".join(head + body)
    return struct.pack("<q", len(raw)) + pa.compress(raw, codec="zstd", asbytes=True)


def unpack(blob: bytes) -> list[np.ndarray]:
    """Whole numbers come back as narrow as they were sent."""
    raw = pa.decompress(blob[8:], decompressed_size=struct.unpack_from("<q", blob)[0], codec="zstd", asbytes=True)
    n, out = raw[0], []
    at = 1 + 9 * n
    for k in range(n):
        char, size = struct.unpack_from("<cq", raw, 1 + 9 * k)
        kind = np.dtype(char.decode())
        a = np.frombuffer(raw, np.uint8, size * kind.itemsize, at).reshape(kind.itemsize, size).T.copy().view(kind).reshape(size)
        at += size * kind.itemsize
        out.append(a)
    return out


# --- counts ---


def census(rows: DataFrame, share: int) -> DataFrame:
    """(kind, key, c, n) of rows (text, held_out): words (kind 1) with their counts in training and in all texts; pairs (2) and triples (3) by
    hash, with their count n in those runs where it is over one in `share` of the tokens."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            held = b.column("held_out").to_numpy(zero_copy_only=False)
            for start, stop, words, now, sizes in runs(b.column("text"), RUN):
                taught = np.repeat(~held[start:stop], sizes)
                n, c = np.bincount(now, minlength=len(words)), np.bincount(now[taught], minlength=len(words))
                yield of(1, pa.array(words, pa.binary()), c, n)
                g, h, least = along(now, sizes), hashes(words), max(2, len(now) // share)
                many = np.bincount(g.triple_of, minlength=len(g.triple_pair))
                pair_many = np.bincount(g.triple_pair, weights=many, minlength=len(g.pair_word)).astype(np.int64)
                pair_hash = joined(h[g.pair_before], h[g.pair_word])
                for kind, key, m in ((2, pair_hash, pair_many), (3, joined(h[g.triple_before], pair_hash[g.triple_pair]), many)):
                    hot = np.flatnonzero(m >= least)
                    yield of(kind, pa.array([x.tobytes() for x in key[hot]], pa.binary()), np.zeros(len(hot), np.int64), m[hot])

    def of(kind: int, keys: pa.Array, c: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(c), kind, np.int32)), keys, pa.array(c.astype(np.int64)), pa.array(n.astype(np.int64))], names=["kind", "key", "c", "n"])

    return arrow_map(rows.select("text", "held_out"), work, "kind int, key binary, c bigint, n bigint").groupBy("kind", "key").agg(F.sum("c").alias("c"), F.sum("n").alias("n"))


@dataclass
class Model:
    """What all tasks know; its size is bounded by shares."""

    spelling: Spelling
    kinds: int
    once: int
    tokens: int
    ends: int
    parts: int
    #: Hot words: hashes, the commonest first, their training counts and log10 p(w); the order of the hashes.
    words: np.ndarray
    c: np.ndarray
    alone: np.ndarray
    order: np.ndarray
    #: Hot pairs and triples: sorted hashes and training counts.
    pairs: np.ndarray
    pair_c: np.ndarray
    triples: np.ndarray
    triple_c: np.ndarray

    @property
    def n_all(self) -> int:
        return self.tokens + self.ends

    def p(self, c: np.ndarray, spelled: np.ndarray) -> np.ndarray:
        """log10 p(w) of words."""
        return word_log10(c, spelled, self.kinds, self.once, self.tokens) + np.log10(1 - self.end_p())

    def end_p(self) -> float:
        return (self.ends + 0.5) / (self.n_all + 1.0)

    def told(self, c3: np.ndarray, c2: np.ndarray, c1: np.ndarray, alone: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """log10 of tokens' numerators over their successors' denominators (of counts 0 at least), at most 0. An end is followed by a text's start."""
        # without counts the logarithm of p(w) itself, which may be too small for a double
        up = np.where((c3 == 0) & (c2 == 0), np.log10(G) + alone, np.log10(c3 + KAPPA * c2 + G * 10.0 ** np.maximum(alone, -300)))
        return up - np.log10(np.where(ends, self.ends + KAPPA * self.ends, c2 + KAPPA * c1) + G)

    def hot_words(self, h: np.ndarray) -> np.ndarray:
        """Numbers of hot words by their hashes, or -1."""
        at = find(self.words[self.order], h)
        return np.where(at >= 0, self.order[at] if len(self.order) else -1, -1)


def hot(rows: DataFrame, found: DataFrame, model: Model, share: int, total: int) -> Model:
    """The model with its hot words, pairs and triples."""
    spark = rows.sparkSession
    shared = spark.sparkContext.broadcast(model)

    def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        spelling = shared.value.spelling
        for b in batches:
            if b.num_rows:
                words, c = b.column("key").to_pylist(), b.column("c").to_numpy()
                ends = np.fromiter((w == EDGE for w in words), bool, len(words))
                alone = np.where(ends, np.log10(shared.value.end_p()), shared.value.p(c, spelling.spell(words)))
                yield pa.RecordBatch.from_arrays([pa.array(hashes(words).view(np.int64)), b.column("c"), b.column("n"), pa.array(alone)], names=["h", "c", "n", "alone"])

    often = found.where((F.col("kind") == 1) & ((F.col("n") > total / HOT_WORDS) | (F.col("key") == F.lit(EDGE))))
    words = arrow_map(often.select("key", "c", "n"), spell, "h bigint, c bigint, n bigint, alone double").toArrow()  # HOT_WORDS at most
    h, c, n, alone = (words.column(x).to_numpy() for x in ("h", "c", "n", "alone"))
    by = np.lexsort((h, -n))
    model.words, model.c, model.alone = h[by].view(np.uint64), c[by], alone[by]
    model.order = np.argsort(model.words)
    for kind in (2, 3):  # `share` rows at most
        keys = found.where((F.col("kind") == kind) & (F.col("n") > total / share)).select("key").toArrow().column("key").to_pylist()
        table = np.sort(np.frombuffer(b"".join(keys), np.uint64))
        if kind == 2:
            model.pairs, model.pair_c = table, np.zeros(len(table), np.int64)
        else:
            model.triples, model.triple_c = table, np.zeros(len(table), np.int64)
    if not len(model.pairs):
        return model
    asked = spark.sparkContext.broadcast((model.pairs, model.triples))

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs, triples = asked.value
        c = np.zeros(len(pairs) + len(triples), np.int64)
        for b in batches:
            for _, _, words, now, sizes in runs(b.column("text"), RUN):
                h = hashes(words)
                first = np.cumsum(sizes) - sizes
                before = np.concatenate(([0], now[:-1]))
                before[first] = 0
                at = find(pairs, two := joined(h[before], h[now]))
                c[: len(pairs)] += np.bincount(at[at >= 0], minlength=len(pairs))
                before = np.concatenate(([0], before[:-1]))
                before[first] = 0
                some = np.flatnonzero(at >= 0)  # a hot triple's pair is hot
                at = find(triples, joined(h[before[some]], two[some]))
                c[len(pairs) :] += np.bincount(at[at >= 0], minlength=len(triples))
        yield pa.RecordBatch.from_arrays([pa.array(np.flatnonzero(c)), pa.array(c[c > 0])], names=["k", "c"])

    counted = arrow_map(rows.where("not held_out").select("text"), exact, "k bigint, c bigint").groupBy("k").agg(F.sum("c").alias("c")).toArrow()
    both = np.zeros(len(model.pairs) + len(model.triples), np.int64)
    both[counted.column("k").to_numpy()] = counted.column("c").to_numpy()
    model.pair_c, model.triple_c = both[: len(model.pairs)], both[len(model.pairs) :]
    return model


# --- one exchange of n-grams, one of answers ---

CELL = "part int, run bigint, digest bigint, cells int, blob binary"


def cells_of(part: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(part, places of its triples in order) of the parts that have some."""
    by = np.argsort(part, kind="stable")
    own = part[by]
    starts = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1]))) if len(own) else np.zeros(0, np.int64)
    for a, b in zip(starts.tolist(), np.append(starts[1:], len(own)).tolist()):
        yield int(own[a]), by[a:b]


def deal(rows: DataFrame, model: Model) -> DataFrame:
    """CELL rows: each run's triples by part, and one row (a number of cells that isn't null) with its texts' ids and what was scored at once."""
    shared = rows.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m: Model = shared.value
        spelling, n_hot = m.spelling, len(m.words)
        task, at = TaskContext.get().partitionId() << 32, count()
        for b in batches:
            held = b.column("held_out").to_numpy(zero_copy_only=False)
            for start, stop, words, now, sizes in runs(b.column("text"), RUN):
                run, g, h = task | next(at), along(now, sizes), hashes(words)
                # what a retried task would have to repeat
                digest = int(mixed(h[now] + np.arange(len(now), dtype=np.uint64)).sum(dtype=np.uint64).view(np.int64))
                text_of = np.repeat(np.arange(len(sizes)), sizes)
                many = np.bincount(g.triple_of, minlength=len(g.triple_pair))
                places = text_of[g.by]
                del text_of, now
                g.triple_of, g.by, ends = None, None, np.cumsum(many)
                word_at = m.hot_words(h)
                number = word_at.copy()  # of hot words for all, of others in a cell
                pair_hash = joined(h[g.pair_before], h[g.pair_word])
                pair_at = np.where(word_at[g.pair_word] >= 0, find(m.pairs, pair_hash), -1)
                triple_hash = joined(h[g.triple_before], pair_hash[g.triple_pair])
                triple_at = np.where(pair_at[g.triple_pair] >= 0, find(m.triples, triple_hash), -1)
                word_of = g.pair_word[g.triple_pair]
                own = np.zeros((3, len(sizes)))
                now_known = np.flatnonzero(triple_at >= 0)
                if len(now_known):
                    w = word_at[word_of[now_known]]
                    values = code(m.told(m.triple_c[triple_at[now_known]], m.pair_c[pair_at[g.triple_pair[now_known]]], m.c[w], m.alone[w], word_of[now_known] == 0))
                    occurs = spread(ends[now_known] - many[now_known], many[now_known])
                    for k, x in enumerate((values, np.log10(m.c[w] + 0.1), m.c[w] > 0)):
                        own[k] = np.bincount(places[occurs], weights=np.repeat(x, many[now_known]), minlength=len(sizes))
                key = np.where(pair_at[g.triple_pair] >= 0, triple_hash, np.where(word_at[word_of] >= 0, pair_hash[g.triple_pair], mixed(h[word_of])))
                rest = np.flatnonzero(triple_at < 0)
                part = (key[rest] % np.uint64(m.parts)).astype(np.min_scalar_type(m.parts))  # narrow numbers are sorted faster
                cold = np.flatnonzero(word_at < 0)
                spelled = np.zeros(len(words), np.float32)
                if len(cold):
                    spelled[cold] = spelling.spell([words[i] for i in cold.tolist()])
                cells = 0
                for to, places_ in cells_of(part):
                    t = rest[places_]
                    pair, pair_new = g.triple_pair[t], flags(g.triple_pair[t])
                    pairs = pair[pair_new]
                    word_new = flags(g.pair_word[pairs])
                    w, v, u = g.pair_word[pairs][word_new], g.pair_before[pairs], g.triple_before[t]
                    local = np.concatenate((w, v, u))
                    local = np.unique(local[word_at[local] < 0])
                    number[local] = np.arange(n_hot, n_hot + len(local))
                    occurs = spread(ends[t] - many[t], many[t])
                    blob = pack(h[local], number[w], spelled[w[word_at[w] < 0]], lengths(word_new), number[v], lengths(pair_new), number[u], many[t], places[occurs], np.packbits(held[start:stop]))
                    cells += 1
                    yield row(to, run, digest, None, blob)
                ids = pa.BufferOutputStream()
                about = pa.RecordBatch.from_arrays([b.column("doc_id").slice(start, stop - start), pa.array(sizes), pa.array(own[0].astype(np.int64)), pa.array(own[1]), pa.array(own[2].astype(np.int64))], names=["doc_id", "n", "value", "base", "known"])
                with pa.ipc.new_stream(ids, about.schema) as out:
                    out.write_batch(about)
                yield row(run % m.parts, run, digest, cells, ids.getvalue().to_pybytes())
                trim()

    def row(part: int, run: int, digest: int, cells: int | None, blob: bytes) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([run], pa.int64()), pa.array([digest], pa.int64()), pa.array([cells], pa.int32()), pa.array([blob], pa.binary())], names=["part", "run", "digest", "cells", "blob"])

    return arrow_map(rows.select("doc_id", "text", "held_out"), work, CELL)


def flags(sorted_: np.ndarray) -> np.ndarray:
    """Where a sorted array's values begin."""
    return np.concatenate(([True], sorted_[1:] != sorted_[:-1]))


def lengths(starts: np.ndarray) -> np.ndarray:
    return np.diff(np.append(np.flatnonzero(starts), len(starts)))


def spread(starts: np.ndarray, many: np.ndarray) -> np.ndarray:
    """The places starts[i], .., starts[i] + many[i] - 1 of all i."""
    return np.repeat(starts - (np.cumsum(many) - many), many) + np.arange(int(many.sum()))


class Part:
    """One part's cells, counted and scored. Arrays as long as the part's triples are few, narrow or made in pieces."""

    PIECE = 1 << 18

    def __init__(self, model: Model, blobs: list[bytes]):
        m, n_hot = model, len(model.words)
        cells = [unpack(b) for b in blobs]
        known, number = np.unique(np.concatenate([c[0] for c in cells]), return_inverse=True)
        firsts = np.cumsum([0] + [len(c[0]) for c in cells])
        ends = np.cumsum([0] + [len(c[7]) for c in cells])
        key, before, taught = np.empty(ends[-1], np.int64), np.empty(ends[-1], np.int64), np.empty(ends[-1], np.int32)
        spelled, self.places, self.many = [], [], []
        for k, (at, upto) in enumerate(zip(ends[:-1].tolist(), ends[1:].tolist())):
            named = lambda x, first=firsts[k]: np.where(x < n_hot, x, n_hot + number[np.clip(x.astype(np.int64) - n_hot + first, 0, len(number) - 1)]) if len(number) else x.astype(np.int64)
            _, words, own, pairs, second, triples, earlier, many, places, out = cells[k]
            cells[k] = None
            words = named(words)
            spelled.append((words[words >= n_hot], own))
            key[at:upto] = np.repeat(np.repeat(words, pairs) << 32 | named(second), triples)
            before[at:upto] = named(earlier)
            taught[at:upto] = np.add.reduceat(1 - np.unpackbits(out.astype(np.uint8))[places].astype(np.int32), np.cumsum(many, dtype=np.int64) - many)
            self.places.append(places)
            self.many.append(many)
        pairs, pair_of = np.unique(key, return_inverse=True)
        del key
        pair_of <<= 32
        pair_of |= before
        del before
        triples, triple_of = np.unique(pair_of, return_inverse=True)
        del pair_of
        self.triple_of = triple_of.astype(np.int32)
        del triple_of
        c3 = np.bincount(self.triple_of, weights=taught, minlength=len(triples)).astype(np.int32)
        del taught
        self.pair_of = (triples >> 32).astype(np.int32)
        earlier = (triples & LOW).astype(np.uint32)
        del triples
        c2 = np.bincount(self.pair_of, weights=c3, minlength=len(pairs)).astype(np.int64)
        words, self.word_of = np.unique(pairs >> 32, return_inverse=True)
        second = pairs & LOW
        c1 = np.bincount(self.word_of, weights=c2, minlength=len(words)).astype(np.int64)
        h, warm = np.concatenate((m.words, known)), words < n_hot
        c1[warm] = m.c[words[warm]]
        hot = np.flatnonzero(warm[self.word_of])
        at = find(m.pairs, joined(h[second[hot]], h[words[self.word_of[hot]]]))
        c2[hot[at >= 0]] = m.pair_c[at[at >= 0]]
        how = np.zeros(len(words))
        ids, costs = (np.concatenate(x) for x in zip(*spelled))
        how[np.searchsorted(words, ids)] = costs
        alone = m.p(c1, how)
        alone[warm] = m.alone[words[warm]]
        is_end = words == m.hot_words(hashes([EDGE]))[0]
        self.base, self.known = np.log10(c1 + 0.1), c1 > 0
        trie = self.written(m, words, second, earlier, c1, c2, c3, alone, is_end)
        # queries: each distinct triple once
        none = np.zeros(len(words))
        unknown = np.round(-m.told(none, none, none, alone, is_end) * SCALE).astype(np.int64)
        one = trie.roots(words)
        single = np.where(one >= 0, np.append(trie.levels[0][2], 0).astype(np.int64)[one], unknown)
        two = np.empty(len(pairs), np.int64)
        for x in self.pieces(len(pairs)):
            two[x] = trie.child(0, one[self.word_of[x]], second[x])
        double = np.where(two >= 0, np.append(trie.levels[1][2], 0).astype(np.int64)[two], single[self.word_of])
        self.values = np.empty(len(earlier), np.int64)
        for x in self.pieces(len(earlier)):
            three = trie.child(1, two[self.pair_of[x]], earlier[x])
            self.values[x] = np.where(three >= 0, np.append(trie.levels[2][2], 0).astype(np.int64)[three], double[self.pair_of[x]])

    def pieces(self, n: int) -> Iterator[slice]:
        return (slice(at, min(n, at + self.PIECE)) for at in range(0, n, self.PIECE))

    def written(self, m: Model, words: np.ndarray, second: np.ndarray, earlier: np.ndarray, c1: np.ndarray, c2: np.ndarray, c3: np.ndarray, alone: np.ndarray, ends: np.ndarray) -> Trie:
        """The trie of what training texts have, from a file that is mapped into memory and has no name: it goes with the task."""
        keep1, keep2 = np.flatnonzero(c1 > 0), np.flatnonzero(c2 > 0)
        up2 = (np.cumsum(c1 > 0) - 1)[self.word_of[keep2]]
        up3 = (np.cumsum(c2 > 0, dtype=np.int32) - 1)[self.pair_of[c3 > 0]]
        value = lambda c3, c2, k: code(m.told(c3, c2, c1[k], alone[k], ends[k]))
        third = np.empty(len(up3), np.uint16)
        at = 0
        for x in self.pieces(len(c3)):
            own = c3[x] > 0
            pair = self.pair_of[x][own]
            third[at : at + len(pair)] = value(c3[x][own], c2[pair], self.word_of[pair])
            at += len(pair)
        trie = Trie.of(
            [words[keep1], second[keep2], earlier[c3 > 0]], [up2, up3],
            [value(np.zeros(len(keep1)), np.zeros(len(keep1)), keep1), value(np.zeros(len(keep2)), c2[keep2], self.word_of[keep2]), third],
        )
        with tempfile.TemporaryFile() as f:
            f.write(trie.pack())
            f.flush()
            return Trie.open(f)

    def answers(self) -> Iterator[bytes]:
        """Per cell: its texts, and their sums of values, base logarithms and known tokens."""
        at = 0
        for places, many in zip(self.places, self.many):
            triples = np.repeat(self.triple_of[at : at + len(many)], many)
            at += len(many)
            texts, own = np.unique(places, return_inverse=True)
            word = self.word_of[self.pair_of[triples]]
            value, base, known = (np.bincount(own, weights=x, minlength=len(texts)) for x in (self.values[triples], self.base[word], self.known[word]))
            yield pack(np.diff(texts.astype(np.int64), prepend=0), value.astype(np.int64), base, known.astype(np.int64))


def answer(dealt: DataFrame, model: Model) -> DataFrame:
    """CELL rows: each cell's answer to its run, and the rows of ids as they came."""
    shared = dealt.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, list[pa.RecordBatch]] = defaultdict(list)
        for b in batches:
            part = b.column("part").to_numpy()
            header = b.column("cells").is_valid().to_numpy(zero_copy_only=False)
            if header.any():
                yield b.filter(pa.array(header))
            for p in np.unique(part[~header]).tolist():
                held[p].append(b.filter(pa.array(~header & (part == p))))
        for p in list(held):
            table = pa.Table.from_batches(held.pop(p))
            got = Part(shared.value, table.column("blob").to_pylist())
            trim()
            answers = pa.array(list(got.answers()), pa.binary())
            yield from table.drop_columns("blob").append_column("blob", answers).combine_chunks().to_batches()

    return arrow_map(dealt.repartitionById(model.parts, F.col("part")), work, CELL)


def total(answers: DataFrame, id_type: str) -> DataFrame:
    """(doc_id, n_tokens, n_known, base, score): one row for each text."""

    def work(table: pa.Table) -> pa.Table:
        table = table.sort_by("part")
        cells = table.column("cells").to_pylist()
        head = [i for i, c in enumerate(cells) if c is not None]
        if len(head) != 1 or cells[head[0]] != len(cells) - 1 or len(set(table.column("digest").to_pylist())) != 1:
            raise RuntimeError("a run of texts lacks answers or was dealt twice in different ways: the input isn't stable when tasks are retried")
        about = pa.ipc.open_stream(table.column("blob")[head[0]].as_py()).read_all()
        value, base, known = (about.column(x).to_numpy().copy() for x in ("value", "base", "known"))
        for i, blob in enumerate(table.column("blob")):
            if i != head[0]:
                texts, v, b, k = unpack(blob.as_py())
                at = np.cumsum(texts, dtype=np.int64)
                value[at] += v.astype(np.int64)
                base[at] += b
                known[at] += k.astype(np.int64)
        return pa.table({"doc_id": about.column("doc_id"), "n_tokens": about.column("n"), "n_known": known, "base": base, "score": value / -SCALE})

    return answers.groupBy("run").applyInArrow(work, f"doc_id {id_type}, n_tokens bigint, n_known bigint, base double, score double")


def score(docs: DataFrame, fold: int = 10, part_bytes: int = PART_BYTES) -> DataFrame:
    """One row for each row of docs: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    rows = docs.select(F.col("doc_id"), F.col("text").cast("string").alias("text"), (bucket_of(F.col("doc_id"), fold) == 0).alias("held_out"))
    spark = docs.sparkSession
    size = rows.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("b")).first()["b"]
    parts = max(shuffle_parts(spark), -(-size // part_bytes), 1)
    share = 16 * parts
    found = cut(census(rows, share))
    words = found.where((F.col("kind") == 1) & (F.col("key") != F.lit(EDGE)))
    got = found.where("kind = 1").agg(
        F.coalesce(F.sum("n"), F.lit(0)).alias("total"), F.count_if((F.col("c") > 0) & (F.col("key") != F.lit(EDGE))).alias("kinds"), F.count_if((F.col("c") == 1) & (F.col("key") != F.lit(EDGE))).alias("once"),
        F.coalesce(F.sum(F.when(F.col("key") != F.lit(EDGE), F.col("c"))), F.lit(0)).alias("tokens"), F.coalesce(F.sum(F.when(F.col("key") == F.lit(EDGE), F.col("c"))), F.lit(0)).alias("ends"),
    ).first()
    spelling = spellings.train(words.where("c > 0"))
    none = np.zeros(0, np.int64)
    empty = none.view(np.uint64)
    model = Model(spelling, got["kinds"], got["once"], got["tokens"], got["ends"], parts, empty, none, none, none, empty, none, empty, none)
    model = hot(rows, found, model, share, got["total"])
    id_type = dict(rows.dtypes)["doc_id"]
    per = total(answer(deal(rows, model), model), id_type)
    v_all = model.kinds + (1 if model.ends else 0)
    scale = float(np.log10(model.n_all + 0.1 * (v_all + 1)))
    return per.select(
        "doc_id", (bucket_of(F.col("doc_id"), fold) == 0).alias("held_out"), "n_tokens", "n_known", F.lit(model.n_all).cast("long").alias("train_tokens"),
        (F.col("base") - F.col("n_tokens") * scale).alias("base_score"), "score",
    )
