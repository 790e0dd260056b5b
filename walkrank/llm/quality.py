"""Quality classifier: similarity-weighted voting of labelled nearest neighbours in a latent space.

Terms of a text are its words (lower case, in hashed buckets), its trigrams of byte classes (lower case, upper case, digit, space, line end, kinds of
punctuation, ...) and the bins of a few counts of its words (how many differ, repeat their neighbour,
are capitals, repeat as lines). Term weights are damped counts times inverse document frequency, scaled to length
one; the leading right singular vectors of the labelled texts' matrix span the latent space. The
labelled vectors (at most `per_class` of each class, so of a fixed size bound) are broadcast, and every
document's cosine with all of them is computed in double precision, block by block; its `k` nearest, and all that tie with the kth in DIGITS digits, vote with
weight similarity ** power.

Only rows outside the held-out fold teach. The sample of labelled ids is the least by hash, per class, at most
`per_class` each: a documented bound. Null texts count as empty. Null labels teach nothing; an id with
several labels or texts teaches with each. Without labelled rows every score is the prior 0.5. Repeated rows get one score; an empty table gives an empty
one; other columns, labels among them, are no input.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map, bucket_of, plus

THRESHOLD = 0.3
CLASSES = 13
GRAMS = CLASSES**3
STATS = 8
BINS = 10
#: Buckets that words fall in by hash.
WORDS = 1024
TERMS = GRAMS + STATS * BINS + WORDS
#: Digits that cosines are rounded to: neighbours that tie with the kth all vote.
DIGITS = 9


def _byte_classes() -> np.ndarray:
    out = np.full(256, 10, dtype=np.int64)
    out[:32] = 12
    out[97:123], out[65:91], out[48:58], out[128:] = 0, 1, 2, 11
    for chars, c in ((b" \t", 3), (b"\n\r", 4), (b".", 5), (b",", 6), (b"!?", 7), (b"|", 8), (b"#$%&*@^~+=<>{}[]\\/_`", 9)):
        for x in chars:
            out[x] = c
    return out


BYTE_CLASS = _byte_classes()


def _share(part: float, whole: float) -> int:
    """A bin of a share, finer near 0 and 1."""
    x = part / whole if whole else 0.0
    edges = (0.005, 0.02, 0.06, 0.15, 0.35, 0.65, 0.85, 0.95, 0.995)
    return sum(x > e for e in edges)


def term_counts(text: str | None) -> np.ndarray:
    """Weights of the terms of one text before scaling."""
    raw = (text or "").encode("utf-8")
    out = np.zeros(TERMS, dtype=np.float32)
    c = BYTE_CLASS[np.frombuffer(raw, dtype=np.uint8)]
    if len(c) > 2:
        out[:GRAMS] = np.bincount((c[:-2] * CLASSES + c[1:-1]) * CLASSES + c[2:], minlength=GRAMS)
        np.log1p(out[:GRAMS], out=out[:GRAMS])
    words = raw.split()
    n = len(words)
    lines = [x for x in raw.split(b"\n") if x.strip()]
    letters = int(np.count_nonzero((c == 0) | (c == 1) | (c == 11)))
    stats = (
        _share(len(set(words)), n),
        _share(sum(map(bytes.__eq__, words[1:], words)), n - 1),
        _share(int(np.count_nonzero(c == 1)), letters),
        _share(letters, len(c)),
        _share(len(set(lines)), len(lines)),
        _share(int(np.count_nonzero((c >= 7) & (c <= 9))), n),
        min(BINS - 1, int(np.log2(1 + n)) * 2 // 3),
        min(BINS - 1, int(len(c) / n) if n else 0),
    )
    weight = 2.0 * float(np.sqrt(np.square(out[:GRAMS]).mean() * 200)) or 1.0
    for i, b in enumerate(stats):
        out[GRAMS + i * BINS + b] = weight
    if words:
        many = np.bincount(np.fromiter((zlib.crc32(w) for w in raw.lower().split()), np.int64, n) % WORDS, minlength=WORDS)
        out[GRAMS + STATS * BINS :] = np.log1p(many)
    return out


@dataclass
class Votes:
    """The fitted model: of a fixed size bound, so it may be broadcast."""

    idf: np.ndarray
    axes: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    k: int
    power: float

    def embed(self, terms: np.ndarray) -> np.ndarray:
        x = terms.astype(np.float64) * self.idf
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        z = x @ self.axes
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)

    def score(self, terms: np.ndarray) -> np.ndarray:
        if not len(self.labels):
            return np.full(len(terms), 0.5)
        cosines = np.round(self.embed(terms) @ self.vectors.T, DIGITS)
        k = min(self.k, len(self.labels))
        kth = np.partition(cosines, -k, axis=1)[:, -k, None]
        row, near = np.nonzero(cosines >= kth)
        votes = np.maximum(cosines[row, near], 1e-6) ** self.power
        told = np.bincount(row, votes * self.labels[near], len(terms)) / np.bincount(row, votes, len(terms))
        return np.clip(np.round(told, DIGITS), 0.0, 1.0)


def fit_matrix(terms: np.ndarray, labels: np.ndarray, dims: int = 64, k: int = 15, power: float = 8.0) -> Votes:
    if not len(terms):
        return Votes(np.ones(TERMS, np.float32), np.zeros((TERMS, 1), np.float32), np.zeros((0, 1), np.float32), np.zeros(0), k, power)
    idf = np.log((1.0 + len(terms)) / (1.0 + (terms > 0).sum(axis=0))) + 1.0
    model = Votes(idf, np.zeros((TERMS, 1)), np.zeros((0, 1)), labels.astype(np.float64), k, power)
    x = terms * idf.astype(np.float32)
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    axes = leading(x, min(dims, len(terms)))
    model.axes = axes * np.sign(axes[np.abs(axes).argmax(axis=0), np.arange(axes.shape[1])])
    model.vectors = np.concatenate([model.embed(terms[at : at + 256]) for at in range(0, len(terms), 256)])
    return model


def leading(x: np.ndarray, dims: int, more: int = 16, rounds: int = 10) -> np.ndarray:
    """The leading right singular vectors of x, by subspace iteration from a fixed start."""
    if len(x) <= dims + more:
        return np.linalg.svd(x.astype(np.float64), full_matrices=False)[2][:dims].T
    q = np.random.default_rng(7).standard_normal((x.shape[1], dims + more)).astype(np.float32)
    for _ in range(rounds):
        q = np.linalg.qr(x.T @ (x @ q))[0]
    values, turn = np.linalg.eigh((y := (x @ q).astype(np.float64)).T @ y)
    return q @ turn[:, np.argsort(-values)[:dims]]


def _terms(rows: DataFrame) -> DataFrame:
    """(label, terms binary) of rows (label, text)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [term_counts(t.as_py()).astype(np.float16).tobytes() for t in b.column("text")]
            yield pa.RecordBatch.from_arrays([b.column("label"), pa.array(got, pa.binary())], names=["label", "terms"])

    return arrow_map(rows, work, "label int, terms binary")


def fit(docs: DataFrame, labels: DataFrame, label: str = "quality", fold: int = 5, per_class: int = 2048, **more) -> Votes:
    """Fits on labelled rows outside the held-out fold (ids whose crc32 is 0 modulo `fold`)."""
    known = labels.select(F.col("doc_id").alias("__id"), F.col(label).cast("int").alias("label")).where(F.col("label").isin(0, 1) & F.col("__id").isNotNull()).where(bucket_of(F.col("__id"), fold) != 0).distinct()
    order = F.xxhash64("__id")
    taught = [known.where(F.col("label") == v).orderBy(order, "__id").limit(per_class) for v in (0, 1)]
    sample = F.broadcast(taught[0].union(taught[1]))
    rows = docs.select(F.col("doc_id").alias("__doc"), F.col("text").cast("string").alias("text")).join(sample, F.col("__doc") == F.col("__id")).select("label", "text")
    # ids may repeat in docs: the bound holds for rows too
    got = _terms(rows).orderBy(F.xxhash64("terms"), "label").limit(2 * per_class).toArrow()
    terms = np.empty((got.num_rows, TERMS), dtype=np.float32)
    for i, t in enumerate(got.column("terms")):
        terms[i] = np.frombuffer(t.as_buffer(), dtype=np.float16)
    return fit_matrix(terms, got.column("label").to_numpy(), **more)


def score_frame(docs: DataFrame, model: Votes, text: str = "text", keep: list[str] | None = None) -> DataFrame:
    """`docs` (or its columns `keep`) with score double; a column of that name is replaced."""
    keep = keep if keep is not None else [c for c in docs.columns if c != "score"]
    source = docs.select(*(F.col(f"`{c}`") for c in keep), F.col(text).cast("string").alias("__text"))
    kept = source.drop("__text").schema
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        votes = shared.value
        for whole in batches:
            for at in range(0, whole.num_rows, 256):
                b = whole.slice(at, 256)
                scores = votes.score(np.array([term_counts(t.as_py()) for t in b.column("__text")], dtype=np.float32))
                yield pa.RecordBatch.from_arrays([*(b.column(f.name) for f in kept.fields), pa.array(scores, pa.float64())], names=[*kept.names, "score"])

    return arrow_map(source, work, plus(kept, score="double"))


def classify(docs: DataFrame, labels: DataFrame, fold: int = 5, **more) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row of docs."""
    scored = score_frame(docs, fit(docs, labels, fold=fold, **more), keep=["doc_id"])
    return scored.select("doc_id", (bucket_of(F.col("doc_id"), fold) == 0).alias("held_out"), "score", F.when(F.col("score") >= THRESHOLD, 1).otherwise(0).alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, **more) -> DataFrame:
    """The rows of docs, whole, that the classifier doesn't reject."""
    scored = score_frame(docs.select([F.col(f"`{c}`") for c in docs.columns if c != "score"]), fit(docs, labels, **more))
    return scored.where(F.col("score") >= THRESHOLD).drop("score")
