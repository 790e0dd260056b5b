"""The spelling of words: an n-gram model over groups of bytes, as tables of a fixed size.

GROUPS groups: a letter each, digits, other ASCII, lead and continuation bytes, the word's start and its end; inside a group all bytes
that a word can hold have equal shares. Order ORDER, smoothed by interpolation of the Witten-Bell kind down to equal shares of groups. The
tables hold the sum of GROUPS ** n entries, n up to ORDER, whatever the corpus.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map

ORDER = 4
#: Bits of a group's number.
BITS = 5
GROUPS = 1 << BITS
START, END, DIGIT, OTHER, LEAD, CONTINUED = range(6)


def _groups() -> tuple[np.ndarray, np.ndarray]:
    """Group of each byte, and log10 of a byte's share of its group. Space and line end, which no word holds, mark its start and end."""
    of = np.full(256, OTHER, dtype=np.int64)
    of[48:58], of[97:123], of[128:192], of[192:] = DIGIT, np.arange(6, GROUPS), CONTINUED, LEAD
    of[32], of[10] = START, END
    possible = np.ones(256, dtype=bool)
    possible[9], possible[11:14], possible[65:91] = False, False, False
    return of, -np.log10(np.bincount(of[possible], minlength=GROUPS)[of])


GROUP, WITHIN = _groups()


def _marked(words: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bytes of all words with their marks, the place of each in its word, and the words' starts."""
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 2
    first = np.cumsum(sizes) - sizes
    raw = np.frombuffer(b" " + b"\n ".join(words) + b"\n", dtype=np.uint8)
    return raw, np.arange(len(raw)) - np.repeat(first, sizes), first


def _keys(groups: np.ndarray, order: int) -> Iterator[tuple[int, np.ndarray]]:
    """(n, the last n groups up to each place as a number), n = 1..order."""
    key = np.zeros(len(groups), dtype=np.int64)
    for n in range(1, order + 1):
        key = np.concatenate(([0], key[:-1] & ((1 << BITS * (n - 1)) - 1))) << BITS | groups
        yield n, key


class Spelling:
    """log10 probability of the last group of each n-gram, by n."""

    def __init__(self, tables: list[np.ndarray]):
        self.tables = tables

    @classmethod
    def train(cls, counts: list[np.ndarray]) -> Spelling:
        """From counts of n-grams by their numbers, n = 1, 2, .."""
        p = np.full(GROUPS, 1.0 / (GROUPS - 1))
        p[START] = 0.0  # the start is never told
        tables = []
        for n, c in enumerate(counts):
            c = c.astype(np.float64).reshape(-1, GROUPS).copy()
            c[:, START] = 0.0
            total, kinds = c.sum(axis=1, keepdims=True), (c > 0).sum(axis=1, keepdims=True)
            # the shorter contexts' shares, for each context that they end
            below = np.broadcast_to(p.reshape(1, -1, GROUPS), (GROUPS if n else 1, max(1, GROUPS ** (n - 1)), GROUPS)).reshape(-1, GROUPS)
            p = np.where(total > 0, (c + kinds * below) / np.maximum(total + kinds, 1), below)
            with np.errstate(divide="ignore"):
                tables.append(np.where(p > 0, np.log10(np.maximum(p, 1e-300)), 0.0).astype(np.float32).reshape(-1))
        return cls(tables)

    def spell(self, words: list[bytes]) -> np.ndarray:
        """log10 probability of each word's bytes and its end."""
        out = np.empty(len(words))
        ends, at = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 2), 0
        while at < len(words):
            begin = ends[at - 1] if at else 0
            upto = min(len(words), int(np.searchsorted(ends, begin + (1 << 20))) + 1)
            raw, place, first = _marked(words[at:upto])
            value = WITHIN[raw]
            for n, key in _keys(GROUP[raw], len(self.tables)):
                own = place >= 1 if n == len(self.tables) == 1 else place >= n - 1 if n == len(self.tables) else place == n - 1
                if n > 1 or len(self.tables) == 1:
                    value[own] += self.tables[n - 1][key[own]]
            out[at:upto] = np.add.reduceat(value, first)
            at = upto
        return out


def train(words: DataFrame, order: int = ORDER) -> Spelling:
    """The model of words (key binary), each once; tasks count in tables of a fixed size."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = [np.zeros(GROUPS**n, np.int64) for n in range(1, order + 1)]
        for b in batches:
            if b.num_rows:
                raw, place, _ = _marked(b.column("key").to_pylist())
                for n, key in _keys(GROUP[raw], order):
                    counts[n - 1] += np.bincount(key[place >= n - 1], minlength=GROUPS**n)
        for n, c in enumerate(counts):
            some = np.flatnonzero(c)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), n, np.int32)), pa.array(some.astype(np.int64)), pa.array(c[some])], names=["n", "key", "c"])

    table = arrow_map(words.select("key"), work, "n int, key bigint, c bigint").groupBy("n", "key").agg(F.sum("c").alias("c")).toArrow()
    n, key, c = (table.column(x).to_numpy() for x in ("n", "key", "c"))
    counts = []
    for k in range(order):
        counts.append(np.zeros(GROUPS ** (k + 1), np.int64))
        counts[k][key[n == k]] = c[n == k]
    return Spelling.train(counts)
