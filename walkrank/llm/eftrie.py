"""Elias-Fano coded n-gram tries whose levels are plain arrays behind one header, so that a file of them can be mapped into memory.

Level n holds the n-grams in path order: last symbols, monotone pointers to their children (Elias-Fano: low bits packed, high
bits unary) and quantised logarithms. A query walks all positions at once: the child of a context is found by successor search
among the symbols between its two pointers.
"""

from __future__ import annotations

import mmap
import struct

import numpy as np

#: Steps of a quantised logarithm to base 10.
SCALE = 2000.0
POP = np.array([bin(x).count("1") for x in range(256)], dtype=np.int64)
SELECT = np.array([[([i for i in range(8) if b >> i & 1] + [0] * 8)[r] for r in range(8)] for b in range(256)], dtype=np.int64)


class EliasFano:
    """A monotone sequence of integers with access to any place."""

    def __init__(self, n: int, low_bits: int, low: np.ndarray, high: np.ndarray):
        self.n, self.low_bits, self.low, self.high = n, low_bits, low, high
        ones = np.bitwise_count(high).astype(np.int64)
        self.before = np.concatenate(([0], np.cumsum(ones)[:-1])) if len(ones) else np.zeros(0, dtype=np.int64)

    @classmethod
    def of(cls, values: np.ndarray) -> EliasFano:
        values = np.asarray(values, dtype=np.uint64)
        n = len(values)
        top = int(values[-1]) if n else 0
        bits = max(0, int(np.floor(np.log2(top / n)))) if n and top > n else 0
        at = np.arange(n, dtype=np.uint64) * np.uint64(bits)
        low = np.zeros(int(n * bits) // 64 + 2, dtype=np.uint64)
        if bits:
            part = values & np.uint64((1 << bits) - 1)
            word, shift = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
            np.bitwise_or.at(low, word, part << shift)
            over = shift + np.uint64(bits) > 64
            np.bitwise_or.at(low, word[over] + 1, part[over] >> (np.uint64(64) - shift[over]))
        ones = (values >> np.uint64(bits)).astype(np.int64) + np.arange(n)
        high = np.zeros((int(ones[-1]) if n else 0) // 64 + 1, dtype=np.uint64)
        np.bitwise_or.at(high, ones >> 6, np.uint64(1) << (ones & 63).astype(np.uint64))
        return cls(n, bits, low, high)

    def at(self, i: np.ndarray) -> np.ndarray:
        word = np.searchsorted(self.before, i, side="right") - 1
        # places of words without ones are passed over: the last word that starts at or before i holds it
        rest = i - self.before[word]
        bits = self.high[word]
        place = np.zeros(len(i), dtype=np.int64)
        byte = (bits & np.uint64(255)).astype(np.int64)
        for b in range(7):
            pop = POP[byte]
            past = (rest >= pop) & (place == 8 * b)
            rest = np.where(past, rest - pop, rest)
            place = np.where(past, 8 * (b + 1), place)
            following = ((bits >> np.uint64(8 * (b + 1))) & np.uint64(255)).astype(np.int64)
            byte = np.where(past, following, byte)
        high = word * 64 + place + SELECT[byte, rest] - i
        if not self.low_bits:
            return high
        at = i.astype(np.uint64) * np.uint64(self.low_bits)
        w, shift = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
        low = self.low[w] >> shift
        low |= np.where(shift > 0, self.low[w + 1] << ((np.uint64(64) - shift) & np.uint64(63)), np.uint64(0))
        return (high << self.low_bits) | (low & np.uint64((1 << self.low_bits) - 1)).astype(np.int64)


def code(log10: np.ndarray) -> np.ndarray:
    """Quantised logarithms of probabilities (at most 0)."""
    return np.clip(np.round(-SCALE * log10), 0, 65535).astype(np.uint16)


class Trie:
    """Levels from 1: symbols, pointers to children (none in the last level), codes."""

    def __init__(self, levels: list[tuple[np.ndarray, EliasFano | None, np.ndarray]]):
        self.levels = levels

    @classmethod
    def of(cls, symbols: list[np.ndarray], parents: list[np.ndarray], codes: list[np.ndarray]) -> Trie:
        """From each level's symbols and codes in path order, and from level 2 on their parents' places in the level above."""
        levels = []
        for n, (own, coded) in enumerate(zip(symbols, codes)):
            pointers = EliasFano.of(np.searchsorted(parents[n], np.arange(len(own) + 1))) if n < len(parents) else None
            levels.append((own.astype(np.uint32), pointers, coded))
        return cls(levels)

    def pack(self) -> bytes:
        """A header of sizes, then the levels' arrays, each at a multiple of 8 bytes."""
        head, parts = [struct.pack("<q", len(self.levels))], []
        for symbols, ef, coded in self.levels:
            arrays = [symbols, coded, *((ef.low, ef.high) if ef else (np.zeros(0, np.uint64),) * 2)]
            head.append(struct.pack("<6q", *map(len, arrays), ef.n if ef else -1, ef.low_bits if ef else 0))
            parts += [a.tobytes() + b"\0" * (-a.nbytes % 8) for a in arrays]
        return b"".join(head + parts)

    @classmethod
    def unpack(cls, raw: bytes | mmap.mmap) -> Trie:
        (n_levels,) = struct.unpack_from("<q", raw, 0)
        sizes = [struct.unpack_from("<6q", raw, 8 + 48 * k) for k in range(n_levels)]
        at, levels = 8 + 48 * n_levels, []
        for *lengths, n, bits in sizes:
            arrays = []
            for kind, size in zip((np.uint32, np.uint16, np.uint64, np.uint64), lengths):
                arrays.append(np.frombuffer(raw, dtype=kind, count=size, offset=at))
                at += arrays[-1].nbytes + -arrays[-1].nbytes % 8
            levels.append((arrays[0], EliasFano(n, bits, arrays[2], arrays[3]) if n >= 0 else None, arrays[1]))
        return cls(levels)

    @classmethod
    def open(cls, file) -> Trie:
        """From an open file, mapped into memory."""
        return cls.unpack(mmap.mmap(file.fileno(), 0, access=mmap.ACCESS_READ))

    def roots(self, symbols: np.ndarray) -> np.ndarray:
        """Places of symbols in the first level, or -1."""
        own = self.levels[0][0]
        if not len(own):
            return np.full(len(symbols), -1, dtype=np.int64)
        at = np.minimum(np.searchsorted(own, symbols), len(own) - 1)
        return np.where(own[at] == symbols, at, -1)

    def child(self, level: int, parent: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        """Of nodes in `level` (from 0; -1: none): the child with that symbol, or -1."""
        out = np.full(len(parent), -1, dtype=np.int64)
        live = np.flatnonzero(parent >= 0)
        pointers, symbols = self.levels[level][1], self.levels[level + 1][0]
        if not len(live) or not len(symbols):
            return out
        asked, which = np.unique(parent[live], return_inverse=True)
        lo, end = (x[which] for x in np.split(pointers.at(np.concatenate((asked, asked + 1))), 2))
        hi, want = end.copy(), symbol[live]
        busy = np.flatnonzero(lo < hi)
        while len(busy):  # the least place whose symbol isn't less than the wanted one
            mid = (lo[busy] + hi[busy]) >> 1
            less = symbols[mid] < want[busy]
            lo[busy[less]] = mid[less] + 1
            hi[busy[~less]] = mid[~less]
            busy = busy[lo[busy] < hi[busy]]
        hit = np.flatnonzero(lo < end)
        hit = hit[symbols[lo[hit]] == want[hit]]
        out[live[hit]] = lo[hit]
        return out
