"""Exact byte-pair encoding by dynamic programming over prefixes, and decoding.

A byte-level vocabulary with ordered merges gives every string one encoding, and every prefix of a
string one *last token*. For each end position the suffix automaton (Aho-Corasick over all token
strings) lists the tokens that end there; the one token that is compatible with the last token of the
prefix before it is kept. Following these tokens back from the end gives the ids. Two tokens are
compatible if encoding their concatenation gives just the two; that is decided by unwinding their
merges, and remembered.

The work is done for each distinct piece of text a worker meets (a bounded memory of pieces); texts
are read whole, in Arrow batches, without a shuffle.

Null texts count as empty (no tokens). Repeated rows give repeated results. Extra columns are kept
by `encode_frame` and ignored by the query.
"""

from __future__ import annotations

import hashlib
import json
import re
from collections.abc import Iterable, Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map, plus

#: Fixed pattern of byte-level BPE vocabularies (contractions, letters, numbers, other, white space).
PIECES = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
#: Most pieces that a worker remembers before it starts anew.
MEMORY = 400_000


def byte_alphabet() -> dict[int, str]:
    """The printable stand-in of each byte in byte-level vocabulary files."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    out = {b: chr(b) for b in shown}
    for b in range(256):
        if b not in out:
            out[b] = chr(256 + len(out) - len(shown))
    return out


class PrefixEncoder:
    """Encoder and decoder for one vocabulary file of the tokenizers library."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.ids: dict[str, int] = model["vocab"]
        self.special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
        self.merged: dict[tuple[int, int], int] = {}
        self.rank: dict[tuple[int, int], int] = {}
        self.parts: dict[int, tuple[int, int]] = {}
        self.order: dict[int, int] = {}
        for n, m in enumerate(model["merges"]):
            left, right = m if isinstance(m, list) else m.split(" ")
            pair, made = (self.ids[left], self.ids[right]), self.ids[left + right]
            self.merged.setdefault(pair, made)
            self.rank.setdefault(pair, n)
            if made not in self.parts:
                self.parts[made], self.order[made] = pair, n
        self.alphabet = byte_alphabet()
        self.stand_in = {b: c for b, c in self.alphabet.items()}
        self.automaton = ahocorasick.Automaton()
        for token, i in self.ids.items():
            if i in self.parts or len(token) == 1:  # a token no merge makes can't come up
                self.automaton.add_word(token, (len(token), i))
        self.automaton.make_automaton()
        back = {c: b for b, c in self.alphabet.items()}
        size = max([*self.ids.values(), *self.special.values()]) + 1
        self.bytes_of: list[bytes] = [b""] * size
        for token, i in self.ids.items():
            self.bytes_of[i] = bytes(back[c] for c in token)
        for token, i in self.special.items():
            self.bytes_of[i] = token.encode()
        self.split_special = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.pattern = regex.compile(PIECES)
        self.compatible: dict[int, bool] = {}
        self.known: dict[str, bytes] = {}
        self.small: dict[str, bytes] = {}

    def _stays_apart(self, left: int, right: int) -> bool:
        """Whether the encoding of the two tokens' text is the two tokens.

        The border is looked at as the merges inside both tokens are undone, the latest first: at each
        moment the two tokens that touch must not have merged before a merge that was done by then.
        """
        # `until`: merges at or after this place in the order had not happened yet when these two touched
        # (for a tie, the merge further left goes first).
        until = float("inf")
        while True:
            at = self.rank.get((left, right))
            if at is not None and at < until:
                return False
            a, b = self.order.get(left, -1), self.order.get(right, -1)
            if a < 0 and b < 0:
                return True
            if a > b:  # the left token was made after the right one: before that its right part touched
                until, left = a, self.parts[left][1]
            else:  # equal places: the left one is made first, so undo the right one
                until, right = b + 0.5, self.parts[right][0]

    def encode_piece(self, piece: str) -> list[int]:
        """Ids of one piece, given in the stand-in alphabet."""
        n = len(piece)
        last: list[int] = [-1] * (n + 1)
        size = [0] * (n + 1)
        apart = self.compatible
        for end, (length, token) in self.automaton.iter(piece):
            end += 1
            if last[end] >= 0:
                continue
            start = end - length
            if start:
                before = last[start]
                if before < 0:
                    continue
                fits = apart.get(before << 20 | token)
                if fits is None:
                    if len(apart) >= 2 * MEMORY:
                        apart.clear()
                    fits = apart[before << 20 | token] = self._stays_apart(before, token)
                if not fits:
                    continue
            last[end], size[end] = token, length
        ids = []
        while n:
            ids.append(last[n])
            n -= size[n]
        return ids[::-1]

    def _long(self, piece: str) -> bytes:
        """Ids, as bytes, of a stretch of text that the pattern may split."""
        out = []
        for word in self.pattern.findall(piece):
            got = self.small.get(word)
            if got is None:
                shown = "".join(map(self.stand_in.__getitem__, word.encode("utf-8")))
                got = np.array(self.encode_piece(shown), dtype="<u4").tobytes()
                if len(word) <= 64:
                    if len(self.small) >= MEMORY:
                        self.small.clear()
                    self.small[word] = got
            out.append(got)
        return b"".join(out)

    def _plain(self, text: str) -> Iterable[bytes]:
        # A space before something other than white space always starts a piece, so the text may be cut there.
        parts = text.split(" ")
        if re.search(r" (?:\s|$)", text):
            joined = [parts[0]]
            for p in parts[1:]:
                if p and not p[0].isspace() and not regex.match(r"\s", p):
                    joined.append(" " + p)
                else:
                    joined[-1] += " " + p
            parts = joined
        else:
            parts[1:] = [" " + p for p in parts[1:]]
        known = self.known
        for p in parts:
            got = known.get(p)
            if got is None:
                got = self._long(p)
                if len(p) <= 64:
                    if len(known) >= MEMORY:
                        known.clear()
                    known[p] = got
            yield got

    def encode_bytes(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if self.split_special is None or not any(s in text for s in self.special):
            return b"".join(self._plain(text))
        out = []
        for i, part in enumerate(self.split_special.split(text)):
            if i % 2:
                out.append(np.array([self.special[part]], dtype="<u4").tobytes())
            elif part:
                out.extend(self._plain(part))
        return b"".join(out)

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_bytes(text), dtype="<u4").tolist()

    def decode(self, ids: Iterable[int]) -> str:
        return b"".join(map(self.bytes_of.__getitem__, ids)).decode("utf-8", errors="replace")


_encoders: dict[str, PrefixEncoder] = {}


def encoder(path: str) -> PrefixEncoder:
    """One encoder a process and vocabulary."""
    if path not in _encoders:
        _encoders[path] = PrefixEncoder(path)
    return _encoders[path]


def encode_frame(docs: DataFrame, path: str, text: str = "text", digests_only: bool = False) -> DataFrame:
    """`docs` with n_tokens, ids_sha256, decoded_sha256 and, unless digests_only, ids (array of int).

    digests_only keeps of docs just doc_id. Columns of docs that bear one of the new names are replaced.
    """
    new = ["n_tokens", "ids_sha256", "decoded_sha256"] + ([] if digests_only else ["ids"])
    source = docs.select(F.col("doc_id"), F.col(text).cast("string").alias("__text")) if digests_only else docs.drop(*new).withColumn("__text", F.col(text).cast("string"))
    kept = source.drop("__text").schema

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for whole in batches:
            for at in range(0, whole.num_rows, 512):
                batch = whole.slice(at, 512)
                counts, raw, back, ids = [], [], [], []
                for t in batch.column("__text"):
                    got = enc.encode_bytes(t.as_py() or "")
                    numbers = np.frombuffer(got, dtype="<u4")
                    counts.append(len(numbers))
                    raw.append(hashlib.sha256(got).hexdigest())
                    back.append(hashlib.sha256(enc.decode(numbers.tolist()).encode("utf-8")).hexdigest())
                    if not digests_only:
                        ids.append(numbers.astype("i4"))
                cols = [batch.column(f.name) for f in kept.fields] + [pa.array(counts, pa.int64()), pa.array(raw, pa.string()), pa.array(back, pa.string())]
                if not digests_only:
                    cols.append(pa.array(ids, pa.list_(pa.int32())))
                yield pa.RecordBatch.from_arrays(cols, names=[f.name for f in kept.fields] + new)

    more = {"n_tokens": "bigint", "ids_sha256": "string", "decoded_sha256": "string"} | ({} if digests_only else {"ids": "array<int>"})
    return arrow_map(source, work, plus(kept, **more))


def decode_frame(encoded: DataFrame, path: str, ids: str = "ids") -> DataFrame:
    """`encoded` with the column decoded, the text of its ids (null for null)."""
    kept = encoded.drop("decoded").schema

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for batch in batches:
            texts = [None if x is None else enc.decode(x) for x in batch.column(ids).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(f.name) for f in kept.fields] + [pa.array(texts, pa.string())], names=[*kept.names, "decoded"])

    return arrow_map(encoded.drop("decoded"), work, plus(kept, decoded="string"))
