"""SimHash near-duplicates with a hierarchical index over fingerprints in Gray order.

Fingerprints: 64 bits, each set if over half of a text's shingle hashes set it. Links: fingerprints
that differ in at most 3 bits. Two such fingerprints agree in at least one of four 16-bit bands, so
each distinct fingerprint goes to four buckets (band, value), which deal it out over the cluster. In a
partition, every bucket's fingerprints are sorted by Gray rank, runs of them become nodes of a tree,
and each node keeps the bits that all of its members share (mask and pattern). The tree is joined
with itself from the top: two nodes whose shared bits already differ in more than 3 places are left out
with all that is below them. Of what links, a partition reports one spanning forest, never all pairs,
and components() joins the forests.

Nodes are distinct fingerprints, so copies cost nothing, and rows that share an id but not a text are apart. Null texts count as empty;
a text without words has fingerprint zero. A row with a null doc_id links like any other; its component is the
smallest id that its group has, null if none. Repeated rows come back as often as they went in. Extra columns are ignored. An empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map, cut, keyed, plus, shuffle_parts
from walkrank.llm.components import components, local_components

BANDS = 4
FANOUT = 8
MOST_BITS = 3
#: Pairs of nodes that are looked at together.
CHUNK = 1 << 19
#: Fingerprints in a bucket beyond which it is dealt again, and about so many in a partition.
HOT = 1 << 16
PART = 1 << 20


def fingerprint(text: str | None, size: int = 3, seed: int = 42) -> int:
    words = (text or "").encode("utf-8").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    if len(words) <= size:
        hashes = np.array([xxhash.xxh64_intdigest(joined, seed)], dtype="<u8")
    else:
        ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1) - 1
        starts = np.concatenate(([0], ends[:-1] + 1))[: len(words) - size + 1].tolist()
        digest = xxhash.xxh64_intdigest
        hashes = np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts, ends[size - 1 :].tolist())), dtype="<u8", count=len(starts))
    ones = np.zeros(64, dtype=np.int64)
    for at in range(0, len(hashes), 1 << 16):
        ones += np.unpackbits(hashes[at : at + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return sum(1 << i for i in np.flatnonzero(2 * ones > len(hashes)).tolist())


def fingerprints(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """(doc_id, *keep, fp long): the fingerprint of every text as a signed 64-bit integer."""
    keep = keep or []
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *keep, F.col("text").cast("string").alias("__text"))
    kept = source.drop("__text").schema

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t.as_py()) for t in batch.column("__text")], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*(batch.column(f.name) for f in kept.fields), pa.array(fps)], names=[*kept.names, "fp"])

    return arrow_map(source, work, plus(kept, fp="bigint"))


def gray_rank(codes: np.ndarray) -> np.ndarray:
    """The place of each code in the Gray sequence."""
    out = codes.copy()
    for s in (1, 2, 4, 8, 16, 32):
        out ^= out >> np.uint64(s)
    return out


class GrayTree:
    """Trees over buckets of fingerprints; one level is one set of arrays for all buckets."""

    def __init__(self, bucket: np.ndarray, codes: np.ndarray):
        self.order = np.lexsort((gray_rank(codes), bucket))
        bucket, codes = bucket[self.order], codes[self.order]
        full = np.full(len(codes), np.uint64(0xFFFFFFFFFFFFFFFF))
        #: From the leaves up: pattern, mask, first child (with an end), bucket.
        self.levels = [(codes, full, None)]
        while True:
            starts = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1])))
            if len(starts) == len(bucket) and len(self.levels) > 1:
                break
            place = np.arange(len(bucket)) - np.repeat(starts, np.diff(np.append(starts, len(bucket))))
            heads = np.flatnonzero(place % FANOUT == 0)
            pattern, mask, _ = self.levels[-1]
            both = np.bitwise_and.reduceat(mask, heads)
            unlike = np.bitwise_or.reduceat(pattern ^ np.repeat(pattern[heads], np.diff(np.append(heads, len(bucket)))), heads)
            mask = both & ~unlike
            self.levels.append((pattern[heads] & mask, mask, np.append(heads, len(bucket))))
            bucket = bucket[heads]

    def links(self, most: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs of places in the input that lie in one bucket and differ in at most `most` bits."""
        top = len(self.levels) - 1
        n = len(self.levels[top][0])
        stack = [(top, np.arange(at, min(at + CHUNK, n)), np.arange(at, min(at + CHUNK, n))) for at in range(0, n, CHUNK)]
        while stack:
            level, a, b = stack.pop()
            if level == 0:
                yield self.order[a], self.order[b]
                continue
            heads = self.levels[level][2]
            step = max(1, CHUNK // (FANOUT * FANOUT))
            for at in range(0, len(a), step) if len(a) > step else (0,):
                x, y = a[at : at + step], b[at : at + step]
                nx, ny = heads[x + 1] - heads[x], heads[y + 1] - heads[y]
                many = nx * ny
                pair = np.repeat(np.arange(len(x)), many)
                k = np.arange(len(pair)) - np.repeat(np.cumsum(many) - many, many)
                i, j = heads[x][pair] + k // ny[pair], heads[y][pair] + k % ny[pair]
                own = x[pair] == y[pair]
                keep = ~own | ((i < j) if level == 1 else (i <= j))
                i, j = i[keep], j[keep]
                pattern, mask, _ = self.levels[level - 1]
                near = np.bitwise_count((pattern[i] ^ pattern[j]) & mask[i] & mask[j]) <= most
                if near.any():
                    stack.append((level - 1, i[near], j[near]))


def _banded(dealt: DataFrame, width: int) -> DataFrame:
    """(fp, key, rest) of dealt (fp, key, rest), four rows each: the key goes on with a quarter of the `width` bits in rest, the rest is what remains.

    Two fingerprints whose rests differ in MOST_BITS bits at most meet in one of the four.
    """
    part = width // BANDS
    low = lambda x, bits: x.bitwiseAND((1 << bits) - 1)
    over = lambda j: F.shiftrightunsigned(F.shiftrightunsigned("rest", (j + 1) * part - 1), 1)  # noqa: E731 - 64 places at once would be none
    each = [F.struct(F.xxhash64("key", F.lit(j), low(F.shiftrightunsigned("rest", j * part), part)).alias("key"), F.shiftleft(over(j), j * part).bitwiseOR(low(F.col("rest"), j * part)).alias("rest")) for j in range(BANDS)]
    return dealt.select("fp", F.explode(F.array(*each)).alias("b")).select("fp", "b.key", "b.rest")


def fingerprint_links(distinct: DataFrame, most: int = MOST_BITS, hot: int = HOT) -> DataFrame:
    """(a, b): links among the rows of distinct (fp long) that connect the same fingerprints as all links do.

    Buckets of over `hot` fingerprints are dealt again by the bits that their band left, up to three times (16, 28 and 37 shared bits).
    """
    dealt = _banded(distinct.select("fp", F.lit(0).cast("long").alias("key"), F.col("fp").alias("rest")), 64)
    done, n = None, 0
    for width in (48, 36, 0):
        sizes = dealt.groupBy("key").agg(F.count("*").alias("c"))
        n += sizes.agg(F.coalesce(F.sum("c"), F.lit(0)).alias("n")).first()["n"]
        large = cut(sizes.where(F.col("c") > hot).select("key")) if width else None
        if large is None or large.isEmpty():
            done = dealt if done is None else done.unionByName(dealt)
            break
        calm = dealt.join(large, "key", "left_anti")
        done = calm if done is None else done.unionByName(calm)
        dealt = _banded(dealt.join(large, "key", "left_semi"), width)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [(b.column("fp").to_numpy(), b.column("key").to_numpy()) for b in batches if b.num_rows]
        if not got:
            return
        fp, bucket = (np.concatenate(x) for x in zip(*got))
        root = np.arange(len(fp))
        for u, v in GrayTree(bucket, fp.view(np.uint64)).links(most):
            more = local_components(len(fp), np.concatenate((root[u], u)), np.concatenate((root[v], root[u])))
            root = more[root]
        up = np.flatnonzero(root != np.arange(len(root)))
        yield pa.RecordBatch.from_arrays([pa.array(fp[up]), pa.array(fp[root[up]])], names=["a", "b"])

    # so many partitions that each holds a bounded number of fingerprints
    spread = done.select("fp", "key").repartition(max(shuffle_parts(distinct.sparkSession), 2, n // PART), "key")
    return arrow_map(spread, work, "a long, b long")


def _grouped(fps: DataFrame) -> DataFrame:
    """(fp, group): the fingerprints of fps, each with the least one that it can reach."""
    distinct = cut(fps.select("fp").distinct())
    found = components(fingerprint_links(distinct))
    return distinct.join(found, distinct["fp"] == found["node"], "left").select("fp", F.coalesce("component", "fp").alias("group"))


def near_duplicates(docs: DataFrame, keep: list[str] | None = None) -> DataFrame:
    """(doc_id, *keep, fingerprint, component_id): one row for each row of docs."""
    fps = cut(fingerprints(docs, keep))
    least = fps.groupBy("fp").agg(F.min("doc_id").alias("id"))
    grouped = cut(_grouped(fps).join(least, "fp"))
    named = grouped.join(grouped.groupBy("group").agg(F.min("id").alias("component_id")), "group").select("fp", "component_id")
    code = F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint")
    return fps.join(named, "fp", "left").select("doc_id", *(keep or []), code, "component_id")


def keep_first(docs: DataFrame) -> DataFrame:
    """One row of docs, whole, of each group of fingerprints: that with the least doc_id (a null one comes last), of these the one
    whose text has the least hash, and of rows that share id and text the one whose other columns have the least. Rows that share an id but are unlike all stay.

    Groups are of fingerprints, not of ids. Rows that share id and text are put together by partial aggregation, in the one shuffle of texts.
    """
    ids = (F.coalesce(F.col("doc_id").cast("string"), F.lit("")).alias("__id"), keyed(F.col("text")).alias("__th"))
    fps = cut(fingerprints(docs.select("doc_id", "text", *ids), ["__id", "__th"]))
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "__th", "__id")).alias("w")
    kept = fps.join(_grouped(fps), "fp").groupBy("group").agg(first).select("w.__id", "w.__th")
    named = docs.select(*ids, F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("__row"), F.xxhash64(*(F.col(f"`{c}`") for c in docs.columns if c != "text")).alias("__o"))
    one = named.groupBy("__id", "__th").agg(F.min_by("__row", "__o").alias("__row"))
    return one.join(kept, ["__id", "__th"], "left_semi").select("__row.*")
