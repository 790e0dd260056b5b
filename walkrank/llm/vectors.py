"""Near-duplicates among vectors by collision counting on many one-dimensional projections.

Unit vectors are turned by a fixed random rotation, whose coordinates are the projections. In a pair of
blocks every projection is sorted into cells, and each vector's window holds the vectors that collide with it there. The
window's half width w and the count are calibrated so that recall is 1: cosine >= c means a squared distance
of at most 2 - 2c = r2, and a pair that misses m windows has squared distance over m * w * w, so with
w * w = r2 / m no such pair misses m, whichever projections are looked at. So each vector takes its own order of the windows' halves
(a miss lies beyond one of the two ends): those come first that hold the fewest, which part most pairs after a fraction of the projections.
What lies beyond an end is a bit set (a prefix in whole cells, or the rest), and misses are counted in bit-sliced counters for 64 vectors at once;
words of 64 that are all parted are left out of further counting. Pairs with fewer than m misses are verified by their cosine in double precision.

Equal vectors are one class from the start. Blocks are boxes by the signs of a few projections, cut to a bounded size;
of the boxes, narrow rows, those pairs within reach are found first, and only for these do vectors travel, several partners to a block that
stays where it is. A pair of blocks reports a number of links per vector and a spanning forest, never its pairs.

Vectors that are null, empty, zero or hold null or non-finite components link with nothing, nor do rows without an id
(their component is null); vectors link only with vectors of their own length. Rows that repeat id and vector are
vectors of their own. Rows with one id but other vectors are vectors of their own too; as components are named by ids, such rows are in one. Components
keep the precision they come in (float, or else double). Extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map, cut, ship
from walkrank.llm.components import components, local_components
from walkrank.llm.topk import _floats, usable

#: Vectors of a block, at least and (of 64 components; fewer, if they have more) at most. Larger blocks travel less often.
BLOCK, LARGEST = 16384, 65536
#: Cells of a projection, at whose borders the sets of smaller vectors are stored; at most 256.
CELLS = 64
#: Vectors whose windows are counted at once, and the share of words under which only those that are left are counted on.
ROWS, SPARSE = 512, 0.1
ALL = np.uint64(2**64 - 1)
VERIFY = 1 << 16


def rotation(dim: int, seed: int = 7) -> np.ndarray:
    q, _ = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, dim)))
    return q


def misses_for(dim: int, r2: float) -> int:
    """How many misses part a pair: so many that a window is a little wider than a component's spread, but fewer than projections."""
    most = 1 << max(0, min(6, dim.bit_length() - 2))
    return int(min(most, max(4, 2 ** round(np.log2(max(1.0, r2 * dim / 1.6))))))


def near_pairs(x: np.ndarray, y: np.ndarray, r2: float, own: bool = False, spent: list[int] | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (i, j) of rotated unit vectors that miss fewer windows than part a pair (own: of y = x, those of i < j): all within r2, and
    few others. The words of windows that were read are appended to `spent`."""
    n, dim = x.shape
    misses = misses_for(dim, r2)
    w = np.sqrt(r2 / misses) * (1 + 1e-9) + 1e-9
    low = y.min(axis=0)
    scale = CELLS / np.maximum(y.max(axis=0) - low, 1e-9)
    # monotone, so a window's cells hold all of the window
    cell = lambda v: np.clip((v - low) * scale, 0, CELLS - 1).astype(np.int32)
    cells = np.empty((dim, len(y)), dtype=np.uint8)
    for at in range(0, len(y), ROWS):
        cells[:, at : at + ROWS] = cell(y[at : at + ROWS]).T
    below = np.zeros((dim, CELLS + 1), dtype=np.int64)
    for c in range(dim):
        np.cumsum(np.bincount(cells[c], minlength=CELLS), out=below[c, 1:])
    # a vector's own order of half windows: those that part it from most come first
    tests = np.empty((2 * dim, n), dtype=np.int32)
    at_c = np.arange(dim)
    for at in range(0, n, ROWS):
        first, last = cell(x[at : at + ROWS] - w), cell(x[at : at + ROWS] + w) + 1
        parted = np.concatenate((below[at_c, first], len(y) - below[at_c, last]), axis=1)
        order = np.argsort((65535 - parted * 65535 // len(y)).astype(np.uint16), axis=1, kind="stable")
        rows = np.concatenate((at_c * (CELLS + 1) + first, (dim + at_c) * (CELLS + 1) + last), axis=1)
        tests[:, at : at + ROWS] = np.take_along_axis(rows, order, axis=1).T
    size = 64 * max(8, min(64, 8192 // dim))
    for s in range(0, len(y), size):
        table = prefixes(cells[:, s : s + size])
        for at in range(0, min(n, s + size) if own else n, ROWS):
            i, j = _left(table, tests[:, at : at + ROWS], misses, spent)
            i, j = i + at, j + s
            kept = (j < len(y)) & ((i < j) | (not own))
            i, j = i[kept], j[kept]
            for k in range(0, len(i), VERIFY):
                yield i[k : k + VERIFY], j[k : k + VERIFY]


def prefixes(cells: np.ndarray) -> np.ndarray:
    """Row c * (CELLS + 1) + k: the set, as bits, of the vectors whose cell in projection c is under k; after these rows, the sets of all others."""
    dim, m = cells.shape
    table = np.zeros((dim, CELLS + 1, -(-m // 64)), dtype=np.uint64)
    one = np.zeros((CELLS, table.shape[2] * 64), dtype=np.uint8)
    for c in range(dim):
        one[cells[c], np.arange(m)] = 1
        table[c, 1:] = np.packbits(one, axis=1, bitorder="little").view(np.uint64)
        one[cells[c], np.arange(m)] = 0
    np.bitwise_or.accumulate(table, axis=1, out=table)
    table = np.concatenate((table, ~table)).reshape(-1, table.shape[2])
    if m % 64:
        # bits of no vector are in every set, so they are parted at once
        table[:, -1] |= ALL << np.uint64(m % 64)
    return table


def _left(table: np.ndarray, tests: np.ndarray, misses: int, spent: list[int] | None) -> tuple[np.ndarray, np.ndarray]:
    """(row, bit) of the table's vectors that miss under `misses` of the row's tests, or are worth a look at their cosine."""
    most, n = tests.shape
    words = table.shape[1]
    over = np.zeros((n, words), dtype=np.uint64)
    counts = [np.zeros_like(over) for _ in range(misses.bit_length() - 1)]
    miss, other = np.empty_like(over), np.empty_like(over)
    alive, c = np.arange(over.size), 0
    # all words, until nearly all are parted from all of their vectors
    while c < most and len(alive) > SPARSE * over.size:
        end = min(c + 4, most)
        for test in tests[c:end]:
            np.take(table, test, axis=0, out=miss, mode="clip")
            for k in counts:
                np.bitwise_and(k, miss, out=other)
                np.bitwise_xor(k, miss, out=k)
                miss, other = other, miss
            np.bitwise_or(over, miss, out=over)
        c = end
        if c >= misses:
            alive = np.flatnonzero(over != ALL)
    read = c * over.size
    over, counts = over.ravel()[alive], [k.ravel()[alive] for k in counts]
    # the words that are left, until what goes is less than what a look costs
    while c < most and len(alive):
        end = min(c + 8, most)
        read += (end - c) * len(alive)
        row, word = alive // words, alive % words
        for test in tests[c:end]:
            miss = table[test[row], word]
            for k in counts:
                carry = k & miss
                k ^= miss
                miss = carry
            over |= miss
        c = end
        kept = over != ALL
        alive, over, counts = alive[kept], over[kept], [k[kept] for k in counts]
        if kept.mean() > 0.75:
            break
    if spent is not None:
        spent.append(read)
    at, bit = np.nonzero(np.unpackbits((~over).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"))
    return alive[at] // words, (alive[at] % words) * 64 + bit


def block_links(x: np.ndarray, y: np.ndarray, own: bool, weights: tuple[np.ndarray, np.ndarray], cosine: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Links between (or, own: inside) two blocks of vectors: their weight per x, per y, and the root of each of x, y."""
    n, m = len(x), len(y)
    turn = rotation(x.shape[1])
    nx, ny = np.linalg.norm(x, axis=1), np.linalg.norm(y, axis=1)
    ux = x / nx[:, None] @ turn
    uy = ux if own else y / ny[:, None] @ turn
    to_x, to_y = np.zeros(n, dtype=np.int64), np.zeros(m, dtype=np.int64)
    root = np.arange(n if own else n + m)
    gap = np.maximum(0, np.maximum(ux.min(axis=0) - uy.max(axis=0), uy.min(axis=0) - ux.max(axis=0)))
    r2 = 2 - 2 * cosine + 1e-9
    if gap @ gap > r2:
        return to_x, to_y, root
    for i, j in near_pairs(ux, uy, r2, own):
        near = np.einsum("ij,ij->i", x[i], y[j]) / (nx[i] * ny[j]) >= cosine
        i, j = i[near], j[near]
        if len(i):
            to_x += np.bincount(i, weights=weights[1][j], minlength=n).astype(np.int64)
            to_y += np.bincount(j, weights=weights[0][i], minlength=m).astype(np.int64)
            v = j if own else j + n
            root = local_components(len(root), np.concatenate((np.arange(len(root)), i)), np.concatenate((root, v)))
    return to_x, to_y, root


def scaled(x: np.ndarray) -> np.ndarray:
    """Vectors times a power of two each, exactly, so that no square leaves the range of doubles."""
    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1, keepdims=True))[1])


def blocks(classes: DataFrame, block_rows: int | None = None) -> tuple[DataFrame, DataFrame, int]:
    """(packed, boxes, n): blocks of classes (node, h, w, dim, v), numbered from 0; the box of each, (dim, block, lo, hi); their number."""
    size = classes.agg(F.count("*").alias("n"), F.max("dim").alias("dim")).first()
    n = max(1, size["n"])
    # four blocks, with some room, as long as that isn't too large
    block_rows = block_rows or max(BLOCK, min(LARGEST * 64 // max(64, size["dim"] or 64), int(n / 3.4)))
    count = -(-n // block_rows)
    # Near vectors get near numbers: a few projections' signs come first, the hash deals the rest.
    bits = max(0, min(16, int(np.log2(count))))
    kind = dict(classes.dtypes)["v"]
    ship(classes.sparkSession)

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            v = b.column("v")
            cells = np.zeros(b.num_rows, dtype=np.int64)
            dims = b.column("dim").to_numpy()
            for d in np.unique(dims):
                rows = np.flatnonzero(dims == d)
                side = scaled(_floats(v.take(pa.array(rows)))) @ rotation(int(d))[:, :bits] > 0
                cells[rows] = side @ (1 << np.arange(side.shape[1]))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(cells)], names=[*b.schema.names, "cell"])

    celled = arrow_map(classes, code, f"node bigint, h bigint, w bigint, dim int, v {kind}, cell bigint")
    sizes = celled.groupBy("dim", "cell").agg(F.count("*").alias("c"))
    # a row a cell: numbering blocks needs only the cells' sizes
    sizes = sizes.withColumn("parts", F.ceil(F.col("c") / block_rows).cast("long"))
    sizes = cut(sizes.withColumn("first", F.sum("parts").over(W.orderBy("dim", "cell").rowsBetween(W.unboundedPreceding, -1))).na.fill(0, ["first"]))
    total = sizes.agg(F.coalesce(F.sum("parts"), F.lit(0)).alias("n")).first()["n"]
    dealt = celled.join(sizes.select("dim", "cell", "parts", "first"), ["dim", "cell"]).withColumn("block", F.col("first") + F.pmod(F.xxhash64("node", "h"), F.col("parts")))
    packed = dealt.groupBy("dim", "block").agg(F.collect_list(F.struct("node", "h", "w", "v")).alias("r"))
    packed = cut(packed.select("dim", "block", "r.node", "r.h", "r.w", F.flatten("r.v").alias("v")))

    def box(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            los, his = [], []
            for r in range(b.num_rows):
                x = _rows(b, r)
                u = x / np.linalg.norm(x, axis=1)[:, None] @ rotation(x.shape[1])
                los.append(u.min(axis=0))
                his.append(u.max(axis=0))
            yield pa.RecordBatch.from_arrays([b.column("dim"), b.column("block"), pa.array(los, pa.list_(pa.float64())), pa.array(his, pa.list_(pa.float64()))], names=["dim", "block", "lo", "hi"])

    return packed, cut(arrow_map(packed.select("dim", "block", "v"), box, "dim int, block bigint, lo array<double>, hi array<double>")), total


def _rows(b: pa.RecordBatch, r: int) -> np.ndarray:
    return scaled(b.column("v")[r].values.to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, b.column("dim")[r].as_py()))


def meetings(boxes: DataFrame, n: int, r2: float) -> DataFrame:
    """(a, slot, role, block): the block a (role 0; 2 if it also meets itself) and up to `side` blocks that it meets (role 1) are wanted at
    (a, slot). Of two blocks whose boxes are within reach, the one that has fewer others meets the other."""
    other = boxes.select("dim", F.col("block").alias("b"), F.col("lo").alias("lo_b"), F.col("hi").alias("hi_b"))
    # narrow rows only: vectors travel for pairs that are left
    gap = F.zip_with(F.zip_with("lo", "hi_b", lambda x, y: F.greatest(x - y, F.lit(0.0))), F.zip_with("lo_b", "hi", lambda x, y: F.greatest(x - y, F.lit(0.0))), lambda x, y: F.greatest(x, y))
    near = F.aggregate(gap, F.lit(0.0), lambda s, x: s + x * x) <= r2
    # of blocks a < b, the even sums go to a and the odd ones to b, so that all have about as many
    pairs = boxes.join(other, "dim").where((F.col("block") < F.col("b")) & near).select(F.col("block").alias("x"), F.col("b").alias("y"), ((F.col("block") + F.col("b")) % 2 == 0).alias("even"))
    owned = pairs.select(F.when(F.col("even"), F.col("x")).otherwise(F.col("y")).alias("a"), F.when(F.col("even"), F.col("y")).otherwise(F.col("x")).alias("block"))
    side = max(2, min(16, n // 4))
    met = owned.withColumn("slot", F.floor(F.col("block") / side).cast("long")).select("a", "slot", F.lit(1).alias("role"), "block")
    itself = boxes.select(F.col("block").alias("a"), F.floor(F.col("block") / side).cast("long").alias("slot"), F.lit(2).alias("role"), "block")
    own = met.select("a", "slot").distinct().join(itself.select("a", "slot"), ["a", "slot"], "left_anti").select("a", "slot", F.lit(0).alias("role"), F.col("a").alias("block"))
    return met.unionByName(itself).unionByName(own).withColumn("task", F.col("a") * (n // side + 1) + F.col("slot"))


def links(packed: DataFrame, wanted: DataFrame, cosine: float, tasks: int) -> DataFrame:
    """(node, h, links, root): per vector its links and a spanning forest, from the blocks that meet; a task holds two blocks at a time."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at, mine = None, None
        for b in batches:
            for r in range(b.num_rows):
                task, role = b.column("task")[r].as_py(), b.column("role")[r].as_py()
                get = lambda c: b.column(c)[r].values.to_numpy(zero_copy_only=False)  # noqa: B023, E731
                block = (_rows(b, r), get("w"), get("node"), get("h"))
                if role != 1:
                    at, mine = task, block
                    if role == 2:
                        yield found(mine, mine, True)
                elif at != task:
                    raise RuntimeError("a block came before the one that it meets")
                else:
                    yield found(mine, block, False)

    def found(a: tuple, b: tuple, own: bool) -> pa.RecordBatch:
        to_a, to_b, root = block_links(a[0], b[0], own, (a[1], b[1]), cosine)
        node, h = (a[2], a[3]) if own else (np.concatenate((a[2], b[2])), np.concatenate((a[3], b[3])))
        many = to_a + to_b if own else np.concatenate((to_a, to_b))
        keep = (many > 0) | (root != np.arange(len(root)))
        return pa.RecordBatch.from_arrays([pa.array(node[keep]), pa.array(h[keep]), pa.array(many[keep]), pa.array(node[root][keep])], names=["node", "h", "links", "root"])

    rows = wanted.join(packed, "block").withColumn("first", F.when(F.col("role") == 1, 1).otherwise(0))
    dealt = rows.select("task", "first", "role", "block", "dim", "node", "h", "w", "v").repartitionById(tasks, F.col("task").cast("int")).sortWithinPartitions("task", "first", "block")
    return arrow_map(dealt, work, "node bigint, h bigint, links bigint, root bigint")


def near_duplicates(rows: DataFrame, cosine: float = 0.95, block_rows: int | None = None) -> DataFrame:
    """(vec_id, n_links, component_id, kept): one row for each row of rows (vec_id, embedding)."""
    # components keep their precision; -0.0 is 0.0
    kind = "float" if dict(rows.dtypes)["embedding"] == "array<float>" else "double"
    v = F.transform("embedding", lambda x: x.cast(kind) + F.lit(0.0).cast(kind))
    clean = rows.select(F.col("vec_id").cast("long").alias("vec_id"), v.alias("v"))
    good = F.col("vec_id").isNotNull() & usable(F.col("v")) & F.coalesce(F.exists("v", lambda x: x != 0), F.lit(False))
    # 128 bits name a vector
    named = clean.withColumn("good", good).withColumn("h", F.when(F.col("good"), F.xxhash64("v"))).withColumn("h2", F.when(F.col("good"), F.xxhash64(F.lit(1), "v")))
    classes = named.where("good").groupBy("h", "h2").agg(F.min("vec_id").alias("node"), F.count("*").alias("w"), F.any_value("v").alias("v"))
    classes = cut(classes.select("node", "h", "h2", "w", F.size("v").alias("dim"), "v"))
    packed, boxes, n = blocks(classes.drop("h2"), block_rows)
    wanted = meetings(boxes, n, 2 - 2 * cosine + 1e-9)
    found = cut(links(packed, wanted, cosine, max(1, n * (n // max(2, min(16, n // 4)) + 1))))
    joined = components(found.where("node <> root").select(F.col("node").alias("a"), F.col("root").alias("b")))
    counts = found.groupBy("node", "h").agg(F.sum("links").alias("links"))
    per = classes.select("node", "h", "h2", "w").join(counts, ["node", "h"], "left").join(joined, "node", "left")
    per = per.select("h", "h2", (F.coalesce("links", F.lit(0)) + F.col("w") - 1).alias("n"), F.coalesce("component", "node").alias("comp"))
    out = named.select("vec_id", "h", "h2").join(per, ["h", "h2"], "left")
    mine = F.coalesce("comp", "vec_id")
    return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), mine.alias("component_id"), F.coalesce(F.col("vec_id") == mine, F.lit(False)).alias("kept"))


ORACLE_SQL = """
WITH RECURSIVE v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings),
link AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_inner_product(a.e, b.e) / sqrt(list_inner_product(a.e, a.e) * list_inner_product(b.e, b.e)) >= 0.95),
reach(a, b) AS (SELECT vec_id, vec_id FROM v UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a),
comp AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a),
deg AS (SELECT a AS vec_id, count(*) AS n FROM link GROUP BY a)
SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, component_id, vec_id = component_id AS kept FROM comp LEFT JOIN deg USING (vec_id)"""
