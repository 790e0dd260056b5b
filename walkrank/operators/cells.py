"""Graphs packed in the cells of a grid of vertex blocks: iterations move parts of vectors, never an edge.

Vertices are longs (codes), dealt to blocks by a hash; a cell has the edges from one block to another. A cell numbers its sources and targets itself, so
that it gets and gives dense vectors of those alone; a block knows where they belong. Edges are held once, 4 bytes each.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.functions.session import cut, dealt, released

#: About so many edges in a cell, so many vertices in a block; so many edges that a task deals out at once.
CELL, BLOCK, DEAL = 1 << 21, 1 << 18, 1 << 20
OUT, IN, SELF = 0, 1, 2


def planes(a: np.ndarray) -> bytes:
    """Longs byte by byte, first all lowest ones: equal high bytes lie together, which shuffles compress."""
    return a.astype(np.int64, copy=False).view(np.uint8).reshape(-1, 8).T.tobytes()


def longs(b: bytes) -> np.ndarray:
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(8, -1).T).view(np.int64).ravel()


def distinct(a: np.ndarray) -> np.ndarray:
    """np.unique() by sorting, which is many times faster here than its hashing."""
    a = np.sort(a)
    return a[np.append(True, a[1:] != a[:-1])]


def narrow(codes: np.ndarray) -> bytes:
    """Sorted longs by their differences, compressed."""
    return zlib.compress(planes(np.diff(codes, prepend=0)), 1)


def wide(b: bytes) -> np.ndarray:
    return np.cumsum(longs(zlib.decompress(b)))


def block_of(codes: np.ndarray, blocks: int) -> np.ndarray:
    x = codes.astype(np.uint64)
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return ((x ^ (x >> np.uint64(31))) % np.uint64(blocks)).astype(np.int64)


def dealer(blocks: int, once: bool, most: int) -> Callable:
    """(src, dst) -> (cell, src, dst) of many edges each; once: without the repeated ones that meet."""

    def flush(held: list) -> pa.RecordBatch:
        src, dst = (np.concatenate(x) for x in zip(*held))
        cell = block_of(src, blocks) * blocks + block_of(dst, blocks)
        order = np.argsort(cell.astype(np.uint16) if blocks <= 256 else cell, kind="stable")
        cell, src, dst = cell[order], src[order], dst[order]
        at = np.flatnonzero(np.diff(cell, prepend=-1))
        rows = []
        for i, j in zip(at, [*at[1:], len(cell)]):
            s, d = src[i:j], dst[i:j]
            if once:
                o = np.lexsort((d, s))
                s, d = s[o], d[o]
                new = np.append(True, (np.diff(s) != 0) | (np.diff(d) != 0))
                s, d = s[new], d[new]
            rows.append((planes(s), planes(d)))
        return pa.record_batch({"cell": cell[at], "src": pa.array([x for x, _ in rows], pa.binary()), "dst": pa.array([x for _, x in rows], pa.binary())})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            if b.num_rows:
                held.append((b["src"].to_numpy(zero_copy_only=False), b["dst"].to_numpy(zero_copy_only=False)))
                n += b.num_rows
            if n >= most:
                yield flush(held)
                held, n = [], 0
        if held:
            yield flush(held)

    return run


def packer(blocks: int, once: bool) -> Callable:
    """A cell's edges -> its sources and targets as codes, out-degrees in the cell, and for each target so many (counts) numbers of sources (idx)."""

    def run(table: pa.Table) -> pa.Table:
        src, dst = (np.concatenate([longs(x.as_py()) for x in table[c]]) for c in ("src", "dst"))
        s, d = distinct(src), distinct(dst)
        key = np.searchsorted(d, dst) * len(s) + np.searchsorted(s, src)
        key = distinct(key) if once else np.sort(key)
        j, i = np.divmod(key, len(s))
        row = {"s": narrow(s), "d": narrow(d), "deg": np.bincount(i, minlength=len(s)).astype(np.int32).tobytes(), "idx": i.astype(np.int32).tobytes(), "counts": np.bincount(j, minlength=len(d)).astype(np.int32).tobytes()}
        return pa.table({"cell": pa.array([table["cell"][0].as_py()], pa.int64()), **{k: pa.array([v], pa.binary()) for k, v in row.items()}})

    return run


def index(table: pa.Table) -> pa.Table:
    """All that cells know of a block -> its vertices (SELF: codes, out-degrees), and where each cell's sources (OUT, with out-degrees) and targets (IN) lie."""
    block = table["block"][0].as_py()
    rows = list(zip(*(table[c].to_pylist() for c in ("cell", "kind", "codes", "deg"))))
    codes = distinct(np.concatenate([wide(r[2]) for r in rows]))
    at = [np.searchsorted(codes, wide(r[2])) for r in rows]
    deg = np.zeros(len(codes), np.int64)
    for (_, kind, _, d), p in zip(rows, at):
        if kind == OUT:
            deg[p] += np.frombuffer(d, np.int32)
    data = [(c, k, p.astype(np.int32).tobytes(), deg[p].tobytes() if k == OUT else None) for (c, k, _, _), p in zip(rows, at)]
    cell, kind, pos, degs = zip(*data, (-1, SELF, narrow(codes), deg.tobytes()))
    return pa.table({"block": pa.array([block] * len(cell), pa.int64()), "cell": pa.array(cell, pa.int64()), "kind": pa.array(kind, pa.int32()), "data": pa.array(pos, pa.binary()), "deg": pa.array(degs, pa.binary()), "n": pa.array([len(codes)] * len(cell), pa.int64())})


def vector(b: bytes) -> np.ndarray:
    return np.frombuffer(b, np.float64)


def one(block: int, x: np.ndarray) -> pa.Table:
    return pa.table({"block": pa.array([block], pa.int64()), "x": pa.array([x.tobytes()], pa.binary())})


def send(routes: pa.Table, xs: pa.Table) -> pa.Table:
    """A block's vector -> what each source of a cell gives to each of its targets."""
    if not (routes.num_rows and xs.num_rows):
        return pa.table({"cell": pa.array([], pa.int64()), "v": pa.array([], pa.binary())})
    x = vector(xs["x"][0].as_py())
    out = [(x[np.frombuffer(p.as_py(), np.int32)] / np.frombuffer(d.as_py(), np.int64)).tobytes() for p, d in zip(routes["data"], routes["deg"])]
    return pa.table({"cell": routes["cell"].combine_chunks(), "v": pa.array(out, pa.binary())})


def multiplier(blocks: int) -> Callable:
    def run(cells: pa.Table, vs: pa.Table) -> pa.Table:
        out = []
        for cell, idx, counts in zip(cells["cell"].to_pylist(), cells["idx"], cells["counts"]):
            ends = np.cumsum(np.frombuffer(counts.as_py(), np.int32), dtype=np.int64)
            given = vector(vs["v"][0].as_py())[np.frombuffer(idx.as_py(), np.int32)]
            out.append((cell % blocks, cell, np.add.reduceat(given, np.append(0, ends[:-1])).tobytes()))
        block, cell, v = zip(*out) if out else ((), (), ())
        return pa.table({"block": pa.array(block, pa.int64()), "cell": pa.array(cell, pa.int64()), "v": pa.array(v, pa.binary())})

    return run


def gatherer(n: int, p_t: float, stay: bool) -> Callable:
    """What cells give to a block (and its old vector, cell -1) -> its new vector; stay: vertices without out-edges keep theirs, as by a self loop."""

    def run(routes: pa.Table, vs: pa.Table) -> pa.Table:
        places, deg = {}, None
        for c, k, data, d in zip(routes["cell"].to_pylist(), routes["kind"].to_pylist(), routes["data"], routes["deg"]):
            if k == SELF:
                deg = np.frombuffer(d.as_py(), np.int64)
            else:
                places[c] = data
        total = np.zeros(len(deg))
        cells = vs["cell"].to_pylist()
        for i in np.argsort(cells, kind="stable"):  # always in the same order
            v = vector(vs["v"][int(i)].as_py())
            if cells[i] >= 0:
                total[np.frombuffer(places[cells[i]].as_py(), np.int32)] += v
            elif stay:
                total += np.where(deg == 0, v, 0.0)
        return one(routes["block"][0].as_py(), total * (1 - p_t) + p_t / n)

    return run


def compare(xs: pa.Table) -> pa.Table:
    """A block's vectors of a cycle -> the last change (L1) and the changes' inner products."""
    x = [vector(b) for _, b in sorted(zip(xs["i"].to_pylist(), xs["x"].to_pylist()))]
    f = [b - a for a, b in zip(x, x[1:])]
    return pa.table({"change": pa.array([np.abs(f[-1]).sum()], pa.float64()), "g": pa.array([np.array([[a @ b for b in f] for a in f]).tobytes()], pa.binary())})


def mixer(w: np.ndarray) -> Callable:
    """A block's vectors of a cycle -> their mean, and the size (L1) of the mean of their changes."""

    def run(xs: pa.Table) -> pa.Table:
        x = [vector(b) for _, b in sorted(zip(xs["i"].to_pylist(), xs["x"].to_pylist()))]
        left = sum(k * (b - a) for k, a, b in zip(w, x, x[1:]))
        return one(xs["block"][0].as_py(), sum(k * b for k, b in zip(w, x[1:]))).append_column("left", pa.array([np.abs(left).sum()], pa.float64()))

    return run


def alone(p_t: float, tol: float, depth: int, most: int, stay: bool, mean: Callable) -> Callable:
    """All cycles of a graph of one block and one cell, in the task that has it: (code, value), no rows if it doesn't converge."""

    def run(parts: pa.Table, cells: pa.Table) -> pa.Table:
        kind = np.array(parts["kind"].to_pylist())
        out, rest = parts.take(np.flatnonzero(kind == OUT)), parts.take(np.flatnonzero(kind != OUT))
        own = parts.take(np.flatnonzero(kind == SELF))
        n = own["n"][0].as_py()
        multiply, gather = multiplier(1), gatherer(n, p_t, stay)
        x = one(0, np.full(n, 1 / n))
        for _ in range(0, most, depth):
            xs = [x]
            for _ in range(depth):
                old = pa.table({"block": xs[-1]["block"], "cell": pa.array([-1], pa.int64()), "v": xs[-1]["x"]})
                xs.append(gather(rest, pa.concat_tables([multiply(cells, send(out, xs[-1])), old])))
            cycle = pa.concat_tables(xs).append_column("i", pa.array(range(depth + 1), pa.int32()))
            change = compare(cycle)
            if change["change"][0].as_py() < tol:
                return decode(own, xs[-1])
            mixed = mixer(mean(np.frombuffer(change["g"][0].as_py()).reshape(depth, depth)))(cycle)
            x = mixed.drop_columns("left") if mixed["left"][0].as_py() < change["change"][0].as_py() else xs[-1]
        return pa.table({"code": pa.array([], pa.int64()), "value": pa.array([], pa.float64())})

    return run


def decode(parts: pa.Table, xs: pa.Table) -> pa.Table:
    return pa.table({"code": pa.array(wide(parts["data"][0].as_py()), pa.int64()), "value": pa.array(vector(xs["x"][0].as_py()), pa.float64())})


@dataclass
class Cells:
    """cells (cell, idx, counts) and parts (block, cell, kind, data, deg, n), each kept where its key lies, without lineage; n vertices."""

    cells: DataFrame
    parts: DataFrame
    blocks: int
    n: int

    def start(self) -> DataFrame:
        n = self.n
        return cut(self.parts.where(F.col("kind") == SELF).select("block", "n").groupBy("block").applyInArrow(lambda t: one(t["block"][0].as_py(), np.full(t["n"][0].as_py(), 1 / n)), "block long, x binary"))

    def step(self, x: DataFrame, p_t: float, stay: bool) -> DataFrame:
        """One iteration of (block, x)."""
        sent = self.parts.where(F.col("kind") == OUT).groupBy("block").cogroup(x.groupBy("block")).applyInArrow(send, "cell long, v binary")
        got = self.cells.groupBy("cell").cogroup(sent.groupBy("cell")).applyInArrow(multiplier(self.blocks), "block long, cell long, v binary")
        got = got.unionByName(x.select("block", F.lit(-1).cast("long").alias("cell"), F.col("x").alias("v")))
        return self.parts.where(F.col("kind") != OUT).groupBy("block").cogroup(got.groupBy("block")).applyInArrow(gatherer(self.n, p_t, stay), "block long, x binary")

    def solved(self, run: Callable) -> DataFrame:
        """(code, value) by alone(), for a graph of one block."""
        return cut(self.parts.groupBy("block").cogroup(self.cells.withColumn("block", F.col("cell")).groupBy("block")).applyInArrow(run, "code long, value double"))

    def values(self, x: DataFrame) -> DataFrame:
        """(code, value) of (block, x)."""
        return self.parts.where(F.col("kind") == SELF).groupBy("block").cogroup(x.groupBy("block")).applyInArrow(decode, "code long, value double")


def packed(edges: DataFrame, once: bool = False) -> Cells | None:
    """Edges (src, dst), longs without nulls, in cells; once: repeated edges count once. None if there are none. The caller frees it."""
    spark = edges.sparkSession
    m, a, b = edges.agg(F.count("*"), F.approx_count_distinct("src"), F.approx_count_distinct("dst")).first()
    if not m:
        return None
    released(spark)
    blocks = max(1, round((m / CELL) ** 0.5), -(-max(a, b) // BLOCK))
    most = int(spark.conf.get("spark.sql.shuffle.partitions"))
    pieces = edges.mapInArrow(dealer(blocks, once, DEAL), "cell long, src binary, dst binary")
    both = cut(pieces.groupBy("cell").applyInArrow(packer(blocks, once), "cell long, s binary, d binary, deg binary, idx binary, counts binary"))
    del pieces
    released(spark)
    cells = dealt(both.select("cell", "idx", "counts"), min(most, blocks * blocks), "cell")
    ends = both.select(F.expr(f"cell div {blocks}").alias("block"), "cell", F.lit(OUT).alias("kind"), F.col("s").alias("codes"), "deg").unionByName(
        both.select((F.col("cell") % blocks).alias("block"), "cell", F.lit(IN).alias("kind"), F.col("d").alias("codes"), F.lit(None).cast("binary").alias("deg")))
    parts = dealt(ends.groupBy("block").applyInArrow(index, "block long, cell long, kind int, data binary, deg binary, n long"), min(most, blocks), "block")
    del both, ends
    released(spark)
    return Cells(cells, parts, blocks, parts.where(F.col("kind") == SELF).agg(F.sum("n")).first()[0])
