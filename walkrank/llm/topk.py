"""Exact top-k by integer inner product: a ball tree per shard, searched by branch and bound.

Candidates are dealt over shards of a bounded number of rows; each shard's vectors become a ball tree, packed into one
row. Queries are packed into blocks. A node's bound for query q is q.centre + |q| * radius; nodes with the
larger bounds are visited first, and a node is left out for the queries whose kth score so far exceeds its
bound. Shards are searched in waves, each several times as many as the one before; between waves the kth scores
found so far are shared by all shards of the next.

Vectors that are null, empty, or hold null or non-finite components take no part; neither do rows without an id.
Vectors compete with queries of their own length. All rows that bear the query's id are its own. Repeated
rows compete each for itself; an id with several vectors asks with each of them, an id repeated with one vector asks once. Ties go to the smaller vec_id. Scores beyond 64 bits are cut to the range of long.
"""

from __future__ import annotations

import io
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.llm.common import arrow_map, cut, ship, shuffle_parts

SHARD = 8192
BLOCK = 1024
LEAF = 128
#: Beyond this, doubles don't hold every integer.
EXACT = float(1 << 52)


def usable(v: Column) -> Column:
    """Whether a vector has components and all of them are finite."""
    return F.coalesce((F.size(v) > 0) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))), F.lit(False))


def integers(v: Column) -> Column:
    """floor(256 * x) of every component, as double (it may exceed every integer type)."""
    # Spark's floor gives a long; what lies beyond is whole already
    return F.transform(v, lambda x: F.when(F.abs(x) < F.lit(1e12), F.floor(256.0 * x.cast("double")).cast("double")).otherwise(256.0 * x.cast("double")))


class BallTree:
    """Nodes in arrays; a node's rows are one stretch of the reordered vectors."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, leaf: int = LEAF):
        order = np.arange(len(ids))
        lo, hi, left, right, centre, radius = [], [], [], [], [], []

        def grow(a: int, b: int) -> int:
            me = len(lo)
            rows = vectors[order[a:b]]
            c = rows.mean(axis=0)
            gap = np.sqrt(np.square(rows - c).sum(axis=1))
            for x, v in ((lo, a), (hi, b), (left, -1), (right, -1), (centre, c), (radius, float(gap.max()) * (1 + 1e-9) + 1e-6)):
                x.append(v)
            if b - a > leaf and radius[me] > 1e-5:
                far = rows[gap.argmax()]
                other = rows[np.square(rows - far).sum(axis=1).argmax()]
                order[a:b] = order[a:b][np.argsort(rows @ (far - other), kind="stable")]
                left[me], right[me] = grow(a, (a + b) // 2), grow((a + b) // 2, b)
            return me

        if len(ids):
            grow(0, len(ids))
        self.lo, self.hi, self.left, self.right = (np.array(x, dtype=np.int64) for x in (lo, hi, left, right))
        self.centre, self.radius = np.array(centre).reshape(len(lo), -1), np.array(radius)
        self.ids, self.vectors = ids[order], vectors[order]

    def pack(self) -> bytes:
        out = io.BytesIO()
        np.savez(out, **self.__dict__)
        return out.getvalue()

    @classmethod
    def unpack(cls, raw: bytes) -> BallTree:
        tree = cls.__new__(cls)
        with np.load(io.BytesIO(raw)) as got:
            tree.__dict__.update({k: got[k] for k in got.files})
        return tree

    def search(self, ids: np.ndarray, queries: np.ndarray, floor: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(scores, ids), k of each a query and -inf where there are fewer, of rows that score `floor` at least."""
        n = len(ids)
        best, who = np.full((n, k), -np.inf), np.full((n, k), np.iinfo(np.int64).max)
        length = np.sqrt(np.square(queries).sum(axis=1))
        bar = floor.astype(np.float64).copy()
        visited = 0

        def bound(node: int, act: np.ndarray) -> np.ndarray:
            b = queries[act] @ self.centre[node] + length[act] * self.radius[node]
            return b + 1e-9 * np.abs(b) + 1e-6

        stack = [(0, np.arange(n), bound(0, np.arange(n)))] if len(self.lo) and n else []
        while stack:
            node, act, limit = stack.pop()
            act = act[limit >= bar[act]]
            if not len(act):
                continue
            if self.left[node] >= 0:
                kids = [(c, act, bound(c, act)) for c in (int(self.left[node]), int(self.right[node]))]
                stack.extend(sorted(kids, key=lambda x: x[2].mean()))
                continue
            visited += 1
            rows, names = self.vectors[self.lo[node] : self.hi[node]], self.ids[self.lo[node] : self.hi[node]]
            big = float(np.abs(queries[act]).max(initial=0)) * float(np.abs(rows).max(initial=0)) * rows.shape[1]
            if big < EXACT:
                scores = queries[act] @ rows.T
            else:  # rare and slow: whole numbers of any size, cut to the range of long
                most = (1 << 63) - 1
                scores = np.array([[max(-most, min(most, sum(int(a) * int(b) for a, b in zip(q, r)))) for r in rows] for q in queries[act]], dtype=object)
            scores = np.where(names[None, :] == ids[act][:, None], -np.inf, scores)
            better = (scores >= bar[act][:, None]).any(axis=1)
            act, scores = act[better], scores[better]
            if len(act):
                s = np.concatenate((best[act].astype(scores.dtype), scores), axis=1)
                w = np.concatenate((who[act], np.broadcast_to(names, scores.shape)), axis=1)
                order = np.lexsort((w, -s), axis=1)[:, :k] if s.dtype != object else np.array([sorted(range(s.shape[1]), key=lambda j: (-r[j], x[j]))[:k] for r, x in zip(s, w)])
                if s.dtype == object and best.dtype != object:
                    best = best.astype(object)
                best[act], who[act] = np.take_along_axis(s, order, axis=1), np.take_along_axis(w, order, axis=1)
                bar[act] = np.maximum(bar[act], best[act][:, k - 1].astype(np.float64))
        self.visited = visited
        return best, who


def _floats(lists: pa.Array) -> np.ndarray:
    lists = lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists
    return lists.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(lists), -1)


def trees(rows: DataFrame, shard_rows: int = SHARD) -> tuple[DataFrame, int]:
    """(dim, shard, tree, n), packed ball trees of rows (vec_id, dim, v), and the number of shards."""
    n = max(1, rows.count())
    shards = -(-n // shard_rows)
    # rows are dealt once, in a checkpoint: equal rows go to different shards, and a retried task finds them where they were
    dealt = cut(rows.withColumn("shard", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(shards))))
    ship(rows.sparkSession)

    def build(table: pa.Table) -> pa.Table:
        v = _floats(table.column("v"))
        tree = BallTree(table.column("vec_id").to_numpy(), v)
        return pa.table({"dim": pa.array([v.shape[1]], pa.int32()), "shard": pa.array([table.column("shard")[0].as_py()], pa.int64()), "tree": pa.array([tree.pack()], pa.binary()), "n": pa.array([len(v)], pa.int64())})

    return dealt.groupBy("dim", "shard").applyInArrow(build, "dim int, shard bigint, tree binary, n bigint"), shards


def top_k(candidates: DataFrame, queries: DataFrame, k: int = 5, shard_rows: int = SHARD, block_rows: int = BLOCK, growth: int = 4) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best candidates of each query; both are frames (vec_id, embedding)."""
    def made(df: DataFrame) -> DataFrame:
        return df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("e")).where(F.col("vec_id").isNotNull() & usable(F.col("e"))).select("vec_id", F.size("e").alias("dim"), integers(F.col("e")).alias("v"))

    packed, shards = trees(made(candidates), shard_rows)
    packed = cut(packed)
    asked = made(queries).withColumn("query", F.xxhash64("vec_id", "v")).groupBy("query", "vec_id").agg(F.any_value("dim").alias("dim"), F.any_value("v").alias("v"))
    blocks = max(1, -(-asked.count() // block_rows))
    asked = cut(asked.withColumn("block", F.pmod(F.col("query"), F.lit(blocks))))
    found = None
    done, wave = 0, 1
    best = W.partitionBy("query").orderBy(F.desc("score"), "vec_id")
    none = lambda *names: [F.lit(None).cast(t).alias(n) for n, t in names]
    lists = (("query", "array<bigint>"), ("ids", "array<bigint>"), ("bar", "array<double>"), ("v", "array<double>"))
    while done < shards:
        upto = min(shards, done + wave)
        if found is None:
            barred = asked.withColumn("bar", F.lit(float("-inf")))
        else:  # the kth score so far, for queries that have k
            bars = found.groupBy("query").agg(F.count("*").alias("c"), F.min("score").alias("s")).select("query", F.when(F.col("c") >= k, F.col("s").cast("double")).alias("bar"))
            barred = asked.join(bars, "query", "left").withColumn("bar", F.coalesce("bar", F.lit(float("-inf"))))
        ask = barred.groupBy("dim", "block").agg(F.collect_list(F.struct("query", "vec_id", "bar", "v")).alias("q"))
        ask = ask.select("dim", F.explode(F.sequence(F.lit(done).cast("long"), F.lit(upto - 1).cast("long"))).alias("shard"), F.col("block").alias("at"), F.lit(None).cast("binary").alias("tree"), "q.query", F.col("q.vec_id").alias("ids"), "q.bar", F.flatten("q.v").alias("v"))
        # a shard's tree comes before the blocks that are searched in it, so it travels once
        trees_ = packed.where((F.col("shard") >= done) & (F.col("shard") < upto)).select("dim", "shard", F.lit(-1).cast("long").alias("at"), "tree", *none(*lists))
        met = trees_.unionByName(ask).repartition(max(shuffle_parts(asked.sparkSession), upto - done), "dim", "shard").sortWithinPartitions("dim", "shard", "at")

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            place, tree = None, None
            for b in batches:
                for r in range(b.num_rows):
                    dim, shard = b.column("dim")[r].as_py(), b.column("shard")[r].as_py()
                    if b.column("at")[r].as_py() < 0:
                        place, tree = (dim, shard), BallTree.unpack(b.column("tree")[r].as_py())
                    elif place == (dim, shard):  # else no candidate has this length
                        query, ids, bar, v = (b.column(x)[r].values.to_numpy(zero_copy_only=False) for x in ("query", "ids", "bar", "v"))
                        scores, who = tree.search(ids, v.reshape(-1, dim), bar, k)
                        i, j = np.nonzero(np.array(scores > -np.inf, dtype=bool))
                        yield pa.RecordBatch.from_arrays([pa.array(query[i]), pa.array(ids[i]), pa.array(who[i, j]), pa.array([int(x) for x in scores[i, j]], pa.int64())], names=["query", "query_id", "vec_id", "score"])

        fresh = arrow_map(met, work, "query bigint, query_id bigint, vec_id bigint, score bigint")
        merged = fresh if found is None else found.unionByName(fresh)
        found = cut(merged.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).drop("rank"))
        done, wave = upto, wave * growth
    return found.select("query_id", F.row_number().over(best).alias("rank"), "vec_id", "score")


ORACLE_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)) AS e FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(embedding) > 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id, list_inner_product(q.e, c.e)::BIGINT AS score FROM v q JOIN v c ON q.vec_id % 50 = 0 AND q.vec_id <> c.vec_id),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5"""
