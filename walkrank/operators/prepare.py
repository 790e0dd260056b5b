"""Graph preparation: degrees, repair of vertices without out-edges, dense indices, replica layouts."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.functions.rng import Rng
from walkrank.functions.session import cut


def vertices(edges: DataFrame) -> DataFrame:
    return edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()


def degrees(edges: DataFrame) -> DataFrame:
    """(id, d_in, d_out) by one aggregation over both ends."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(0).alias("i"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("id"), F.lit(1).alias("i"), F.lit(0).alias("o")))).alias("e"))
    return ends.groupBy("e.id").agg(F.sum("e.i").cast("long").alias("d_in"), F.sum("e.o").cast("long").alias("d_out"))


def dangling(edges: DataFrame) -> DataFrame:
    """(id): vertices without out-edges."""
    return edges.select(F.col("dst").alias("id")).distinct().join(edges.select(F.col("src").alias("id")), "id", "left_anti")


def repair(edges: DataFrame, policy: str = "self_loop") -> DataFrame:
    """Edges in which every vertex has an out-edge.

    self_loop: an edge to itself. reverse_edge: its in-edges turned round. drop: it goes, and so on until none is
    left. reject: an error. ("to_all", equal shares for all, is a term of the power iteration instead.)
    """
    if policy == "self_loop":
        return edges.union(dangling(edges).select("id", F.col("id").alias("dst")))
    if policy == "reverse_edge":
        back = edges.join(dangling(edges).withColumnRenamed("id", "dst"), "dst", "left_semi").select(F.col("dst").alias("src"), F.col("src").alias("dst"))
        return edges.union(back).distinct()
    if policy == "drop":
        while True:
            gone = cut(dangling(edges))
            if gone.isEmpty():
                return edges
            edges = cut(edges.join(gone.withColumnRenamed("id", "dst"), "dst", "left_anti").select("src", "dst"))
    if policy == "reject":
        if not dangling(edges).isEmpty():
            raise ValueError("the graph has vertices without out-edges")
        return edges
    raise ValueError(f"unknown policy {policy}")


def indexed(verts: DataFrame, rng: Rng, buckets: int | None = None) -> DataFrame:
    """(id, idx): dense indices from 0, by bucket then id, without a global sort (only bucket counts meet in one place). Buckets: 64, and more so that
    each has about half a million at most."""
    buckets = buckets or max(64, verts.count() >> 19)
    b = verts.select("id", (rng.draw("v", 0, "id") % buckets).alias("bucket"))
    sizes = b.groupBy("bucket").agg(F.count("*").alias("c"))
    offsets = sizes.select("bucket", (F.sum("c").over(W.orderBy("bucket")) - F.col("c")).alias("offset"))  # a row a bucket
    return b.join(F.broadcast(offsets), "bucket").select("id", (F.col("offset") + F.row_number().over(W.partitionBy("bucket").orderBy("id")) - 1).alias("idx"))


def encode(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges with long ids, dictionary (id, key)); ids are hashes, checked for collisions."""
    keys = vertices(edges).select(F.xxhash64("id").alias("id"), F.col("id").alias("key"))
    if not keys.groupBy("id").agg(F.count("*").alias("n")).where("n > 1").isEmpty():
        raise ValueError("two keys have the same hash")
    return edges.select(F.xxhash64("src").alias("src"), F.xxhash64("dst").alias("dst")), keys


@dataclass
class Layout:
    """replicas (src, shard, nbrs, d_local), one row a vertex of its replicas (src, d_out, reps), dense indices (id, idx)."""

    replicas: DataFrame | None
    directory: DataFrame | None
    vertices: DataFrame
    n: int
    index: DataFrame
    #: Whether replicas and directory are tables bucketed by src, which walks of any size join without moving them.
    bucketed: bool = False
    #: (replicas, directory) of the vertices (src) alone that a step leaves from, for graphs too large to be laid out whole.
    near: Callable[[DataFrame], tuple[DataFrame, DataFrame]] | None = None

    def replication(self) -> DataFrame:
        return self.directory.agg(F.avg(F.size("reps")).alias("replication_factor"))


def shard_of(kind: str, shards: int, rng: Rng, chunk: int = 4096):
    """(edges -> edges with shard) for the layouts random, spread, grid, source, chunked."""
    if kind == "random":  # `shards` replicas, however large the hub
        return lambda e: e.withColumn("shard", rng.draw("y", 0, "src", "dst") % shards)
    if kind == "spread":  # as random, or as many more as a hub needs to keep them bounded
        def at_random(e: DataFrame) -> DataFrame:
            d = e.groupBy("src").agg(F.count("*").alias("d"))
            return e.join(d, "src").withColumn("shard", rng.draw("y", 0, "src", "dst") % F.greatest(F.lit(shards), F.ceil(F.col("d") / chunk))).drop("d")
        return at_random
    if kind == "grid":
        rows = max(1, int(shards**0.5))
        cols = max(1, shards // rows)
        return lambda e: e.withColumn("shard", (rng.draw("y", 1, "src") % rows) * cols + rng.draw("y", 2, "dst") % cols)
    if kind == "source":
        return lambda e: e.withColumn("shard", rng.draw("y", 3, "src") % shards)
    if kind == "chunked":  # at most about `chunk` neighbours a replica, however large the hub
        def chunked(e: DataFrame) -> DataFrame:
            d = e.groupBy("src").agg(F.count("*").alias("d"))
            return e.join(d, "src").withColumn("shard", rng.draw("y", 4, "src", "dst") % F.ceil(F.col("d") / chunk)).drop("d")
        return chunked
    raise ValueError(f"unknown layout {kind}")


def replicated(edges: DataFrame, kind: str = "random", shards: int = 8, rng: Rng = Rng(), chunk: int = 4096, keep: bool = True) -> tuple[DataFrame, DataFrame]:
    """(replicas, directory) of a layout."""
    placed = shard_of(kind, shards, rng, chunk)(edges)
    reps = placed.groupBy("src", "shard").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).withColumn("d_local", F.size("nbrs"))
    reps = cut(reps) if keep else reps
    directory = reps.groupBy("src").agg(F.sum("d_local").alias("d_out"), F.array_sort(F.collect_list(F.struct("shard", "d_local"))).alias("reps"))
    directory = cut(directory) if keep else directory
    return reps, directory


def layout(edges: DataFrame, kind: str = "random", shards: int = 8, rng: Rng = Rng(), chunk: int = 4096, keep: bool = True) -> Layout:
    """Replicas of repaired edges. Done once per graph; walks only read it."""
    reps, directory = replicated(edges, kind, shards, rng, chunk, keep)
    verts = directory.select(F.col("src").alias("id"))
    index = cut(indexed(verts, rng)) if keep else indexed(verts, rng)
    return Layout(reps, directory, verts, index.count(), index)


def bucketed(layout: Layout, table: str, buckets: int = 64) -> Layout:
    """The layout with its replicas and its directory as tables bucketed and sorted by source, in the warehouse."""
    spark = layout.replicas.sparkSession
    for frame, name in ((layout.replicas, f"{table}_replicas"), (layout.directory, f"{table}_directory")):
        frame.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(name)
    return Layout(spark.table(f"{table}_replicas"), spark.table(f"{table}_directory"), layout.vertices, layout.n, layout.index, True)
