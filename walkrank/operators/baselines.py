"""Baselines: power iteration (converged, few iterations, tolerance, per-vertex tolerance), sparsified, series, in-degree."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.functions.rng import Rng
from walkrank.functions.session import cut, released
from walkrank.operators import cells
from walkrank.operators.prepare import indexed, repair, vertices

EVERY = 5


def with_degree(edges: DataFrame, full: DataFrame | None = None) -> DataFrame:
    """(src, dst, d): edges with their source's out-degree, in `full` if given."""
    d = (full if full is not None else edges).groupBy("src").agg(F.count("*").alias("d"))
    return edges.join(d, "src")


def by_source(edges_d: DataFrame) -> DataFrame:
    """Edges dealt by source once, sorted and cached so, that iterations neither move nor sort edges, but ranks only. The caller frees them.

    They are counted here, as plans know the partitioning of a cache only when it is filled (without, only adaptive execution finds it, while running).
    """
    out = edges_d.repartition(int(edges_d.sparkSession.conf.get("spark.sql.shuffle.partitions")), "src").sortWithinPartitions("src").persist()
    out.count()
    return out


def start(verts: DataFrame, n: int) -> DataFrame:
    return verts.select("id", F.lit(1.0 / max(n, 1)).alias("value"))


def step(rank: DataFrame, edges_d: DataFrame, verts: DataFrame, n: int, p_t: float = 0.15, to_all: DataFrame | None = None) -> DataFrame:
    """One iteration. to_all (id): vertices without out-edges whose mass is shared by all."""
    n = max(n, 1)
    # a zero for every vertex instead of a join with all: one exchange an iteration, after which ranks lie where edges by_source() do
    sent = edges_d.join(rank.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), (F.col("value") / F.col("d")).alias("m"))
    out = sent.unionByName(verts.select("id", F.lit(0.0).alias("m"))).groupBy("id").agg(F.sum("m").alias("m"))
    spread = F.lit(0.0)
    if to_all is not None:
        lost = rank.join(to_all, "id", "left_semi").agg(F.coalesce(F.sum("value"), F.lit(0.0)).alias("lost"))
        out, spread = out.crossJoin(F.broadcast(lost)), F.col("lost") / n  # one row
    return out.select("id", ((F.coalesce("m", F.lit(0.0)) + spread) * (1 - p_t) + p_t / n).alias("value"))


def fixed(edges: DataFrame, iterations: int, p_t: float = 0.15, degree_of: DataFrame | None = None, to_all: bool = False, verts: DataFrame | None = None) -> DataFrame:
    """(id, value) after a fixed number of iterations from equal shares."""
    verts = cut(vertices(edges)) if verts is None else verts
    n = verts.count()
    e = with_degree(edges, degree_of)
    if iterations > 1:
        e = by_source(e)
    idle = verts.join(edges.select(F.col("src").alias("id")), "id", "left_anti") if to_all else None
    rank = start(verts, n)
    for i in range(iterations):
        rank = step(rank, e, verts, n, p_t, idle)
        if i % EVERY == EVERY - 1 or i == iterations - 1 > 0:
            rank = cut(rank)
    if iterations > 1:
        e.unpersist()
    return rank


def tolerance(edges: DataFrame, tol: float, p_t: float = 0.15, norm: str = "l1", most: int = 400, every: int = 1) -> tuple[DataFrame, int]:
    """(rank, iterations): stops when an iteration's change in the norm ("l1" or "max") is below tol; looked at every few iterations. An error if `most` don't do."""
    verts = cut(vertices(edges))
    n = verts.count()
    e = by_source(with_degree(edges))
    rank = start(verts, n)
    f = F.sum if norm == "l1" else F.max
    try:
        for i in range(0, most, every):
            for _ in range(every - 1):
                rank = step(rank, e, verts, n, p_t)
            old = cut(rank) if every > 1 else rank
            both = cut(step(old, e, verts, n, p_t).join(old.withColumnRenamed("value", "old"), "id"))
            change = both.agg(f(F.abs(F.col("value") - F.col("old")))).first()[0]
            rank = both.select("id", "value")
            if change is None or change < tol:
                return rank, i + every
    finally:
        e.unpersist()
    raise RuntimeError(f"no convergence to {tol} within {most} iterations")


def exact(edges: DataFrame, p_t: float = 0.15, tol: float = 1e-12, depth: int = 8, most: int = 400) -> DataFrame:
    """The rank vector to convergence, as converged(), of vertices of any type; kept once per graph by its users."""
    verts = cut(vertices(edges))
    idx = cut(indexed(verts, Rng()))
    ends = [idx.select(F.col("id").alias(c), F.col("idx").alias(f"{c}_")) for c in ("src", "dst")]
    coded = edges.join(ends[0], "src").join(ends[1], "dst").select(F.col("src_").alias("src"), F.col("dst_").alias("dst"))
    rank = converged(coded, p_t, tol, depth, most)
    return start(verts, 0) if rank is None else rank.join(idx, F.col("code") == F.col("idx")).select("id", "value")


def converged(edges: DataFrame, p_t: float = 0.15, tol: float = 1e-12, depth: int = 8, most: int = 400, once: bool = False, stay: bool = False) -> DataFrame | None:
    """(code, value): the rank vector of edges between longs (without nulls); None without edges. As tolerance(), an iteration's change (L1) is below tol at the end, but it takes fewer.

    After every `depth` iterations the next start is the affine mean of theirs whose change is least (squares, from inner products),
    so that slow modes don't have to fade by themselves; the last one, if that mean isn't nearer. once: repeated edges count once; stay: vertices without out-edges have a self loop.
    """
    spark = edges.sparkSession
    grid = cells.packed(edges, once)
    if grid is None:
        return None
    if grid.blocks == 1:
        rank = grid.solved(cells.alone(p_t, tol, depth, most, stay, least_mean))
        if rank.isEmpty():
            raise RuntimeError(f"no convergence to {tol} within {most} iterations")
        return rank
    x = grid.start()
    for _ in range(0, most, depth):
        xs = [x]
        for _ in range(depth):
            xs.append(cut(grid.step(xs[-1], p_t, stay)))
            released(spark)
        cycle = reduce(DataFrame.unionByName, (x.withColumn("i", F.lit(i)) for i, x in enumerate(xs)))
        rows = cycle.groupBy("block").applyInArrow(cells.compare, "change double, g binary").collect()  # a row a block
        change = sum(r.change for r in rows)
        if change < tol:
            return cut(grid.values(xs[-1]))
        w = least_mean(sum(np.frombuffer(r.g).reshape(depth, depth) for r in rows))
        mixed = cut(cycle.groupBy("block").applyInArrow(cells.mixer(w), "block long, x binary, left double"))
        # least in squares can be more in L1, in which alone each iteration is sure to bring the change down
        x = mixed.select("block", "x") if mixed.agg(F.sum("left")).first()[0] < change else xs[-1]
    raise RuntimeError(f"no convergence to {tol} within {most} iterations")


def least_mean(g: np.ndarray) -> np.ndarray:
    """Weights, of sum one, of the least affine mean of vectors with the inner products g; all weight on the last if there is none."""
    size = np.sqrt(np.diag(g))
    last = np.eye(len(g))[-1]
    if not (size > 0).all():
        return last
    w = np.linalg.lstsq(g / np.outer(size, size), 1 / size, rcond=1e-15)[0] / size
    return w / w.sum() if np.isfinite(w).all() and w.sum() > 0 else last


def delta(edges: DataFrame, tol: float, p_t: float = 0.15, most: int = 400) -> tuple[DataFrame, int]:
    """(rank, iterations): only vertices whose value changed by over tol send their change on."""
    verts = cut(vertices(edges))
    n = verts.count()
    e = by_source(with_degree(edges))
    state = cut(verts.select("id", F.lit(p_t / n).alias("value"), F.lit(p_t / n).alias("change")))
    for i in range(most):
        sent = e.join(state.where(F.abs("change") > tol).select(F.col("id").alias("src"), "change"), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("change") / F.col("d") * (1 - p_t)).alias("m"))
        got = F.coalesce("m", F.lit(0.0))
        # a change too small to be sent is kept until it has grown
        kept = F.when(F.abs("change") > tol, 0.0).otherwise(F.col("change"))
        state = cut(state.join(sent, "id", "left").select("id", (F.col("value") + got).alias("value"), (kept + got).alias("change")))
        if state.where(F.abs("change") > tol).isEmpty():
            e.unpersist()
            return state.select("id", "value"), i + 1
    e.unpersist()
    raise RuntimeError(f"changes over {tol} are left after {most} iterations")


def sparsified(edges: DataFrame, r: float, rng: Rng = Rng()) -> DataFrame:
    """Edges without a random share r; a filter on a keyed draw, so it is pushed below joins."""
    return edges.where(~rng.happens(r, "s", 0, "src", "dst")) if r > 0 else edges


def sparsified_rank(edges: DataFrame, r: float, iterations: int = 2, p_t: float = 0.15, rng: Rng = Rng(), reweight: bool = False) -> DataFrame:
    """Power iteration on the sparsified and repaired graph, over all vertices of the full one; reweight: divided by full degrees."""
    verts = cut(vertices(edges))
    left = sparsified(edges, r, rng)
    idle = verts.join(left.select(F.col("src").alias("id")), "id", "left_anti")
    kept = cut(left.union(idle.select("id", F.col("id").alias("dst"))))
    return fixed(kept, iterations, p_t, degree_of=edges if reweight else None, verts=verts)


def series(edges: DataFrame, t: int, p_t: float = 0.15) -> DataFrame:
    """The law of where a walker stops: sum of p_T (1 - p_T)^s P^s u for s < t, and the rest at t. Equals t iterations."""
    verts = cut(vertices(edges))
    n = verts.count()
    e = cut(with_degree(edges))
    at = start(verts, n)
    out = None
    for s in range(t + 1):
        w = p_t * (1 - p_t) ** s if s < t else (1 - p_t) ** t
        term = at.select("id", (F.col("value") * w).alias("value"))
        out = term if out is None else out.unionByName(term)
        if s < t:
            at = cut(step(at, e, verts, n, 0.0))
    return out.groupBy("id").agg(F.sum("value").alias("value"))


def in_degree(edges: DataFrame) -> DataFrame:
    """The trivial floor: shares of in-edges."""
    total = edges.agg(F.count("*").alias("all"))
    got = vertices(edges).join(edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("c")), "id", "left")
    return got.crossJoin(F.broadcast(total)).select("id", (F.coalesce("c", F.lit(0)) / F.col("all")).alias("value"))


__all__ = ["converged", "delta", "exact", "fixed", "in_degree", "repair", "series", "sparsified", "sparsified_rank", "start", "step", "tolerance", "with_degree"]
