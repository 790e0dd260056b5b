"""Error bounds as calculators (numbers in, number out), as columns for sweeps, and diagnostics measured on graphs."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.functions.session import cut
from walkrank.operators.accuracy import beside
from walkrank.operators.baselines import start, step, with_degree
from walkrank.operators.prepare import vertices


def mixing(p_t: float, t: int) -> float:
    """Part of the bound that is due to stopping after t steps."""
    return math.sqrt((1 - p_t) ** (t + 1) / p_t)


def sampling(k: int, delta: float, n_walkers: int, p_s: float, p_meet: float) -> float:
    """Part that is due to few walkers and to their shared erasures."""
    return math.sqrt(k / delta * (1 / n_walkers + (1 - p_s**2) * p_meet))


def total(p_t: float, t: int, k: int, delta: float, n_walkers: int, p_s: float, p_meet: float) -> float:
    """With probability 1 - delta at least, the mass captured falls short of the best by no more than this."""
    return mixing(p_t, t) + sampling(k, delta, n_walkers, p_s, p_meet)


def meeting(n: int, t: int, pi_max: float, p_t: float) -> float:
    """Bound on the probability that two walkers meet within t steps."""
    return 1 / n + t * pi_max / p_t


def power_law(n: int, theta: float = 2.2, gamma: float = 0.5, c: float = 1.0) -> float:
    """Bound on P(largest rank > n^-gamma) for ranks with a power-law tail; the constant is the caller's."""
    return c * n ** (gamma - 1 / (theta - 1))


def meeting_power_law(n: int, t: int, p_t: float) -> float:
    return 1 / n + t / (p_t * math.sqrt(n))


def plan_walkers(mu: float, k: int, const: float = 1.0) -> tuple[int, int]:
    """(t, N) of the order that a loss of mu asks for; the constants are ours."""
    return max(1, math.ceil(const * math.log(1 / mu))), math.ceil(const * k / mu**2)


def chi2_decay(p_t: float, t: int) -> float:
    return (1 - p_t) / p_t * (1 - p_t) ** t


def chi2_start(c: float) -> float:
    return (1 - c) / c


def interference(p_s: float, p_meet: float) -> float:
    """Bound on the probability that shared erasures ever part two walkers' law from that of independent ones."""
    return (1 - p_s**2) * p_meet


def second_moment(n_walkers: int, p_s: float, p_meet: float) -> float:
    return 1 / n_walkers + (n_walkers - 1) * (1 - p_s**2) * p_meet / n_walkers


def tail(n_walkers: int, p_s: float, p_meet: float, eps: float) -> float:
    """P(distance >= eps) by Markov's inequality."""
    return min(1.0, second_moment(n_walkers, p_s, p_meet) / eps**2)


def chernoff_samples(x: float, eps: float, delta: float) -> int:
    """Independent walkers that see a vertex of mass x within relative error eps with probability 1 - delta."""
    return math.ceil(3 * math.log(2 / delta) / (eps**2 * x))


def columns(rows: DataFrame) -> DataFrame:
    """rows (p_t, t, k, delta, n_walkers, p_s, p_meet, n, pi_max) with the bounds as columns: one projection."""
    c = F.col
    mix = F.sqrt(F.pow(1 - c("p_t"), c("t") + 1) / c("p_t"))
    block = (1 - c("p_s") * c("p_s")) * c("p_meet")
    samp = F.sqrt(c("k") / c("delta") * (1 / c("n_walkers") + block))
    return rows.withColumns({
        "mixing": mix, "sampling": samp, "total": mix + samp, "meeting": 1 / c("n") + c("t") * c("pi_max") / c("p_t"),
        "chi2_decay": (1 - c("p_t")) / c("p_t") * F.pow(1 - c("p_t"), c("t")), "interference": block,
        "second_moment": 1 / c("n_walkers") + (c("n_walkers") - 1) * block / c("n_walkers"),
        "meeting_power_law": 1 / c("n") + c("t") / (c("p_t") * F.sqrt("n")),
        "rank_tail": F.least(F.lit(1.0), F.pow(c("n").cast("double"), c("gamma") - 1 / (c("theta") - 1))),
        "chi2_start": (1 - c("p_t")) / c("p_t"), "distance_tail": F.least(F.lit(1.0), (1 / c("n_walkers") + (c("n_walkers") - 1) * block / c("n_walkers")) / (c("eps") * c("eps"))),
        "plan_t": F.greatest(F.lit(1), F.ceil(F.ln(1 / c("mu")))).cast("int"), "plan_n": F.ceil(c("k") / (c("mu") * c("mu"))).cast("long"),
        "chernoff": F.ceil(3 * F.ln(2 / c("delta")) / (c("eps") * c("eps") * c("pi_max"))).cast("long"),
    })


def sweep(measured: DataFrame) -> DataFrame:
    """A grid of parameters for graphs of which measured (n, pi_max) has a row each; p_meet from its power-law bound."""
    one = measured.select("n", "pi_max", *(F.lit(v).alias(c) for c, v in {"p_t": 0.15, "delta": 0.1, "theta": 2.2, "gamma": 0.5, "eps": 0.11, "mu": 0.07}.items()))
    grid = one.withColumn("t", F.explode(F.array(*map(F.lit, (3, 4, 10, 11, 40))))).withColumn("k", F.explode(F.array(F.lit(10), F.lit(100)))).withColumn("n_walkers", F.explode(F.array(F.lit(8000), F.lit(800000)))).withColumn("p_s", F.explode(F.array(*map(F.lit, (1.0, 0.7, 0.4, 0.1)))))
    return columns(grid.withColumn("p_meet", 1 / F.col("n") + F.col("t") / (F.col("p_t") * F.sqrt("n"))))


def meeting_mass(edges: DataFrame, t: int, p_t: float = 0.15) -> DataFrame:
    """(step, l2sq, cumulative): squared norms of the walk's law from equal shares; their sum bounds P(two walkers meet)."""
    verts = cut(vertices(edges))
    n = verts.count()
    e = cut(with_degree(edges))
    rank = start(verts, n)
    out = None
    for s in range(t + 1):
        row = rank.agg(F.lit(s).alias("step"), F.sum(F.col("value") * F.col("value")).alias("l2sq"))
        out = row if out is None else out.unionByName(row)
        if s < t:
            rank = cut(step(rank, e, verts, n, p_t))
    return out.withColumn("cumulative", F.sum("l2sq").over(W.orderBy("step")))  # t + 1 rows


def contraction(edges: DataFrame, iterations: int, p_t: float = 0.15) -> DataFrame:
    """(step, l1_delta, ratio): the change per iteration and how it shrinks; by 1 - p_T at least."""
    verts = cut(vertices(edges))
    n = verts.count()
    e = cut(with_degree(edges))
    rank = cut(start(verts, n))
    out = None
    for s in range(1, iterations + 1):
        new = cut(step(rank, e, verts, n, p_t))
        row = beside(new, rank).agg(F.lit(s).alias("step"), F.sum(F.abs(F.col("a") - F.col("b"))).alias("l1_delta"))
        out = row if out is None else out.unionByName(row)
        rank = new
    return out.withColumn("ratio", F.col("l1_delta") / F.lag("l1_delta").over(W.orderBy("step")))  # a row an iteration


def met(pos: DataFrame) -> DataFrame:
    """(a, b, step): the first step at which two walkers of pos (walker, id, step) stand on one vertex, for pairs (2i, 2i + 1)."""
    pairs = pos.select("step", "id", F.expr("walker div 2").alias("pair"), F.col("walker"))
    both = pairs.groupBy("pair", "step", "id").agg(F.count("*").alias("c"), F.min("walker").alias("a"), F.max("walker").alias("b")).where("c = 2")
    return both.groupBy("a", "b").agg(F.min("step").alias("step"))


def meet_rate(pos: DataFrame, n_walkers: int) -> DataFrame:
    """(step, pairs, rate): pairs of walkers (all of them) on one vertex per step, from counts per vertex."""
    c = pos.groupBy("step", "id").agg(F.count("*").alias("c"))
    return c.groupBy("step").agg(F.sum(F.expr("c * (c - 1) div 2")).cast("long").alias("pairs")).withColumn("rate", F.col("pairs") / F.lit(n_walkers * (n_walkers - 1) / 2))


def first_interference(pos: DataFrame) -> DataFrame:
    """(step, pairs): the first step at which a pair (2i, 2i + 1) of a blocking walk stands together while one of it is blocked in its next move; how many pairs by step.

    A pair that meets unblocked and is blocked when it is together later counts at that later step.
    """
    nxt = pos.where("blocked").select("walker", (F.col("step") - 1).alias("step"), F.lit(1).alias("hit"))
    now = pos.select("walker", "step", "id").join(nxt, ["walker", "step"], "left").groupBy(F.expr("walker div 2").alias("pair"), "step", "id").agg(F.count("*").alias("c"), F.max("hit").alias("hit"))
    first = now.where("c = 2 and hit = 1").groupBy("pair").agg(F.min("step").alias("step"))
    return first.groupBy("step").agg(F.count("*").alias("pairs"))


def floor_ceiling(rank: DataFrame, n: int, p_t: float = 0.15, walks: DataFrame | None = None) -> DataFrame:
    """(least, most, floor_ok), and, given the laws of walks (id, value), (walk_most, ceiling, ceiling_ok): every vertex has a rank of
    p_T / n at least, and no walk's law has a vertex over the largest rank divided by p_T."""
    out = rank.agg(F.min("value").alias("least"), F.max("value").alias("most")).withColumn("floor_ok", F.col("least") >= p_t / n - 1e-15)
    if walks is None:
        return out
    return out.crossJoin(walks.agg(F.max("value").alias("walk_most"))).withColumn("ceiling", F.col("most") / p_t).withColumn("ceiling_ok", F.col("walk_most") <= F.col("ceiling") + 1e-15)


def step_lengths(pos: DataFrame, n_walkers: int, horizon: int, p_t: float = 0.15) -> DataFrame:
    """(step, stopped, expected): when walkers stopped, and when they should."""
    got = pos.where("stopped").groupBy("step").agg(F.count("*").alias("stopped"))
    law = F.when(F.col("step") < horizon, F.pow(F.lit(1 - p_t), F.col("step")) * p_t).otherwise(F.lit((1 - p_t) ** horizon))
    return got.withColumn("expected", law * n_walkers)


def set_mass_gap(est: DataFrame, ref: DataFrame, k: int) -> DataFrame:
    """(gap, bound, ok): for the k vertices that differ most, the difference in mass is at most sqrt(k) times the L2 distance."""
    d = beside(est, ref).select(F.abs(F.col("a") - F.col("b")).alias("d"), "id")
    top = d.orderBy(F.desc("d"), "id").limit(k).agg(F.sum("d").alias("gap"))
    l2 = d.agg((F.sqrt(F.sum(F.col("d") * F.col("d"))) * math.sqrt(k)).alias("bound"))
    return top.crossJoin(l2).withColumn("ok", F.col("gap") <= F.col("bound") + 1e-12)
