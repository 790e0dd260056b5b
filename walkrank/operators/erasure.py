"""Erasure models: which out-edges of a vertex can carry walkers in a step."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from walkrank.functions.rng import Rng


def independent(edges: DataFrame, p_s: float, step: int, rng: Rng = Rng()) -> DataFrame:
    """Each edge is live with probability p_s."""
    return edges.where(rng.happens(p_s, "e", step, "src", "dst"))


def at_least_one(edges: DataFrame, p_s: float, step: int, rng: Rng = Rng()) -> DataFrame:
    """As independent(); a source that would have none gets one edge, each alike: the least by its own draw."""
    flagged = edges.select("src", "dst", rng.happens(p_s, "e", step, "src", "dst").alias("live"), rng.draw("f", step, "src", "dst").alias("h"))
    per = flagged.groupBy("src").agg(F.collect_list(F.when(F.col("live"), F.col("dst"))).alias("live"), F.min_by("dst", F.struct("h", "dst")).alias("forced"))
    return per.select("src", F.explode(F.when(F.size("live") > 0, F.col("live")).otherwise(F.array("forced"))).alias("dst"))


def live_replicas(directory: DataFrame, p_s: float, step: int, rng: Rng = Rng(), force: bool = True) -> DataFrame:
    """`directory` with reps cut to those refreshed in this step. Narrow: no shuffle, and it runs before rows travel."""
    if p_s >= 1:
        return directory
    chosen = F.filter("reps", lambda r: rng.draw("r", step, F.col("src"), r["shard"]) < F.lit(int(p_s * (1 << 60))))
    if not force:
        return directory.withColumn("reps", chosen)
    one = F.array(F.element_at("reps", (1 + rng.draw("f", step, "src") % F.size("reps")).cast("int")))
    return directory.withColumn("__live", chosen).withColumn("reps", F.when(F.size("__live") > 0, F.col("__live")).otherwise(one)).drop("__live")


def by_replica(replicas: DataFrame, directory: DataFrame, p_s: float, step: int, rng: Rng = Rng(), force: bool = True) -> DataFrame:
    """(src, dst): the edges of the refreshed replicas."""
    live = live_replicas(directory, p_s, step, rng, force).select("src", F.explode("reps").alias("r")).select("src", "r.shard")
    return replicas.join(live, ["src", "shard"], "left_semi").select("src", F.explode("nbrs").alias("dst"))


def live_probability(d: Column, p_s: Column | float) -> Column:
    """P(an edge is live) under at_least_one."""
    p = F.lit(p_s) if isinstance(p_s, float) else p_s
    return p + F.pow(1 - p, d) / d


def no_block_probability(d: Column, p_s: Column | float) -> Column:
    """P(neither of two walkers that meet is blocked) under at_least_one."""
    p = F.lit(p_s) if isinstance(p_s, float) else p_s
    return live_probability(d, p) / d + (1 - 1 / d) * p * p


def audit(edges: DataFrame, p_s: float, steps: int, model: str = "at_least_one", rng: Rng = Rng()) -> DataFrame:
    """(property, observed, required, ok): rates over many steps, on a graph of few edges.

    keep: share of live edges. joint: P(live | another edge of the source is live). source: correlation of the
    live counts of different sources. step: correlation of one edge's states in successive steps.
    """
    f = {"independent": independent, "at_least_one": at_least_one}[model]
    live = None
    for s in range(steps):
        one = f(edges, p_s, s, rng).select("src", "dst", F.lit(s).alias("step"))
        live = one if live is None else live.union(one)
    grid = edges.crossJoin(edges.sparkSession.range(steps).select(F.col("id").cast("int").alias("step")))  # steps x a few edges
    state = grid.join(live.withColumn("x", F.lit(1.0)), ["src", "dst", "step"], "left").fillna({"x": 0.0})
    state = state.persist()
    keep = state.agg(F.avg("x")).first()[0]
    per = state.groupBy("src", "step").agg(F.sum("x").alias("n"), F.count("*").alias("d")).where("d > 1")
    joint = per.agg(F.sum(F.col("n") * (F.col("n") - 1)) / F.sum(F.col("n") * (F.col("d") - 1))).first()[0]
    a = state.groupBy("src", "step").agg(F.avg("x").alias("a"))
    pair = a.alias("l").join(a.alias("r"), (F.col("l.step") == F.col("r.step")) & (F.col("l.src") < F.col("r.src")))
    source = pair.agg(F.corr("l.a", "r.a")).first()[0]
    later = state.select("src", "dst", (F.col("step") - 1).alias("step"), F.col("x").alias("y"))
    follow = state.join(later, ["src", "dst", "step"]).agg(F.corr("x", "y")).first()[0]
    state.unpersist()
    rows = [("keep", keep, p_s, keep >= p_s - 0.05), ("joint", joint, p_s, joint is not None and joint >= p_s - 0.03), ("source", source, 0.0, source is None or abs(source) < 0.1), ("step", follow, 0.0, follow is None or abs(follow) < 0.1)]
    return edges.sparkSession.createDataFrame(rows, "property string, observed double, required double, ok boolean")
