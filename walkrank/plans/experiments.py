"""The experiment workloads: sweeps that write one `run` row per setting, with cost and accuracy side by side.

    python -m walkrank.plans.experiments SF_DIR OUT [NAME...]

Times and bytes are those of the machine it runs on; only ratios between rows of one run are comparable.
"""

from __future__ import annotations

import sys
from collections.abc import Iterator
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.functions.rng import Rng
from walkrank.functions.session import cut
from walkrank.operators import accuracy, baselines, cost, prepare, walk
from walkrank.plans.methods import graph

RUN = "experiment string, method string, graph string, params map<string,string>, seconds double, step_seconds double, task_seconds double, cpu_seconds double, shuffle_bytes bigint, model_bytes bigint, k int, mass double, hit_share double"


class Bench:
    """A prepared graph (loading isn't timed) with its converged vector."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, shards: int = 8, kind: str = "random", seed: int = 7):
        self.spark, self.name, self.rng = spark, name, Rng(seed, "fast")
        self.edges = cut(prepare.repair(cut(graph(spark, sf_dir, name))))
        self.layout = prepare.layout(self.edges, kind, shards, self.rng)
        self.ref = cut(baselines.exact(self.edges))
        self.extra = cost.baseline_model_bytes(self.layout, 1).first()["bytes"]

    def row(self, experiment: str, method: str, est: DataFrame, used: dict, steps: int, size: int, params: dict, k: int) -> tuple:
        got = accuracy.curve(est, self.ref, [k]).first()
        return experiment, method, self.name, {a: str(b) for a, b in params.items()}, used["seconds"], used["seconds"] / max(1, steps), used["task_seconds"], used["cpu_seconds"], int(used["shuffle_bytes"]), int(size), k, got["mass_norm"], got["hit_share"]

    def walkers(self, experiment: str, k: int, **params) -> tuple:
        p = walk.WalkParams(rng=self.rng, **params)
        with cost.meter(self.spark) as used:  # without counters, as the baselines have none
            got = walk.walker_tally(self.layout, replace(p, counters=False))
            est = cut(walk.estimate(got.tally, p.n_walkers, p.normalize))
        got.release()
        counted = walk.walker_tally(self.layout, replace(p, counters=True))
        counted.release()
        return self.row(experiment, "walkers", est, used, len(counted.steps), cost.walker_model_bytes(counted.steps), params | {"shards": self.layout.replicas.select("shard").distinct().count()}, k)

    def power(self, experiment: str, k: int, iterations: int) -> tuple:
        """Power iteration on the walkers' own replicas, through the runner."""
        with cost.meter(self.spark) as used:
            est = walk.run(walk.power_program(self.layout), self.layout, iterations)
        return self.row(experiment, "power", est, used, iterations, self.extra * iterations, {"iterations": iterations}, k)

    def converged(self, experiment: str, k: int, tol: float = 1e-6) -> tuple:
        """Power iteration to a tolerance, on edges dealt by source."""
        with cost.meter(self.spark) as used:
            est, iterations = baselines.tolerance(self.edges, tol, every=10)
        return self.row(experiment, "converged", est, used, iterations, self.extra * iterations, {"tolerance": tol, "iterations": iterations}, k)

    def sparse(self, experiment: str, k: int, r: float, iterations: int = 2) -> tuple:
        with cost.meter(self.spark) as used:
            est = cut(baselines.sparsified_rank(self.edges, r, iterations, rng=self.rng))
        return self.row(experiment, "sparsified", est, used, iterations, int(self.extra * iterations * (1 - r)), {"r": r, "iterations": iterations}, k)


def _n(b: Bench, share: float) -> int:
    return max(100, int(b.layout.n * share))


def cluster_size(spark, d) -> Iterator[tuple]:
    """W1: shards stand for machines; local cores are set when the session starts."""
    for shards in (4, 8, 12, 16, 24):
        b = Bench(spark, d, "words", shards)
        for p in (1.0, 0.7, 0.4, 0.1):
            yield b.walkers("cluster_size", 100, n_walkers=_n(b, 0.2), refresh_rate=p)
        for i in (1, 2):
            yield b.power("cluster_size", 100, i)
        yield b.converged("cluster_size", 100)


def accuracy_k(spark, d) -> Iterator[tuple]:
    """W2."""
    b = Bench(spark, d, "words")
    for k in (10, 30, 100, 300, 1000):
        for p in (1.0, 0.7, 0.4, 0.1):
            yield b.walkers("accuracy_k", k, n_walkers=_n(b, 0.5), refresh_rate=p)
        for i in (1, 2):
            yield b.power("accuracy_k", k, i)


def frontier(spark, d, name: str = "words", k: int = 100) -> Iterator[tuple]:
    """W3, W4 (the same rows as a table of three measures), W8 on the small graphs."""
    b = Bench(spark, d, name)
    for t in (2, 3, 4, 5, 6):
        for p in (1.0, 0.7, 0.4, 0.1):
            yield b.walkers(f"frontier_{name}", k, n_walkers=_n(b, 0.5), horizon=t, refresh_rate=p)
    for i in (1, 2, 4):
        yield b.power(f"frontier_{name}", k, i)


def small_frontier(spark, d) -> Iterator[tuple]:
    """W8: the frontier on the smaller graphs."""
    for name, k in (("trade", 50), ("similarity", 20)):
        yield from frontier(spark, d, name, k)


def sparsify(spark, d) -> Iterator[tuple]:
    """W5."""
    b = Bench(spark, d, "words")
    for r in (0.1, 0.3, 0.5, 0.7):
        yield b.sparse("sparsify", 100, r)
    for p in (1.0, 0.7, 0.4, 0.1):
        yield b.walkers("sparsify", 100, n_walkers=_n(b, 0.5), refresh_rate=p)


def sweep_walkers(spark, d) -> Iterator[tuple]:
    """W6."""
    b = Bench(spark, d, "similarity")
    for share in (0.02, 0.05, 0.1, 0.2, 0.5, 1, 2, 8, 32):
        yield b.walkers("sweep_walkers", 20, n_walkers=max(10, int(b.layout.n * share)))


def bytes_vs_n(spark, d) -> Iterator[tuple]:
    """W9: traffic against the number of walkers, at full and at partial refresh."""
    b = Bench(spark, d, "trade")
    for share in (0.1, 0.2, 0.5, 1, 2, 4):
        for p in (1.0, 0.4):
            yield b.walkers("bytes_vs_n", 50, n_walkers=_n(b, share), refresh_rate=p)


def sweep_horizon(spark, d) -> Iterator[tuple]:
    """W7."""
    b = Bench(spark, d, "similarity")
    for t in range(1, 9):
        yield b.walkers("sweep_horizon", 20, n_walkers=_n(b, 16), horizon=t)


def two_sizes(spark, d) -> Iterator[tuple]:
    """W10: one setting on this scale factor; run it on several."""
    for name in ("words", "trade"):
        b = Bench(spark, d, name)
        yield b.walkers("two_sizes", 100, n_walkers=20_000)


def ablation(spark, d) -> Iterator[tuple]:
    """W16: one factor at a time."""
    for kind in ("random", "grid", "source", "chunked"):
        b = Bench(spark, d, "similarity", kind=kind)
        base = {"n_walkers": _n(b, 16), "refresh_rate": 0.4}
        yield b.walkers(f"ablation_layout_{kind}", 20, **base)
        if kind == "random":
            for more in ({"rounding": "exact"}, {"replica_weight": "degree"}, {"scatter": "binomial"}, {"scatter": "binomial_unbiased"}, {"erasure": "independent"}, {"birth": "per_vertex"}, {"normalize": "total"}):
                yield b.walkers("ablation_" + "_".join(map(str, next(iter(more.items())))), 20, **base, **more)


ALL = {f.__name__: f for f in (cluster_size, accuracy_k, frontier, small_frontier, sparsify, sweep_walkers, bytes_vs_n, sweep_horizon, two_sizes, ablation)}


def scaling(rows: DataFrame, size: str = "shards") -> DataFrame:
    """Speed-up over the smallest cluster and its share of the ideal, per method and setting, of cluster_size's rows.

    Rows without that parameter (the baseline's) drop out; params but `size` name a setting.
    """
    setting = F.map_filter("params", lambda key, _: ~key.isin(size, "n_walkers"))
    at = rows.where(F.map_contains_key("params", F.lit(size))).select("method", "graph", "k", F.to_json(F.map_from_entries(F.array_sort(F.map_entries(setting)))).alias("setting"), F.element_at("params", size).cast("int").alias("size"), "seconds")
    least = W.partitionBy("method", "graph", "k", "setting").orderBy("size")
    up = F.first("seconds").over(least) / F.col("seconds")
    return at.withColumn("speed_up", up).withColumn("efficiency", up * F.first("size").over(least) / F.col("size"))


def runs(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A table of run rows."""
    return spark.createDataFrame(list(ALL[name](spark, sf_dir)), RUN)


def main(args: list[str]) -> None:
    spark = SparkSession.builder.config("spark.sql.shuffle.partitions", "8").config("spark.ui.enabled", "false").getOrCreate()
    for name in args[2:] or ALL:
        out = runs(spark, args[0], name)
        out.write.mode("append").partitionBy("experiment").parquet(args[1])
        out.show(200, truncate=False)


if __name__ == "__main__":
    main(sys.argv[1:])
