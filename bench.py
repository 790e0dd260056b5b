"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

Graphs are built and laid out before timing, as loading isn't part of the published times. `ratios` holds the walker
method against the baseline: seconds per step, model bytes, and accuracy beside them.
"""

from __future__ import annotations

import json
import os
import tempfile
import time

from pyspark.sql import SparkSession

from walkrank.functions.rng import Rng
from walkrank.functions.session import cut
from walkrank.operators import accuracy, baselines, cost, prepare, walk
from walkrank.plans import relational
from walkrank.plans.methods import graph


def main() -> None:
    sf = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    cpus = os.environ.get("BENCH_CPUS", "4")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "4g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.checkpoint.dir", tempfile.mkdtemp(prefix="bench-")).getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    took: dict[str, float] = {}
    ratios: dict[str, float] = {}

    def timed(name: str, f):
        began = time.monotonic()
        out = f()
        took[name] = round(time.monotonic() - began, 3)
        return out

    rng = Rng(7, "fast")
    for name, share in (("words", 0.2), ("trade", 1.0)):
        edges = timed(f"{name}_load", lambda: cut(prepare.repair(cut(graph(spark, sf, name)))))
        lay = timed(f"{name}_layout", lambda: prepare.layout(edges, "random", 8, rng))
        n = int(lay.n * share)
        base = timed(f"{name}_power2", lambda: cut(baselines.fixed(edges, 2)))
        ref = timed(f"{name}_power10", lambda: cut(baselines.fixed(edges, 10)))
        timed(f"{name}_sparsified_r50", lambda: cut(baselines.sparsified_rank(edges, 0.5, 2, rng=rng)))
        extra = cost.baseline_model_bytes(lay, 1).first()["bytes"]
        for p in (1.0, 0.7, 0.4, 0.1):
            run = walk.walker_tally(lay, walk.WalkParams(n_walkers=n, refresh_rate=p, counters=False, rng=rng))
            tally = timed(f"{name}_walkers_ps{p}", lambda: cut(run.tally))
            run.release()
            got = accuracy.curve(walk.estimate(tally, n), ref, [100]).first()
            ratios[f"{name}_ps{p}_mass100"] = round(got["mass_norm"], 4)
            ratios[f"{name}_ps{p}_identified100"] = round(got["hit_share"], 3)
        steps = walk.walker_tally(lay, walk.WalkParams(n_walkers=n, refresh_rate=0.1, rng=rng)).steps
        ratios[f"{name}_bytes_power10_over_walkers"] = round(10 * extra / max(1, cost.walker_model_bytes(steps)), 1)
        ratios[f"{name}_step_speedup"] = round((took[f"{name}_power10"] / 10) / (took[f"{name}_walkers_ps0.1"] / 4), 2)
        got = accuracy.curve(base, ref, [100]).first()
        ratios[f"{name}_power2_mass100"] = round(got["mass_norm"], 4)
    for q in ("join_rank_edges", "interval_activity_edges", "asof_user_order", "adjacency_arrays", "rollup_trade"):
        timed(q, lambda: relational.Q[q](spark, sf).write.format("noop").mode("overwrite").save())
    print(json.dumps({"metric": "seconds over all headline queries", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": sf.rsplit("sf", 1)[-1], "ratios": ratios, "cpus": cpus}))


if __name__ == "__main__":
    main()
