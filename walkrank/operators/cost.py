"""Cost: seconds per step and in all, model bytes (a stated model), and Spark's own counters from the event log."""

from __future__ import annotations

import json
import time
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkrank.operators.prepare import Layout

#: Bytes of an id and a count.
MESSAGE = 16


def walker_model_bytes(steps: list[dict]) -> int:
    """Refresh messages and merged signals, each an id and a count."""
    return sum(MESSAGE * (s["refresh_sent"] + s["destinations"]) for s in steps)


def baseline_model_bytes(layout: Layout, iterations: int) -> DataFrame:
    """(iterations, messages, bytes): per iteration a partial sum up and a value down for each replica beyond the owner."""
    extra = layout.directory.agg(F.sum(F.size("reps") - 1).alias("x"))
    return extra.select(F.lit(iterations).alias("iterations"), (2 * F.col("x") * iterations).alias("messages"), (2 * F.col("x") * iterations * MESSAGE).alias("bytes"))


def _stages(spark: SparkSession) -> dict[tuple[int, int], tuple[float, float, int]]:
    """(seconds of tasks, their CPU seconds in the JVM, bytes written to shuffles) of each stage attempt that Spark's own status store still holds.

    Not by executor: of a local master's one, which is the driver, the store tells the application's age as its task time.
    """
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    rows = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    each = [rows.apply(i) for i in range(rows.size())]
    return {(x.stageId(), x.attemptId()): (x.executorRunTime() / 1e3, x.executorCpuTime() / 1e9, x.shuffleWriteBytes()) for x in each}


@contextmanager
def meter(spark: SparkSession) -> Iterator[dict]:
    """Fills a dict with seconds, task_seconds (all tasks' run time), cpu_seconds (theirs in the JVM, without Python workers) and shuffle_bytes of
    what runs inside, which may have as many stages as spark.ui.retainedStages (1000) keeps."""
    out: dict = {}
    before, began = _stages(spark), time.monotonic()
    yield out
    out["seconds"] = time.monotonic() - began
    more = [[a - b for a, b in zip(got, before.get(key, (0, 0, 0)))] for key, got in _stages(spark).items()]
    out["task_seconds"], out["cpu_seconds"], out["shuffle_bytes"] = (sum(x[k] for x in more) for k in range(3))


def event_log(folder: str) -> dict:
    """Shuffle bytes written and read, CPU seconds and spill over all tasks in an event log folder."""
    out = {"shuffle_written": 0, "shuffle_read": 0, "remote_read": 0, "cpu_s": 0.0, "spill": 0, "tasks": 0}
    for path in Path(folder).rglob("*"):
        if not path.is_file():
            continue
        for line in path.open(errors="replace"):
            if '"SparkListenerTaskEnd"' not in line:
                continue
            m = json.loads(line).get("Task Metrics") or {}
            r, w = m.get("Shuffle Read Metrics", {}), m.get("Shuffle Write Metrics", {})
            out["shuffle_written"] += w.get("Shuffle Bytes Written", 0)
            out["shuffle_read"] += r.get("Remote Bytes Read", 0) + r.get("Local Bytes Read", 0)
            out["remote_read"] += r.get("Remote Bytes Read", 0)
            out["cpu_s"] += m.get("Executor CPU Time", 0) / 1e9
            out["spill"] += m.get("Disk Bytes Spilled", 0)
            out["tasks"] += 1
    return out
