"""The continuous variant: activity edges from a stream of events, and the heaviest users of each window.

Edges lead from each user to the user of the next event of the same channel (event type). Late events beyond the watermark are
dropped by Spark; events that repeat an id within it are dropped too. State is the last event per channel.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from walkrank.functions.rng import Rng
from walkrank.operators import prepare, walk

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"
EDGES = "channel string, ts timestamp, src bigint, dst bigint"


def source(spark, path: str, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def clean(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def window_counts(events: DataFrame, size: str = "1 hour", slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    """(start, event_type, n): tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return events.withWatermark("ts", delay).groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user_id", "n")


def _next(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
    last = state.get[0] if state.exists else None
    users = rows.user_id.tolist()
    src = ([last] if last is not None else []) + users[:-1]
    dst = users if last is not None else users[1:]
    ts = rows.ts.tolist() if last is not None else rows.ts.tolist()[1:]
    if users:
        state.update((int(users[-1]),))
    out = pd.DataFrame({"channel": key[0], "ts": ts, "src": src, "dst": dst})
    yield out[out.src != out.dst] if len(out) else out


def next_user_edges(events: DataFrame) -> DataFrame:
    """(channel, ts, src, dst): stateful; each micro-batch goes on from the last user of the one before."""
    return events.groupBy("event_type").applyInPandasWithState(_next, EDGES, "user bigint", "append", GroupStateTimeout.NoTimeout)


def with_names(edges: DataFrame, customers: DataFrame) -> DataFrame:
    """A stream joined with a static table."""
    return edges.join(customers.select(F.col("c_custkey").alias("dst"), "c_name"), "dst", "left")


def top_users(n_walkers: int = 1000, k: int = 10, into: str = "walkrank_top_users", rng: Rng = Rng()):
    """A foreachBatch function: adds the batch's edges to what it has and ranks anew by walkers."""
    def rerank(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        edges = batch.select(F.col("src").cast("string"), F.col("dst").cast("string"))
        known = spark.table(f"{into}_edges") if spark.catalog.tableExists(f"{into}_edges") else None
        both = edges.distinct() if known is None else known.union(edges).distinct()
        if both.isEmpty():
            return
        from walkrank.functions.session import cut
        both = cut(both)
        both.createOrReplaceTempView(f"{into}_edges")
        lay = prepare.layout(cut(prepare.repair(both)), "source", 4, rng)
        p = walk.WalkParams(n_walkers=n_walkers, horizon=3, refresh_rate=0.7, counters=False, rng=rng)
        walk.top_k(walk.estimate(walk.walker_tally(lay, p).tally, n_walkers), k).withColumn("epoch", F.lit(epoch)).createOrReplaceTempView(into)

    return rerank
