"""Session helpers: lineage cuts in the folder that the session names, size-checked broadcasts."""

from __future__ import annotations

import re
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the folder that the session names; only a local master may go without one.

    A checkpoint alone would compute its plan twice (once to run it, once to write it), so the plan is cached meanwhile.
    """
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        named = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not named and not re.fullmatch(r"local(\[[^,\]]*(,[^\]]*)?\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="walkrank-"))
    df.persist()
    out = df.checkpoint(eager=True)
    df.unpersist()
    return out


def dealt(df: DataFrame, n: int, key: str) -> DataFrame:
    """cut() of rows dealt to n partitions by a key, of which later plans know (an adaptive plan does not tell them)."""
    conf, name = df.sparkSession.conf, "spark.sql.adaptive.enabled"
    was = conf.get(name)
    conf.set(name, "false")
    try:
        return cut(df.repartition(n, key))
    finally:
        conf.set(name, was)


def released(spark: SparkSession) -> None:
    """Has Spark remove the shuffle files of frames that nobody holds any more; by itself it does so only when the driver collects garbage."""
    spark.sparkContext._jvm.System.gc()


def small(df: DataFrame, rows: int, most_rows: int = 2_000_000) -> DataFrame:
    """`df` marked for broadcast if its row bound is proven and small, else as it is (a shuffle join then)."""
    return F.broadcast(df) if rows <= most_rows else df
