"""Connected components of a table of links, as DataFrames.

Rounds of two steps (every node's larger neighbours are hung under its least neighbour, then its
smaller ones) until nothing changes. Each round's links are checkpointed; the loop ends after about
log n rounds. Hot nodes are handled by partial aggregation and by skewed-join splitting.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from walkrank.llm.common import cut


def _hang(links: DataFrame, larger: bool) -> DataFrame:
    """One step: for each node u with neighbours v, link the chosen v (and u) to the least of all."""
    if larger:
        links = links.union(links.select("b", "a"))
    links = links.toDF("u", "v")
    if not larger:
        links = links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = links.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    hung = links.join(least, "u")
    out = hung.where(F.col("v") > F.col("u")).select("v", "m") if larger else hung.select("v", "m").union(least.select("u", "m"))
    return out.toDF("a", "b").where("a <> b").distinct()


def components(links: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, component): for the nodes of links (a long, b long), the smallest node that each can reach."""
    links = cut(links.select(F.col("a").cast("long"), F.col("b").cast("long")).where("a <> b").distinct())
    seen = None
    for _ in range(max_rounds):
        links = cut(_hang(_hang(links, larger=True), larger=False))
        state = links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == seen:
            break
        seen = state
    else:
        raise RuntimeError(f"components have not settled after {max_rounds} rounds")
    pairs = links.select(F.greatest("a", "b").alias("node"), F.least("a", "b").alias("component"))
    return pairs.union(pairs.select("component", "component")).groupBy("node").agg(F.min("component").alias("component"))


def local_components(n: int, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """For nodes 0..n-1 with links u-v: the smallest node that each can reach."""
    root = np.arange(n)
    while len(u):
        a, b = root[u], root[v]
        apart = a != b
        if not apart.any():
            break
        u, v, a, b = u[apart], v[apart], a[apart], b[apart]
        np.minimum.at(root, np.maximum(a, b), np.minimum(a, b))
        while True:
            up = root[root]
            if (up == root).all():
                break
            root = up
    return root
