"""Accuracy of an estimate of the rank vector against a reference: both frames (id, value)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.operators.walk import top_k


def mass_captured(est: DataFrame, ref: DataFrame, k: int, normalised: bool = False) -> DataFrame:
    """(k, mass): the reference's weight of the estimate's k heaviest; normalised by the reference's own best k."""
    got = top_k(est, k).select("id").join(ref, "id", "left").agg(F.coalesce(F.sum("value"), F.lit(0.0)).alias("got"))
    if not normalised:
        return got.select(F.lit(k).alias("k"), F.col("got").alias("mass"))
    best = top_k(ref, k).agg(F.sum("value").alias("best"))
    return got.crossJoin(best).select(F.lit(k).alias("k"), F.when(F.col("best") > 0, F.col("got") / F.col("best")).otherwise(0.0).alias("mass"))


def identified(est: DataFrame, ref: DataFrame, k: int) -> DataFrame:
    """(k, hits, hit_share): how many of the reference's k heaviest are among the estimate's."""
    both = top_k(est, k).select("id").intersect(top_k(ref, k).select("id")).agg(F.count("*").alias("hits"))
    return both.select(F.lit(k).alias("k"), "hits", (F.col("hits") / F.lit(max(k, 1))).alias("hit_share"))


def curve(est: DataFrame, ref: DataFrame, ks: list[int]) -> DataFrame:
    """(k, mass, mass_norm, hits, hit_share) for all ks at once, over one pass to the largest k."""
    most = max(ks)
    mine = top_k(est, most).select("id", F.col("position").alias("p"))
    best = top_k(ref, most).select("id", F.col("position").alias("q"), F.col("value").alias("w"))
    both = mine.join(F.broadcast(best), "id", "left").join(ref.withColumnRenamed("value", "v"), "id", "left")
    rows = mine.sparkSession.createDataFrame([(k,) for k in ks], "k int")
    got = both.join(F.broadcast(rows), F.col("p") <= F.col("k")).groupBy("k").agg(F.sum("v").alias("mass"), F.count_if(F.col("q") <= F.col("k")).alias("hits"))
    top = best.join(F.broadcast(rows), F.col("q") <= F.col("k")).groupBy("k").agg(F.sum("w").alias("best"))
    return got.join(top, "k").select("k", "mass", (F.col("mass") / F.col("best")).alias("mass_norm"), "hits", (F.col("hits") / F.col("k")).alias("hit_share"))


def beside(a: DataFrame, b: DataFrame) -> DataFrame:
    """(id, a, b), zeros where one lacks a vertex."""
    return a.withColumnRenamed("value", "a").join(b.withColumnRenamed("value", "b"), "id", "full_outer").select("id", F.coalesce("a", F.lit(0.0)).alias("a"), F.coalesce("b", F.lit(0.0)).alias("b"))


def distance(a: DataFrame, b: DataFrame) -> DataFrame:
    """(l1, l2, linf, chi2): norms of the difference, and the contrast sum of (a - b)^2 / b."""
    d = F.col("a") - F.col("b")
    return beside(a, b).agg(F.sum(F.abs(d)).alias("l1"), F.sqrt(F.sum(d * d)).alias("l2"), F.max(F.abs(d)).alias("linf"), F.sum(F.when(F.col("b") > 0, d * d / F.col("b"))).alias("chi2"))


def loss_chain(est: DataFrame, ref: DataFrame, k: int) -> DataFrame:
    """(loss, l1, root_chi2, ok): the loss of mass of the estimate's k heaviest is at most l1, and that the root of chi2."""
    best, got = mass_captured(ref, ref, k), mass_captured(est, ref, k)
    d = distance(est, ref)
    loss = best.select(F.col("mass").alias("m")).crossJoin(got.select(F.col("mass").alias("g"))).crossJoin(d).select((F.col("m") - F.col("g")).alias("loss"), "l1", F.sqrt("chi2").alias("root_chi2"))
    return loss.withColumn("ok", (F.col("loss") <= F.col("l1") + 1e-12) & (F.col("l1") <= F.col("root_chi2") + 1e-12))


def rank_corr(a: DataFrame, b: DataFrame, k: int) -> DataFrame:
    """(k, spearman, ndcg): of the reference b's k heaviest."""
    best = top_k(b, k).select("id", F.col("value").alias("b"), "position")
    both = best.join(a.withColumnRenamed("value", "a"), "id", "left").fillna({"a": 0.0})
    ranked = both.withColumn("p", F.row_number().over(W.orderBy(F.desc(F.round("a", 12)), "id")))  # k rows
    mine = top_k(a, k).join(b.withColumnRenamed("value", "g"), "id", "left").fillna({"g": 0.0})
    gain = mine.agg(F.sum(F.col("g") / F.log2(F.col("position") + 1)).alias("dcg"))
    ideal = best.agg(F.sum(F.col("b") / F.log2(F.col("position") + 1)).alias("idcg"))
    return ranked.agg(F.corr("p", "position").alias("spearman")).crossJoin(gain).crossJoin(ideal).select(F.lit(k).alias("k"), "spearman", (F.col("dcg") / F.col("idcg")).alias("ndcg"))
