"""The queries of this subpackage, one for each operator, and the SQL of those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from walkrank.llm import bpe, html_extract, licenses, lm, mixing, quality, simhash, topk, urlfilter, vectors
from walkrank.llm.common import read


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(read(spark, sf_dir, "documents"), target=0.5, limit=4.0, budget=1.0)


def op2_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(read(spark, sf_dir, "documents"))


def op3_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "embeddings")
    return topk.top_k(rows, rows.where("vec_id % 50 = 0"), k=5)


def op4_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_frame(read(spark, sf_dir, "documents"), vocabulary(), digests_only=True)


def op5_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.near_duplicates(read(spark, sf_dir, "embeddings"), cosine=0.95)


def op6_lm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm.score(read(spark, sf_dir, "documents"))


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.classify(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(read(spark, sf_dir, "documents")).select("doc_id", "fingerprint", "component_id")


def op9_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extract.extract(read(spark, sf_dir, "pages"))


def op10_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = read(spark, sf_dir, "pages").select("page_id", "url")
    found = urlfilter.apply_lists(pages.withColumn("fetched_at", F.expr(urlfilter.FETCHED)), urlfilter.rule_list(pages))
    return found.select("page_id", "url", F.unix_seconds("fetched_at").alias("fetched_s"), "host", "blocked", "n_rules", "categories", "rule")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_mixing, op2_licenses, op3_topk, op4_bpe, op5_vectors, op6_lm, op7_quality, op8_simhash, op9_html, op10_urls)}


def oracle_sql() -> dict[str, str]:
    return {"op2_licenses": licenses.oracle_sql(), "op3_topk": topk.ORACLE_SQL, "op5_vectors": vectors.ORACLE_SQL, "op10_urls": urlfilter.oracle_sql()}
