"""A corpus pipeline of four stages: quality, near-duplicates, mixing, encoding.

Each stage takes the documents that its predecessor kept; all but the last return the columns of documents. In all stages null texts count as
empty, a null id or source is a value of its own, and empty tables give empty ones.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from walkrank.llm import bpe, mixing, quality, simhash
from walkrank.llm.common import cut, read
from walkrank.llm.queries import vocabulary

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier doesn't reject. Repeated rows fare alike; without labels all stay."""
    return quality.keep_good(docs, read(spark, sf_dir, "labels")).select(COLUMNS)


def unlike(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each SimHash group: the least doc_id, then the least hash of its text. Unlike rows that share an id all stay."""
    return simhash.keep_first(docs).select(COLUMNS)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as often as its source's weight wants it, once at least; documents without tokens come with every pass."""
    # the least budget that drops no document: every source comes whole once, the smaller ones more often
    return mixing.realise(docs, budget="cover", target=0.5, limit=4.0).select(COLUMNS)


def encoded(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, source, n_tokens, ids_sha256, decoded_sha256, ids) for each row: what a trainer reads. A document that comes several times has as many rows."""
    return bpe.encode_frame(docs.select("doc_id", "source", "text"), vocabulary()).drop("text")


STAGES = [("quality classifier", good), ("SimHash near-dedup", unlike), ("mixing sources", mixed), ("BPE encoding", encoded)]

#: The first, second and last stage aren't SQL; tests hold each stage against plain Python on small tables.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = cut(docs)
    return docs
