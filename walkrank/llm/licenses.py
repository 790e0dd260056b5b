"""License scans by diagonal voting, with DataFrame functions only.

A text's words are joined, as rolling hashes of two words, with the positions of the same word pairs in a fixed set of
templates (a broadcast table of a few hundred rows; its size is checked). A hit at text word p and template
word j votes for the diagonal p - j. Votes are gathered per document, template and diagonal as a bit
mask of template positions, diagonals a few words apart are merged (words put in or left out), and a
span counts if enough of its template is covered. Hash matches are verified on the words themselves.

Whole texts are read; only hits are shuffled. A null text is empty. Rows that share an id but not a text are told
apart by the text's hash; rows that repeat both get the same answer each. Words are lower-cased for A-Z only.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from walkrank.llm.common import keyed

#: Fixed phrases with their labels.
BASE = (("mit", "mit license"), ("apache", "apache license"), ("gpl", "general public license"))
#: Longer clauses of well-known licenses; a part of their words is enough.
CLAUSES = (
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("mit", "released under the mit license"),
    ("apache", "licensed under the apache license version 2 0"),
    ("apache", "you may not use this file except in compliance with the license"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("gpl", "licensed under the gnu general public license version 3"),
    ("lgpl", "gnu lesser general public license"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("cc", "this content is licensed under a creative commons attribution international license"),
    ("isc", "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted"),
)
#: Most word pairs of a template: a vote is a bit of a long.
MOST = 62
DELIMITERS = "[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+"


@dataclass(frozen=True)
class Template:
    label: str
    words: tuple[str, ...]
    base: bool

    @property
    def pairs(self) -> int:
        return len(self.words) - 1


def templates(base=BASE, clauses=CLAUSES) -> list[Template]:
    out = [Template(label, tuple(text.split()), kind) for kind, group in ((True, base), (False, clauses)) for label, text in group]
    for t in out:
        if not 1 <= t.pairs <= MOST:
            raise ValueError(f"a template has 2 to {MOST + 1} words; cut longer texts into clauses")
    if sum(t.pairs for t in out) > 1 << 16:
        raise ValueError("the templates are too many to broadcast")
    return out


def words_of(text: Column) -> Column:
    """The words of whole texts; A-Z are lower-cased, and no other letters become a-z."""
    safe = F.replace(F.replace(F.coalesce(text, F.lit("")), F.lit("K"), F.lit("")), F.lit("İ"), F.lit(""))
    return F.array_remove(F.split(F.lower(safe), DELIMITERS), "")


def _table(spark: SparkSession, found: list[Template]) -> DataFrame:
    rows = [(i, t.base, t.label, t.pairs, j, t.words[j], t.words[j + 1]) for i, t in enumerate(found) for j in range(t.pairs)]
    values = ", ".join(f"({i}, {str(b).lower()}, '{label}', {m}, {j}, '{a}', '{c}')" for i, b, label, m, j, a, c in rows)
    table = spark.sql(f"SELECT * FROM VALUES {values} AS t(t, base, label, m, j, w1, w2)")
    return table.withColumn("h", F.xxhash64("w1", "w2"))


def hits(docs: DataFrame, found: list[Template]) -> DataFrame:
    """(doc_id, th, t, base, label, m, diagonal, mask, first, last): votes per document, template and diagonal."""
    words = docs.select(F.col("doc_id"), keyed(F.col("text")).alias("th"), words_of(F.col("text")).alias("w"))
    pairs = words.where(F.size("w") > 1).select("doc_id", "th", F.posexplode(F.arrays_zip(F.expr("slice(w, 1, size(w) - 1)").alias("a"), F.expr("slice(w, 2, size(w) - 1)").alias("b"))).alias("p", "pair"))
    rolled = pairs.select("doc_id", "th", "p", F.col("pair.a").alias("a"), F.col("pair.b").alias("b")).withColumn("h", F.xxhash64("a", "b"))
    met = rolled.join(F.broadcast(_table(docs.sparkSession, found)), "h").where("a = w1 and b = w2")
    return met.groupBy("doc_id", "th", "t", "base", "label", "m", (F.col("p") - F.col("j")).alias("diagonal")).agg(
        F.bit_or(F.expr("shiftleft(1L, j)")).alias("mask"), F.min("p").alias("first"), F.max("p").alias("last")
    )


def spans(votes: DataFrame, gap: int = 3, share: float = 0.8) -> DataFrame:
    """(doc_id, th, base, label, exact, first, coverage): the places that the votes prove.

    Base phrases: each diagonal with all pairs is a place. Clauses: diagonals at most `gap` apart are merged, and
    a merged span of not much more than the clause's length with at least `share` of its pairs is a place.
    """
    base = votes.where("base and bit_count(mask) = m").select("doc_id", "th", "base", "label", F.col("diagonal").alias("first"), F.lit(1.0).alias("coverage"))
    along = W.partitionBy("doc_id", "th", "t").orderBy("diagonal")
    other = votes.where("not base").withColumn("new", F.when(F.col("diagonal") - F.lag("diagonal").over(along) <= gap, 0).otherwise(1))
    # diagonals that lie near each other but whose words lie far apart belong to different places
    apart = F.when(F.col("first") - F.lag("last").over(along) > F.col("m"), 1).otherwise(F.col("new"))
    runs = other.withColumn("run", F.sum(apart).over(along))
    merged = runs.groupBy("doc_id", "th", "t", "label", "m", "run").agg(F.bit_or("mask").alias("mask"), F.min("first").alias("first"), F.max("last").alias("last"))
    fits = merged.withColumn("coverage", F.expr("bit_count(mask) / cast(m as double)")).where((F.col("coverage") >= share) & (F.col("last") - F.col("first") + 1 <= F.col("m") + 2 * gap))
    return base.unionByName(fits.select("doc_id", "th", F.lit(False).alias("base"), "label", "first", "coverage"))


def scan(docs: DataFrame, gap: int = 3, share: float = 0.8) -> DataFrame:
    """One row for each row of docs: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score."""
    per = spans(hits(docs, templates()), gap, share).groupBy("doc_id", "th").agg(
        F.count_if("base").alias("n"),
        F.min(F.when(F.col("base"), F.col("first"))).cast("long").alias("first_word"),
        F.max(F.when(F.col("base"), F.col("first"))).cast("long").alias("last_word"),
        F.array_join(F.array_sort(F.collect_set(F.when(F.col("base"), F.col("label")))), ",").alias("bl"),
        F.array_join(F.array_sort(F.collect_set("label")), ",").alias("al"),
        F.max("coverage").alias("cov"),
    )
    rows = docs.select("doc_id", keyed(F.col("text")).alias("th"), F.size(words_of(F.col("text"))).cast("long").alias("n_words"))
    p = per.select(F.col("doc_id").alias("d2"), F.col("th").alias("t2"), "n", "first_word", "last_word", "bl", "al", "cov")
    return rows.join(p, rows.doc_id.eqNullSafe(p.d2) & (rows.th == p.t2), "left").select(
        "doc_id", "n_words", F.coalesce("n", F.lit(0)).cast("long").alias("n_base"), "first_word", "last_word",
        F.coalesce("bl", F.lit("")).alias("base_labels"), F.coalesce("al", F.lit("")).alias("labels"), F.round(F.coalesce("cov", F.lit(0.0)), 6).alias("score"),
    )


def oracle_sql(gap: int = 3, share: float = 0.8) -> str:
    """The same scan as DuckDB SQL over the table documents."""
    rows = ", ".join(f"({i}, {str(t.base).lower()}, '{t.label}', {t.pairs}, {j}, '{t.words[j]}', '{t.words[j + 1]}')" for i, t in enumerate(templates()) for j in range(t.pairs))
    return rf"""
WITH tpl(t, base, label, m, j, w1, w2) AS (VALUES {rows}),
doc AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
pos AS (SELECT doc_id, w, unnest(range(1, len(w))) AS p FROM doc WHERE len(w) > 1),
pair AS (SELECT doc_id, p - 1 AS p, w[p] AS a, w[p + 1] AS b FROM pos),
vote AS (SELECT doc_id, t, base, label, m, p - j AS diagonal, bit_or(1::BIGINT << j) AS mask, min(p) AS lo, max(p) AS hi
         FROM pair JOIN tpl ON a = w1 AND b = w2 GROUP BY ALL),
near AS (SELECT *, CASE WHEN lo - lag(hi) OVER o > m THEN 1 WHEN diagonal - lag(diagonal) OVER o <= {gap} THEN 0 ELSE 1 END AS fresh
         FROM vote WHERE NOT base WINDOW o AS (PARTITION BY doc_id, t ORDER BY diagonal)),
run AS (SELECT *, sum(fresh) OVER (PARTITION BY doc_id, t ORDER BY diagonal) AS r FROM near),
merged AS (SELECT doc_id, t, label, m, r, bit_or(mask) AS mask, min(lo) AS lo, max(hi) AS hi FROM run GROUP BY ALL),
span AS (SELECT doc_id, base, label, diagonal AS lo, 1.0::DOUBLE AS cov FROM vote WHERE base AND bit_count(mask) = m
         UNION ALL SELECT doc_id, false, label, lo, bit_count(mask) / m::DOUBLE FROM merged WHERE bit_count(mask) / m::DOUBLE >= {share} AND hi - lo + 1 <= m + {2 * gap}),
per AS (SELECT doc_id, count(*) FILTER (base) AS n, min(lo) FILTER (base) AS f, max(lo) FILTER (base) AS l,
        string_agg(DISTINCT label, ',' ORDER BY label) FILTER (base) AS bl, string_agg(DISTINCT label, ',' ORDER BY label) AS al, max(cov) AS cov FROM span GROUP BY doc_id)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(n, 0)::BIGINT AS n_base, f::BIGINT AS first_word, l::BIGINT AS last_word,
       coalesce(bl, '') AS base_labels, coalesce(al, '') AS labels, round(coalesce(cov, 0), 6)::DOUBLE AS score
FROM doc d LEFT JOIN per USING (doc_id)"""
