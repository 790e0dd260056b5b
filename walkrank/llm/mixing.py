"""Mixing sources to target weights, with DataFrame functions only.

Weights: a source's share of all tokens to the power of an exponent, normalised. The exponent, in [0, 1], is
bisected: the least for which the weights' entropy is at most a target and no source is repeated more
often than a limit allows (both fall as the exponent rises, so one bisection meets both). A pass
evaluates all midpoints of four bisection steps in one aggregation over the table of sources.

Realisation: a source with budget b and T tokens gets b div T whole passes and a part of b mod T
tokens. Its documents lie in about sqrt(n) blocks by hash; blocks are permuted by hash, and so are the
documents in each. The part takes whole blocks in permuted order, then documents of the block where the
budget ends. Only block totals are summed along an order, and only one block's documents per source; the
documents' texts aren't shuffled: each row compares its own hashes with its source's cut.

A null source is a source of its own. Null texts have no tokens; documents without tokens cost nothing
and come with every pass. Rows that repeat id and text fare alike. Without tokens every document comes once.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from walkrank.llm.common import cut, draw

#: Salts that a source's rows are dealt over when they meet their source's plan: so many at least, and one for so many rows.
SALTS = 64
SALT_ROWS = 1 << 20
STEPS = 40


def n_words(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit("[^\\x20\\x09-\\x0D]+")).cast("long")


def _name(source: Column) -> Column:
    """Sources as text; null is told apart from all texts."""
    return F.when(source.isNull(), "-").otherwise(F.concat(F.lit("+"), source.cast("string")))


def _measures(p: Column, tokens: Column, total: Column, x: float) -> list[Column]:
    """Aggregates that give the entropy and the most repetitions for exponent x."""
    w = F.pow(p, F.lit(x))
    return [F.sum(w), F.sum(w * F.ln(w)), F.max(w * total / tokens)]


def solve_exponent(sources: DataFrame, target: float, limit: float, steps: int = STEPS) -> float:
    """The least exponent in [0, 1], to 2 ** -steps, whose entropy is at most `target` of the way from that in
    proportion (0) to that of equal weights (1), and that repeats no source over `limit` times for a budget of all tokens."""
    some = sources.where("tokens > 0")
    total, n = some.agg(F.sum("tokens"), F.count("*")).first()
    if not total or n < 2:
        return 1.0
    t = F.lit(float(total))
    p = F.col("tokens") / t
    h1 = some.agg(F.sum(-p * F.ln(p))).first()[0]
    wanted = h1 + target * (math.log(n) - h1)
    lo, hi = 0.0, 1.0
    for _ in range(0, steps, 4):
        width = (hi - lo) / 16
        grid = [lo + width * i for i in range(1, 16)]
        got = some.agg(*[m.alias(f"m{i}_{j}") for i, x in enumerate(grid) for j, m in enumerate(_measures(p, F.col("tokens"), t, x))]).first()
        fits = [math.log(got[3 * i]) - got[3 * i + 1] / got[3 * i] <= wanted and got[3 * i + 2] / got[3 * i] <= limit for i in range(15)]
        a, b = 0, 16
        while b - a > 1:
            mid = (a + b) // 2
            a, b = (a, mid) if fits[mid - 1] else (mid, b)
        lo, hi = lo + width * a, lo + width * b
    return hi


def plan(docs: DataFrame, target: float = 0.5, limit: float = 4.0, budget: float | str = 1.0, seed: int = 1) -> tuple[DataFrame, DataFrame]:
    """(counted, sources): docs with their names and hashes; per source its weight, passes and cut.

    budget: a multiple of all tokens, or "cover": the least that gives every source one whole pass.
    """
    name = _name(F.col("source"))
    counted = docs.select(
        F.col("doc_id"), name.alias("__s"), n_words(F.col("text")).alias("__n"),
        draw(seed, "block", F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).alias("__hb"),
        draw(seed, "order", F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).alias("__ho"),
    )
    counted = cut(counted)  # words are counted once
    sources = cut(counted.groupBy("__s").agg(F.sum("__n").alias("tokens"), F.count("*").alias("n_docs")))
    x = solve_exponent(sources, target, limit)
    total = sources.agg(F.sum("tokens").cast("double").alias("all"))
    weighted = sources.crossJoin(F.broadcast(total)).withColumn("w", F.when(F.col("tokens") > 0, F.pow(F.col("tokens") / F.col("all"), F.lit(x))).otherwise(0.0))
    norm = weighted.agg(F.sum("w").alias("sum_w"), F.max(F.when(F.col("tokens") > 0, F.col("tokens") / F.col("w"))).alias("cover"))
    share = F.when(F.col("sum_w") > 0, F.col("w") / F.col("sum_w")).otherwise(0.0)
    want = F.col("cover") * F.col("sum_w") if budget == "cover" else F.lit(float(budget)) * F.col("all")
    sized = (
        weighted.crossJoin(F.broadcast(norm))
        .withColumn("weight", share)
        .withColumn("budget", F.coalesce(F.floor(F.round(share * want, 3)), F.lit(0)).cast("long"))
        .withColumn("passes", F.when(F.col("tokens") > 0, F.expr("budget div tokens")).otherwise(1))
        .withColumn("part", F.when(F.col("tokens") > 0, F.col("budget") % F.col("tokens")).otherwise(0))
        .withColumn("n_blocks", F.greatest(F.lit(1), F.ceil(F.sqrt("n_docs"))).cast("long"))
        .select("__s", "tokens", "n_docs", "weight", "budget", "passes", "part", "n_blocks")
    )
    sized = cut(sized)
    salts = max(SALTS, sized.agg(F.coalesce(F.sum("n_docs"), F.lit(0)).alias("n")).first()["n"] // SALT_ROWS)
    placed = meet(counted, sized.select("__s", "n_blocks"), salts).withColumn("__b", F.col("__hb") % F.col("n_blocks"))
    blocks = placed.groupBy("__s", "__b").agg(F.sum("__n").alias("tokens"))
    blocks = blocks.withColumn("key", draw(seed, "permute", F.col("__s"), F.col("__b").cast("string")))
    along = W.partitionBy("__s").orderBy("key", "__b")
    before = blocks.withColumn("upto", F.sum("tokens").over(along)).withColumn("before", F.col("upto") - F.col("tokens"))
    ends = before.join(sized.select("__s", "part"), "__s").where("before <= part and upto > part").select("__s", F.col("__b").alias("end_block"), F.col("key").alias("end_key"), (F.col("part") - F.col("before")).alias("left_over"))
    ends = cut(ends)
    inside = meet(placed.select("__s", "__b", "__n", "__ho"), ends, salts).where(F.col("__b") == F.col("end_block")).groupBy("__s", "left_over", "__ho").agg(F.sum("__n").alias("n"))
    taken = inside.withColumn("run", F.sum("n").over(W.partitionBy("__s").orderBy("__ho"))).where("run <= left_over").groupBy("__s").agg(F.max("__ho").alias("end_order"))
    return counted, cut(sized.join(ends.drop("left_over"), "__s", "left").join(taken, "__s", "left").withColumn("salts", F.lit(salts)))


def meet(rows: DataFrame, by_source: DataFrame, salts: int) -> DataFrame:
    """rows joined with their source's row; a source's rows are dealt over `salts` partitions."""
    salt = F.pmod(F.xxhash64("__ho"), F.lit(salts))
    copies = by_source.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return rows.withColumn("__salt", salt).join(copies, ["__s", "__salt"]).drop("__salt")


def _salts(sources: DataFrame) -> int:
    row = sources.select("salts").first()
    return row["salts"] if row else SALTS


def _copies(seed: int) -> Column:
    """How often a row that has met its source's plan comes."""
    block = F.col("__hb") % F.col("n_blocks")
    key = draw(seed, "permute", F.col("__s"), block.cast("string"))
    earlier = (key < F.col("end_key")) | ((key == F.col("end_key")) & (block < F.col("end_block")))
    at_end = (block == F.col("end_block")) & (F.col("__ho") <= F.coalesce(F.col("end_order"), F.lit(-1)))
    # tokens of all blocks within the part: no end, no part
    return F.col("passes") + F.when(F.col("part") > 0, F.when(earlier | at_end, 1).otherwise(0)).otherwise(0)


def mix(docs: DataFrame, seed: int = 1, **more) -> DataFrame:
    """(doc_id, source, n_tokens, weight, copies): how often each row of docs comes in the mixture."""
    counted, sources = plan(docs, seed=seed, **more)
    return meet(counted, sources.drop("salts"), _salts(sources)).select(
        "doc_id", F.when(F.col("__s") == "-", None).otherwise(F.substring("__s", 2, 1 << 20)).alias("source"), F.col("__n").alias("n_tokens"),
        F.round("weight", 9).alias("weight"), _copies(seed).cast("long").alias("copies"),
    )


def realise(docs: DataFrame, seed: int = 1, **more) -> DataFrame:
    """The rows of docs, whole, each as often as the mixture wants it."""
    _, sources = plan(docs, seed=seed, **more)
    sid = F.coalesce(F.col("doc_id").cast("string"), F.lit(""))
    rows = docs.withColumns({"__s": _name(F.col("source")), "__hb": draw(seed, "block", sid), "__ho": draw(seed, "order", sid)})
    # The plan has one row per source, of fixed width: it is broadcast only if Spark's own size threshold allows that.
    copied = meet(rows, sources.drop("tokens", "n_docs", "weight", "budget", "salts"), _salts(sources)).withColumn("__copies", _copies(seed))
    again = copied.where("__copies > 0").withColumn("__pass", F.explode(F.sequence(F.lit(1).cast("long"), F.col("__copies").cast("long"))))
    return again.select(*docs.columns)
