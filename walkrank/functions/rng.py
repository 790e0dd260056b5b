"""Keyed draws: a hash of (seed, purpose, step, keys) instead of a stateful generator.

A task that is run again draws the same numbers, whatever the partitioning. `portable` draws are 60 bits of
an MD5 digest, which other engines can repeat; `fast` draws are 60 bits of xxhash64.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

BITS = 60


def threshold(p: float) -> int:
    """The integer below which a draw falls with probability p."""
    return int(p * (1 << BITS))


@dataclass(frozen=True)
class Rng:
    seed: int = 7
    kind: str = "portable"

    def draw(self, purpose: str, step: int, *keys: Column | str) -> Column:
        cols = [F.col(k) if isinstance(k, str) else k for k in keys]
        if self.kind == "fast":
            return F.xxhash64(F.lit(self.seed), F.lit(purpose), F.lit(step), *cols).bitwiseAND(F.lit((1 << BITS) - 1))
        text = F.concat_ws("|", F.lit(f"{self.seed}|{purpose}|{step}"), *(c.cast("string") for c in cols))
        return F.conv(F.substring(F.md5(text.cast("binary")), 1, 15), 16, 10).cast("long")

    def happens(self, p: float, purpose: str, step: int, *keys: Column | str) -> Column:
        if p >= 1:
            return F.lit(True)
        return self.draw(purpose, step, *keys) < F.lit(threshold(p))

    def sql(self, purpose: str, step: int, *keys: str) -> str:
        """The portable draw as DuckDB SQL; keys are SQL expressions."""
        return f"('0x' || substr(md5('{self.seed}|{purpose}|{step}|' || " + " || '|' || ".join(f"({k})::VARCHAR" for k in keys) + "), 1, 15))::BIGINT"


@dataclass(frozen=True)
class PartRng(Rng):
    """For graphs of many parts, whose vertices are 'part|vertex': draws as if each part were alone. Portable draws only."""

    def draw(self, purpose: str, step: int, *keys: Column | str) -> Column:
        return super().draw(purpose, step, *(F.substring_index((F.col(k) if isinstance(k, str) else k).cast("string"), "|", -1) for k in keys))


def register(spark: SparkSession) -> None:
    """SQL functions of this session, plain expressions to the optimizer: walk_draw(text) is the portable draw of
    'seed|purpose|step|key..', walk_happens(text, p) is true with probability p."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION walk_draw(t STRING) RETURNS BIGINT RETURN cast(conv(substr(md5(cast(t AS BINARY)), 1, 15), 16, 10) AS BIGINT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION walk_happens(t STRING, p DOUBLE) RETURNS BOOLEAN RETURN cast(conv(substr(md5(cast(t AS BINARY)), 1, 15), 16, 10) AS BIGINT) < cast(p * {1 << BITS}D AS BIGINT)")
