"""Helpers shared by the operators: reading tables, cutting lineage, row keys."""

from __future__ import annotations

import contextlib
import ctypes
import re
import tempfile
import zipfile
from collections.abc import Callable
from pathlib import Path

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint, in the folder that the session names. Only a local master may go without: executors elsewhere couldn't read a folder of our own."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        named = df.sparkSession.conf.get("spark.checkpoint.dir", None)
        if not named and not re.fullmatch(r"local(\[[^,\]]*(,[^\]]*)?\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="walkrank-"))
    return df.checkpoint(eager=True)


def trim() -> None:
    """Gives memory that this worker has freed back to the system, where the C library can."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL("libc.so.6").malloc_trim(0)


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def bucket_of(doc_id: Column, mod: int) -> Column:
    """crc32 of the id as text, modulo `mod`; a null id counts as empty text."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % mod


def draw(*parts: Column | str | int) -> Column:
    """A 60-bit integer from a digest of the parts, which other engines can compute too."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *(p if isinstance(p, Column) else F.lit(str(p)) for p in parts)).cast("binary")), 1, 15), 16, 10).cast("long")


def keyed(text: Column) -> Column:
    """Distinguishes rows that share an id but not a text."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def plus(schema: T.StructType, **fields: str) -> T.StructType:
    """`schema` with more fields, as a new schema (StructType.add changes its own)."""
    return T.StructType([*schema.fields, *(T.StructField(k, T._parse_datatype_string(v)) for k, v in fields.items())])


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Gives the executors this package, once an application, for clusters where it isn't installed."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    top = Path(__file__).resolve().parents[1]
    name = Path(tempfile.mkdtemp(prefix="walkrank-ship-")) / "walkrank_package.zip"
    with zipfile.ZipFile(name, "w") as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, p.relative_to(top.parent))
    sc.addPyFile(str(name))
    _shipped.add(sc.applicationId)


def arrow_map(df: DataFrame, work: Callable, schema: T.StructType | str) -> DataFrame:
    """mapInArrow on executors that are sure to have this package."""
    ship(df.sparkSession)
    return df.mapInArrow(work, schema)
