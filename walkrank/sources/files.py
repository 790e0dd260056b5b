"""Edge lists from files and a generator; sinks for adjacency, top lists and runs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def edge_list(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """Text of two columns; lines that begin with # are skipped."""
    return spark.read.csv(path, sep=sep, comment="#", schema="src string, dst string")


def edge_json(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.json(path, schema="src string, dst string")


def edge_orc(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("src string, dst string").orc(path)


class _Part(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class PowerlawGraph(DataSource):
    """A seeded random graph whose in-degrees have a power-law tail.

    Options: n (vertices), degree (out-edges each), theta (tail exponent), seed, partitions. Every vertex draws its
    edges from its own number, so partitions and retries don't change them.
    """

    @classmethod
    def name(cls) -> str:
        return "powerlaw_graph"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return _PowerlawReader(self.options)


class _PowerlawReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.degree = int(options.get("n", 1000)), int(options.get("degree", 8))
        self.theta, self.seed, self.parts = float(options.get("theta", 2.2)), int(options.get("seed", 7)), int(options.get("partitions", 4))

    def partitions(self):
        step = -(-self.n // self.parts)
        return [_Part(a, min(self.n, a + step)) for a in range(0, self.n, step)]

    def read(self, partition):
        import random

        for v in range(partition.first, partition.last):
            rng = random.Random(self.seed * 1_000_003 + v)
            got = set()
            while len(got) < min(self.degree, self.n - 1):
                # the rank of the target by inverse of a Pareto law, its number by a fixed permutation
                u = int(min(self.n - 1, (1 - rng.random()) ** (-(self.theta - 1) / 1.0) - 1))
                u = (u * 7919 + 13) % self.n if self.n % 7919 else u
                if u != v:
                    got.add(u)
                elif self.n <= 2:
                    got.add((v + 1) % self.n)
                if rng.random() < 0.2:
                    w = rng.randrange(self.n)
                    if w != v:
                        got.add(w)
            for u in sorted(got)[: self.degree]:
                yield v, u


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PowerlawGraph)


def write_adjacency(replicas: DataFrame, table: str, buckets: int = 64) -> None:
    """Bucketed and sorted by source, so that walks join it without shuffling it again."""
    replicas.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)


def write_top(top: DataFrame, path: str) -> None:
    top.coalesce(1).write.mode("overwrite").csv(path, header=True)  # k rows


def write_runs(runs: DataFrame, path: str) -> None:
    runs.write.mode("append").partitionBy("method").parquet(path)


def noop(df: DataFrame) -> None:
    """Runs a plan to the end without keeping its rows."""
    df.write.format("noop").mode("overwrite").save()


def distinct_edges(edges: DataFrame) -> DataFrame:
    return edges.where(F.col("src") != F.col("dst")).distinct()
