"""A data source of uniform pairs: ``spark.read.format("uniform_pairs").option("n", ..).option("m", ..).load()``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .shipping import ship

ROUNDS = 6
BATCH = 1 << 16


def _mix(x: np.ndarray, key: int) -> np.ndarray:
    x = (x + np.uint64(key)) * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    return x ^ (x >> np.uint64(32))


def shuffled_ranks(t: np.ndarray, total: int, seed: int) -> np.ndarray:
    """Images of the numbers ``t`` under a keyed permutation of 0 .. total - 1: a balanced network over the next even number of
    bits, applied again to images outside the range. Distinct numbers stay distinct, so no task has to know what others drew."""
    half = np.uint64(max(1, ((total - 1).bit_length() + 1) // 2))
    low = np.uint64((1 << int(half)) - 1)
    keys = [(seed * 0x100000001B3 + r * 0x632BE59BD9B4E019) % 2**64 for r in range(ROUNDS)]
    out = t.astype(np.uint64)
    todo = np.arange(len(out))
    while len(todo):
        left, right = out[todo] >> half, out[todo] & low
        for k in keys:
            left, right = right, left ^ (_mix(right, k) & low)
        out[todo] = left << half | right
        todo = todo[out[todo] >= np.uint64(total)]
    return out.astype(np.int64)


def decoded(rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The pairs (i, j), i < j, of ranks below 2^60: triangular roots with exact corrections."""
    j = ((1 + np.sqrt(1 + 8 * rank.astype(np.float64))) / 2).astype(np.int64)
    for _ in range(2):
        j = np.where(j * (j - 1) // 2 > rank, j - 1, j)
        j = np.where(j * (j + 1) // 2 <= rank, j + 1, j)
    return rank - j * (j - 1) // 2, j


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.n, self.m, self.seed = int(options["n"]), int(options["m"]), int(options.get("seed", 42))
        self.total = self.n * (self.n - 1) // 2
        self.m = max(0, min(self.m, self.total))
        self.rows = int(options.get("rowsPerTask", 1_000_000))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition((a, min(a + self.rows, self.m))) for a in range(0, max(1, self.m), self.rows)]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        start, stop = partition.value
        for a in range(start, stop, BATCH):
            i, j = decoded(shuffled_ranks(np.arange(a, min(a + BATCH, stop)), self.total, self.seed))
            yield pa.RecordBatch.from_arrays([pa.array(i), pa.array(j)], ["i", "j"])


class UniformPairs(DataSource):
    """``m`` of the pairs (i, j), 0 <= i < j < ``n``, without repeats and without a shuffle; all of them if ``m`` is larger.

    Draw number t is the t-th pair of a keyed random order of the pair space, so tasks make their stretches on their own, and
    a lost task makes the same again. Options: n, m, seed (42), rowsPerTask (1,000,000)."""

    @classmethod
    def name(cls) -> str:
        return "uniform_pairs"

    def schema(self) -> str:
        return "i long, j long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def read_pairs(spark: SparkSession, n: int, m: int, seed: int = 42) -> DataFrame:
    """(i, j) of ``m`` uniform pairs of ``n`` places."""
    ship(spark)
    spark.dataSource.register(UniformPairs)
    return spark.read.format("uniform_pairs").option("n", n).option("m", m).option("seed", seed).load()


def pairs_of(df: DataFrame, id_col: str, m: int, seed: int = 42) -> DataFrame:
    """(id_a, id_b): ``m`` uniform pairs of the records of a table."""
    from headcount.operators.sampling import dense_index

    places = dense_index(df, id_col)
    drawn = read_pairs(df.sparkSession, df.count(), m, seed)
    a = drawn.join(places.select(F.col("idx").alias("i"), F.col(id_col).alias("x")), "i")
    b = a.join(places.select(F.col("idx").alias("j"), F.col(id_col).alias("y")), "j")
    return b.select(F.least("x", "y").alias("id_a"), F.greatest("x", "y").alias("id_b"))
