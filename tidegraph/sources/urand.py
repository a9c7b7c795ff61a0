"""Uniform random graphs: 2^k vertices, endpoints drawn by a hash, the same in any engine.

Draw i has the ends md5("seed:a:i") and md5("seed:b:i"), their first 60 bits modulo 2^k; loops go.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def urand(spark: SparkSession, k: int, avg_degree: int = 16, seed: int = 42, directed: bool = False) -> DataFrame:
    """src, dst; undirected graphs hold each edge in both directions, once."""
    n = 1 << k

    def end(which: str):
        text = F.concat(F.lit(f"{seed}:{which}:"), F.col("id").cast("string"))
        return F.pmod(F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint"), F.lit(n)).alias("src" if which == "a" else "dst")

    drawn = spark.range(n * avg_degree // 2).select(end("a"), end("b")).where("src <> dst")
    if not directed:
        drawn = drawn.unionByName(drawn.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
    return drawn.distinct()


#: Draws in a batch.
_BATCH = 1 << 16


def draw(numbers: Iterable[int], n: int, seed: str = "42") -> pa.RecordBatch:
    """src, dst of the draws of these numbers."""
    numbers = list(numbers)
    ends = [np.frombuffer(b"".join(hashlib.md5(b"%b%d" % (start, i)).digest()[:8] for i in numbers), ">u8") for start in (f"{seed}:{c}:".encode() for c in "ab")]
    # the first 60 bits
    return pa.RecordBatch.from_arrays([pa.array(((e >> np.uint64(4)) % np.uint64(n)).astype(np.int64)) for e in ends], names=["src", "dst"])


def urand_of(numbers: DataFrame, column: str, n: int, seed: str = "42") -> DataFrame:
    """src, dst: the draw whose number stands in each row of a table, as UrandSource makes it."""

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield draw(batch.column(0).to_pylist(), n, seed)

    return numbers.select(F.col(column).cast("bigint")).where(F.col(column).isNotNull()).mapInArrow(one, "src bigint, dst bigint")


class UrandSource(DataSource):
    """format("urand") with options k, degree, seed, partitions: the draws, in one direction, loops and repeats included."""

    @classmethod
    def name(cls) -> str:
        return "urand"

    def schema(self) -> str:
        return "src bigint, dst bigint"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.n = 1 << int(options.get("k", 10))
        self.draws = self.n * int(options.get("degree", 16)) // 2
        self.seed, self.parts = options.get("seed", "42"), int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        cuts = [self.draws * i // self.parts for i in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def read(self, partition: _Range) -> Iterator[pa.RecordBatch]:
        for lo in range(partition.first, partition.last, _BATCH):
            yield draw(range(lo, min(lo + _BATCH, partition.last)), self.n, self.seed)
