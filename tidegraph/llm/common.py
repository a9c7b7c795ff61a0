"""What the operators of this subpackage share on Spark's side."""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A side with no more rows than this of at most some 16 bytes each may be broadcast; its size is counted first.
BROADCAST_ROWS = 1_000_000
#: Bytes of a slice of a batch, about.
SLICE_BYTES = 2 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crc_mod(column: str, by: int) -> Column:
    """Null ids give null, so they belong to no side of a split."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % by


@lru_cache(maxsize=1)
def _trim() -> Callable[[int], int] | None:
    """glibc's malloc_trim; other C libraries have none."""
    return getattr(ctypes.CDLL(None), "malloc_trim", None)


def give_back() -> None:
    """Returns the memory that Arrow's pool and malloc hold without need, which a Python worker would keep until it ends."""
    pa.default_memory_pool().release_unused()
    if trim := _trim():
        trim(0)


def slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    """The rows of a batch in order, in slices of about SLICE_BYTES, if its rows are of like size, but of a row at least."""
    rows = max(1, batch.num_rows * SLICE_BYTES // max(batch.nbytes, SLICE_BYTES))
    for at in range(0, batch.num_rows, rows):
        yield batch.slice(at, rows)


def per_batch(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | None], schema: str | T.StructType, cut: bool = False) -> DataFrame:
    """fn turns each Arrow batch, or with cut each slice of one, into one of the given schema, or None for nothing."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch) if cut else [batch]:
                if part.num_rows and (out := fn(part)) is not None:
                    yield from slices(out)
                part = out = None
            batch = None
            give_back()

    return df.mapInArrow(run, schema)


def small_side(df: DataFrame, rows: int) -> DataFrame:
    """Hints a broadcast if the counted rows keep within the bound; else Spark shuffles."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df


def bounded_rows(df: DataFrame, column: str, rows: int, salt: int = 31) -> DataFrame:
    """About `rows` rows at most, chosen by a hash of the column over all of df; all of them if no more are there."""
    there = df.count()
    if there <= rows:
        return df
    return df.where(F.pmod(F.xxhash64(F.col(column), F.lit(salt)), F.lit(1 << 30)) < int((1 << 30) * rows / there))
