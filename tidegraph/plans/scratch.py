"""Tables written between the steps of an iterative operator.

They go to the folder that the session names in spark.checkpoint.dir, which the driver and all
executors share, so a lost executor costs no finished step and lineage stays short.
"""

from __future__ import annotations

import os
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Estimated bytes of a bucket below which fewer buckets are made.
BUCKET_BYTES = 4 << 20


def shared_folder(spark: SparkSession) -> str:
    """The cluster's folder; a local one only where the session names none and all tasks run in this process, as in tests."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named and not spark.sparkContext.master.startswith("local["):
        raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return named or os.path.join(tempfile.gettempdir(), "tidegraph-scratch")


@contextmanager
def settings(spark: SparkSession, values: dict[str, str]):
    """Plans made and run inside have these settings; afterwards those of before hold again."""
    before = {name: spark.conf.get(name) for name in values}
    try:
        for name, value in values.items():
            spark.conf.set(name, value)
        yield
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)


def joined_in_place(spark: SparkSession):
    """Plans made inside may join on several keys in place if both sides are dealt by one of them."""
    return settings(spark, {"spark.sql.requireAllClusterKeysForCoPartition": "false"})


class Scratch:
    """Writes DataFrames as Parquet under one new folder and reads them back.

    Use as a context manager only where no lazy result still reads the tables.
    """

    def __init__(self, spark: SparkSession, label: str = "op"):
        self.spark = spark
        self.root = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex[:12]}"
        self.tables: set[str] = set()

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def save_bucketed(self, df: DataFrame, name: str, key: str | tuple[str, ...], like: DataFrame | None = None, n: int | None = None, sort: tuple[str, ...] = (), folders: tuple[str, ...] = (), placed: bool = False, append: bool = False) -> DataFrame:
        """Saves df as a table bucketed and sorted by key, one column or several (then by sort), one file a bucket.

        Joins and groups by the key then move the other side only. Without n there are as many buckets as shuffles
        have partitions, or fewer for little data, by the estimated bytes of df, or of like. folders: columns with a folder
        for each value. placed: rows of a bucket are in one task already. append: to the table of that name. Release it with drop_table.
        """
        n = n or self.buckets(like or df)
        keys = (key,) if isinstance(key, str) else key
        out = (df if placed else df.repartition(n, *keys)).write.bucketBy(n, *keys).sortBy(*keys, *sort).option("path", self.path(name)).format("parquet")
        out = out.mode("append") if append else out
        (out.partitionBy(*folders) if folders else out).saveAsTable(self._label(name))
        self.tables.add(name)
        if append:
            self.spark.catalog.refreshTable(self._label(name))
        return self.spark.table(self._label(name))

    def buckets(self, df: DataFrame) -> int:
        """As many as shuffles have partitions, so that shuffled rows meet them in place, or fewer for little data."""
        size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        return max(1, min(int(self.spark.conf.get("spark.sql.shuffle.partitions")), -(-size // BUCKET_BYTES)))

    def _label(self, name: str) -> str:
        return f"tide_{self.root.rpartition('-')[2]}_{name.replace('-', '_')}"

    def release(self, name: str, schema) -> DataFrame:
        """Forgets the table's entry and reads its files, which stay."""
        self.spark.sql(f"drop table if exists {self._label(name)}")
        self.tables.discard(name)
        return self.spark.read.schema(schema).parquet(self.path(name))

    def drop_table(self, name: str) -> None:
        self.spark.sql(f"drop table if exists {self._label(name)}")
        self.tables.discard(name)
        self.drop(name)

    def keep_only(self, *names: str) -> None:
        """Drops everything but the named tables, which a lazy result still reads."""
        for name in sorted(self.tables - set(names)):
            self.drop_table(name)
        jvm = self.spark.sparkContext._jvm
        root = jvm.org.apache.hadoop.fs.Path(self.root)
        files = root.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if files.exists(root):
            for entry in files.listStatus(root):
                if (path := entry.getPath()).getName() not in names:
                    files.delete(path, True)

    def drop(self, name: str = "") -> None:
        """Deletes one table, or all with no name."""
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path(name) if name else self.root)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)

    def __enter__(self) -> Scratch:
        return self

    def __exit__(self, *exc) -> None:
        self.drop()
