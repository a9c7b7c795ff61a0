"""Edge files: text lists, and round trips through row and column formats; bucketed and partitioned sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.model import owner
from tidegraph.plans.scratch import Scratch

SCHEMA = "src bigint, dst bigint"


def read_edge_list(spark: SparkSession, path: str) -> DataFrame:
    """src, dst from lines of two numbers parted by white space; lines that begin with # or % and blank ones are skipped.

    A line of another form gives null ends, which Graph.validate counts.
    """
    lines = spark.read.text(path).where(~F.trim("value").rlike("^([#%].*)?$"))
    parts = F.split(F.trim("value"), r"\s+")
    return lines.select(F.get(parts, F.lit(0)).try_cast("bigint").alias("src"), F.get(parts, F.lit(1)).try_cast("bigint").alias("dst"))


def write_edge_list(edges: DataFrame, path: str, header: str = "src dst") -> None:
    lines = edges.select(F.concat_ws(" ", "src", "dst").alias("value"))
    lines.unionByName(edges.sparkSession.createDataFrame([(f"# {header}",)], "value string")).write.mode("overwrite").text(path)


def round_trip(edges: DataFrame, kind: str) -> DataFrame:
    """Edges written as csv, json, orc or parquet and read with an explicit schema."""
    scratch = Scratch(edges.sparkSession, f"edges-{kind}")
    edges.write.format(kind).save(scratch.path("edges"))
    return edges.sparkSession.read.schema(SCHEMA).format(kind).load(scratch.path("edges"))


def save_bucketed(edges: DataFrame, table: str, blocks: int, how: str = "cyclic", path: str | None = None) -> DataFrame:
    """Edges with blk, bucketed by it and sorted by src: joins and groups by blk then need no shuffle."""
    writer = edges.withColumn("blk", owner(F.col("src"), how, blocks)).write.mode("overwrite").bucketBy(blocks, "blk").sortBy("blk", "src")
    (writer.option("path", path) if path else writer).saveAsTable(table)
    return edges.sparkSession.table(table)
