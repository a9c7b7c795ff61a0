"""Graphs as edge DataFrames, ids, owners and blocks."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from tidegraph.plans.scratch import Scratch

#: Kinds of vertices and what is added to their keys, so that kinds don't meet. Fixed values.
OFFSETS = {
    "part": 0,
    "supplier": 1_000_000_000_000,
    "customer": 2_000_000_000_000,
    "order": 3_000_000_000_000,
    "nation": 4_000_000_000_000,
    "region": 5_000_000_000_000,
    "user": 6_000_000_000_000,
    "page": 7_000_000_000_000,
    "path": 8_000_000_000_000,
    "host": 9_000_000_000_000,
}

EDGES = T.StructType([T.StructField("src", T.LongType(), False), T.StructField("dst", T.LongType(), False)])


@dataclass
class Graph:
    """edges: src, dst of integral type (further columns stay); vertices: id, or None for those that have edges."""

    edges: DataFrame
    given: DataFrame | None = None

    def __post_init__(self) -> None:
        kinds = dict(self.edges.dtypes)
        for c in ("src", "dst"):
            if kinds.get(c) not in ("bigint", "int", "smallint", "tinyint"):
                raise TypeError(f"edges need an integral column {c}, not {kinds.get(c)}")
        if self.given is not None and "id" not in self.given.columns:
            raise TypeError("vertices need a column id")

    @cached_property
    def vertices(self) -> DataFrame:
        if self.given is not None:
            return self.given.select(F.col("id").cast("bigint").alias("id")).distinct()
        ends = self.edges.select(F.col("src").alias("id")).unionAll(self.edges.select(F.col("dst").alias("id")))
        return ends.select(F.col("id").cast("bigint").alias("id")).where("id is not null").distinct()

    def simple(self, drop_loops: bool = False) -> Graph:
        """Distinct edges without null ends."""
        kept = self.edges.select("src", "dst").where("src is not null and dst is not null").distinct()
        return Graph(kept.where("src <> dst") if drop_loops else kept, self.given)

    def reverse(self) -> Graph:
        return Graph(self.edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")), self.given)

    def undirected(self) -> Graph:
        """Each edge in both directions, once."""
        return Graph(self.edges.select("src", "dst").unionByName(self.reverse().edges).distinct(), self.given)

    def degrees(self, kind: str = "out") -> DataFrame:
        """id, degree of every vertex, 0 included; kind: out, in or all."""
        ends = {"out": ["src"], "in": ["dst"], "all": ["src", "dst"]}[kind]
        counted = None
        for c in ends:
            one = self.edges.groupBy(F.col(c).alias("id")).agg(F.count(F.lit(1)).alias("degree"))
            counted = one if counted is None else counted.unionByName(one).groupBy("id").agg(F.sum("degree").alias("degree"))
        return self.vertices.join(counted, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))

    def adjacency(self, chunk: int | None = None) -> DataFrame:
        """id, nbrs ascending, for vertices with out-edges; with chunk, a hub's list is cut into parts of about that many."""
        if chunk is None:
            return self.edges.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))
        degree = self.edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
        part = F.pmod(F.xxhash64("dst"), F.ceil(F.col("d") / chunk)).alias("part")
        return self.edges.join(degree, "src").groupBy(F.col("src").alias("id"), part).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))

    @staticmethod
    def from_adjacency(adjacency: DataFrame) -> Graph:
        return Graph(adjacency.select(F.col("id").alias("src"), F.explode("nbrs").alias("dst")))

    def validate(self) -> DataFrame:
        """One row of counts: edges, null ends, loops, surplus repeats, ends absent from the vertices."""
        e = self.edges
        flat = e.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))
        counts = flat.agg(
            F.sum("n").alias("edges"),
            F.coalesce(F.sum(F.when(F.col("src").isNull() | F.col("dst").isNull(), F.col("n"))), F.lit(0)).alias("null_ends"),
            F.coalesce(F.sum(F.when(F.col("src") == F.col("dst"), F.col("n"))), F.lit(0)).alias("loops"),
            F.sum(F.when(F.col("src").isNotNull() & F.col("dst").isNotNull(), F.col("n") - 1).otherwise(0)).alias("surplus"),
        )
        ends = e.select(F.col("src").alias("id")).unionAll(e.select(F.col("dst").alias("id"))).where("id is not null")
        unknown = ends.distinct().join(self.vertices, "id", "left_anti").agg(F.count(F.lit(1)).alias("unknown_ends"))
        return counts.join(unknown)  # one row with one row


def dense_ids(df: DataFrame, key: str, partitions: int | None = None) -> DataFrame:
    """key, id with ids 0..n-1 in ascending order of the distinct non-null keys.

    Two passes: keys are dealt by range, ranges counted, and each range numbered from its offset; no
    window spans more than a range.
    """
    spark = df.sparkSession
    scratch = Scratch(spark, "dense-ids")
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = df.select(key).where(F.col(key).isNotNull()).distinct().repartitionByRange(n, key).withColumn("part", F.spark_partition_id())
    ranged = scratch.save(ranged, "ranges")
    sizes = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
    offset = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("offset"))
    rank = F.row_number().over(Window.partitionBy("part").orderBy(key))
    return ranged.withColumn("r", rank).join(F.broadcast(offset), "part").select(key, (F.col("offset") + F.col("r") - 1).cast("bigint").alias("id"))


def owner(id_: Column, how: str, blocks: int, n: int | None = None) -> Column:
    """Block of a vertex. block: contiguous ranges of dense ids 0..n-1; cyclic; hash."""
    if how == "block":
        if not n:
            raise ValueError("contiguous blocks need the number of vertices")
        return F.least(F.floor(id_ * F.lit(blocks) / F.lit(n)), F.lit(blocks - 1)).cast("int")
    if how == "cyclic":
        return F.pmod(id_, F.lit(blocks)).cast("int")
    if how == "hash":
        return F.pmod(F.xxhash64(id_), F.lit(blocks)).cast("int")
    raise ValueError(f"no owner function {how!r}")


def split_edges(g: Graph, how: str, blocks: int, n: int | None = None) -> tuple[DataFrame, DataFrame]:
    """Edges inside a block and edges between blocks, with sblk and dblk."""
    e = g.edges.withColumn("sblk", owner(F.col("src"), how, blocks, n)).withColumn("dblk", owner(F.col("dst"), how, blocks, n))
    return e.where("sblk = dblk"), e.where("sblk <> dblk")
