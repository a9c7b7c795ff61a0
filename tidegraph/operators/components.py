"""Connected components by alternating star contractions.

Each round rewrites the edge set so that every vertex points at the smallest id it can see: first
larger neighbours are hung on the smallest neighbour (large star), then smaller ones (small star).
Rounds grow with the logarithm of a component's size; no neighbourhood is ever gathered in one
task, since minima are partial aggregates and the rest are joins that may be split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tidegraph.plans.scratch import Scratch


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One contraction of pairs (u, v) with u > v, returned in the same form."""
    pairs = edges.select("u", "v")
    if large:
        pairs = pairs.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = pairs.groupBy("u").agg(F.min("v").alias("m"))
    joined = pairs.join(low, "u")
    if large:
        # v > u hangs on min(u, its smallest neighbour)
        out = joined.where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v"))
    else:
        out = joined.select("u", "m").union(joined.where("v <> m").select("v", "m")).toDF("u", "v")
    return out.where("u <> v").distinct()


def connected_components(edges: DataFrame, scratch: Scratch, name: str = "cc", max_rounds: int = 60) -> DataFrame:
    """(id, component) for each vertex that has an edge; component is the smallest id in it.

    edges has columns a, b of bigint; loops, repeats, either direction and nulls are allowed.
    Raises if max_rounds don't suffice, which takes more vertices than any table has.
    """
    now = scratch.save(
        edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), f"{name}-0"
    )
    seen = None
    for i in range(1, max_rounds + 1):
        now = scratch.save(_star(_star(now, large=True), large=False), f"{name}-{i}")
        # equal counts and sums of row hashes: nothing moved
        mark = now.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        scratch.drop(f"{name}-{i - 1}")
        if seen == tuple(mark):
            # at the fixed point each u has one row, (u, smallest id)
            tops = now.select(F.col("v").alias("id")).distinct().withColumn("component", F.col("id"))
            return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(tops)
        seen = tuple(mark)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
