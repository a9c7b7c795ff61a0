"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable
from statistics import median

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tidegraph.model import Graph, split_edges


def timed(fn: Callable, repeats: int = 3) -> dict:
    """median, least and most seconds of the calls, and the last result."""
    took, out = [], None
    for _ in range(repeats):
        began = time.perf_counter()
        out = fn()
        took.append(time.perf_counter() - began)
    return {"seconds": median(took), "least": min(took), "most": max(took), "result": out}


def speedup(runs: DataFrame) -> DataFrame:
    """runs: graph, method, workers, seconds, sequential (boolean). Adds speedup (the graph's best sequential
    time over this one) and efficiency (speedup over workers)."""
    best = F.min(F.when(F.col("sequential"), F.col("seconds"))).over(Window.partitionBy("graph"))
    return runs.withColumn("speedup", best / F.col("seconds")).withColumn("efficiency", F.col("speedup") / F.col("workers"))


def load_balance(load: DataFrame) -> DataFrame:
    """load: round, blk, expanded. Per round: blocks, total, max over mean, p99 over p50, deviation."""
    p = lambda q: F.percentile_approx("expanded", q)
    return load.groupBy("round").agg(
        F.count(F.lit(1)).alias("blocks"), F.sum("expanded").alias("total"), F.coalesce(F.try_divide(F.max("expanded"), F.avg("expanded")), F.lit(1.0)).alias("max_over_mean"),
        (p(0.99) / F.greatest(p(0.5), F.lit(1))).alias("p99_over_p50"), F.coalesce(F.stddev_pop("expanded"), F.lit(0.0)).alias("deviation"),
    )


def edge_cut(g: Graph, how: str, blocks: int, n: int | None = None) -> DataFrame:
    """edges, cut, share."""
    inside, between = split_edges(g, how, blocks, n)
    counted = inside.agg(F.count(F.lit(1)).alias("i")).join(between.agg(F.count(F.lit(1)).alias("cut")))
    return counted.select((F.col("i") + F.col("cut")).alias("edges"), "cut", (F.col("cut") / F.greatest(F.col("i") + F.col("cut"), F.lit(1))).alias("share"))


def message_counts(state: DataFrame, g: Graph) -> DataFrame:
    """level, sent (edges leaving it), combined (distinct targets): what a level-wise search moves without and with combining."""
    out = state.select(F.col("id").alias("src"), "level").join(g.edges.select("src", "dst"), "src")
    return out.groupBy("level", "dst").agg(F.count(F.lit(1)).alias("n")).groupBy("level").agg(F.sum("n").alias("sent"), F.count(F.lit(1)).alias("combined"))


def frontier_profile(state: DataFrame, g: Graph) -> DataFrame:
    """level, vertices, edges active."""
    degree = g.edges.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("d"))
    return state.join(degree, "id", "left").groupBy("level").agg(F.count(F.lit(1)).alias("vertices"), F.coalesce(F.sum("d"), F.lit(0)).alias("edges"))


def compare_ranks(a: DataFrame, b: DataFrame, k: int = 10) -> DataFrame:
    """One row: largest and summed difference, both masses, and how many of the k highest agree."""
    both = a.select("id", F.col("rank").alias("x")).join(b.select("id", F.col("rank").alias("y")), "id")
    d = F.abs(F.col("x") - F.col("y"))
    top = [r.orderBy(F.desc("rank"), "id").limit(k).select("id") for r in (a, b)]
    agree = top[0].join(top[1], "id").agg(F.count(F.lit(1)).alias("agree"))
    return both.agg(F.max(d).alias("largest"), F.sum(d).alias("l1"), F.sum("x").alias("mass_a"), F.sum("y").alias("mass_b")).join(agree)


def teps(state: DataFrame, g: Graph, seconds: float) -> float:
    """Edges of the reached part over seconds."""
    return frontier_profile(state, g).agg(F.sum("edges")).first()[0] / seconds


def log_frame(spark, log: list[dict]) -> DataFrame:
    """A round log as a DataFrame; logs have a row a round."""
    return spark.createDataFrame([tuple(x.values()) for x in log], list(log[0]))
