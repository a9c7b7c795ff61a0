"""Streams of edges and events: windows, watermarks, joins, running degrees and incremental search.

Sources are Parquet files; runs take all that is there and stop (availableNow), so a stream's result can
be held against a batch's. Checkpoints and results lie in the shared folder.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions.adaptive import small
from tidegraph.operators.bfs import STATE, reduce_claims
from tidegraph.plans.scratch import Scratch

SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def events_stream(spark: SparkSession, sf_dir: str, table: str = "events", schema: str = SCHEMA) -> DataFrame:
    """The table as a stream; times become timestamps, read as UTC, since watermarks take no others."""
    raw = spark.readStream.schema(schema).option("pathGlobFilter", f"{table}.parquet").parquet(sf_dir)
    return as_utc(raw) if "ts" in raw.columns else raw


def as_utc(df: DataFrame) -> DataFrame:
    """Wall-clock times as instants, whatever the session's zone."""
    return df.withColumn("ts", F.make_timestamp_ltz(*(f("ts") for f in (F.year, F.month, F.day, F.hour, F.minute)), F.extract(F.lit("SECOND"), "ts"), F.lit("UTC")))


def run_to_end(stream: DataFrame, mode: str = "append", label: str = "stream") -> DataFrame:
    """Runs a stream over all present files and returns what it gave out (in complete mode: the last result)."""
    spark = stream.sparkSession
    scratch = Scratch(spark, label)

    def put(batch: DataFrame, epoch: int) -> None:
        # a repeated epoch overwrites itself
        batch.write.mode("overwrite").parquet(scratch.path(f"out/epoch={epoch}"))

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", scratch.path("checkpoint")).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    got = spark.read.schema(stream.schema).parquet(scratch.path("out"))
    if mode == "complete":
        last = spark.read.parquet(scratch.path("out")).agg(F.max("epoch")).first()[0]
        got = spark.read.schema(stream.schema).parquet(scratch.path(f"out/epoch={last}"))
    return got.select(stream.columns)


def windowed(stream: DataFrame, size: str, slide: str | None = None) -> DataFrame:
    """window start (seconds since 1970), n: counts of tumbling or sliding windows."""
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return stream.withWatermark("ts", "1 hour").groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_timestamp("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "2 hours") -> DataFrame:
    """user_id, start, n of runs of events no further apart than the gap."""
    w = F.session_window("ts", gap)
    return stream.withWatermark("ts", "1 hour").groupBy("user_id", w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_timestamp("w.start").alias("start"), "n")


def without_repeats(stream: DataFrame, key: str = "event_id") -> DataFrame:
    return stream.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark([key])


def clicks_to_purchases(clicks: DataFrame, purchases: DataFrame, within: str = "1 hour") -> DataFrame:
    """click_id, purchase_id of one user, the purchase after the click and no later than `within`."""
    a = clicks.select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("ct")).withWatermark("ct", "1 hour")
    b = purchases.select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("pu"), F.col("ts").alias("pt")).withWatermark("pt", "1 hour")
    return a.join(b, F.expr(f"cu = pu and pt > ct and pt <= ct + interval {within}")).select("click_id", "purchase_id")


def fold(stream: DataFrame, step: Callable[[DataFrame | None, DataFrame, int], DataFrame], label: str) -> DataFrame:
    """Keeps a table up to date: step(old table or None, new rows, epoch) gives the next version.

    Versions are written by epoch, so a repeated epoch starts from the version before it.
    """
    spark = stream.sparkSession
    scratch = Scratch(spark, label)
    versions: list[str] = []

    def put(batch: DataFrame, epoch: int) -> None:
        before = [v for v in versions if v != f"v{epoch}"]
        old = spark.read.parquet(scratch.path(before[-1])) if before else None
        scratch.save(step(old, batch, epoch), f"v{epoch}")
        versions[:] = [*before, f"v{epoch}"]

    query = stream.writeStream.option("checkpointLocation", scratch.path("checkpoint")).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return spark.read.parquet(scratch.path(versions[-1]))


def running_degrees(edges: DataFrame) -> DataFrame:
    """id, degree of an edge stream (src, dst), kept up batch by batch."""

    def step(old: DataFrame | None, batch: DataFrame, epoch: int) -> DataFrame:
        new = batch.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("degree"))
        return new if old is None else old.unionByName(new).groupBy("id").agg(F.sum("degree").alias("degree"))

    return fold(edges, step, "degrees")


def incremental_bfs(edges: DataFrame, root: int) -> DataFrame:
    """id, parent, level after each batch of inserted edges: levels only fall, so relaxing from the ends of
    new edges is enough. Deletions would need a new search and are not taken.
    """
    spark = edges.sparkSession
    scratch = Scratch(spark, "bfs-stream")
    kept: list[str] = []

    def step(old: DataFrame | None, batch: DataFrame, epoch: int) -> DataFrame:
        state = old if old is not None else spark.createDataFrame([(root, root, 0)], STATE)
        scratch.save(batch.select("src", "dst").distinct(), f"edges-{epoch}")
        if f"edges-{epoch}" not in kept:
            kept.append(f"edges-{epoch}")
        known = spark.read.schema("src bigint, dst bigint").parquet(*(scratch.path(k) for k in kept))
        front, via, r = state, batch.select("src", "dst"), 0
        while True:
            r += 1
            told = front.join(via, front["id"] == via["src"]).select(F.col("dst").alias("id"), F.col("src").alias("parent"), (F.col("level") + 1).alias("level"))
            better = scratch.save(reduce_claims(told, state, "min_level"), f"better-{epoch}-{r}")
            n = better.count()
            if not n:
                return state
            state = scratch.save(state.unionByName(better).groupBy("id").agg(F.min(F.struct("level", "parent")).alias("s")).select("id", "s.parent", "s.level"), f"state-{epoch}-{r}")
            for old_table in (f"state-{epoch}-{r - 1}", f"better-{epoch}-{r - 1}"):
                scratch.drop(old_table)
            front, via = small(better, n), known

    return fold(edges, step, "bfs-incremental")
