"""Streaming queries, each with SQL for the batch answer that it must equal once all has arrived."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.plans.method_queries import STATE_SQL, bfs_sql
from tidegraph.plans.scratch import Scratch
from tidegraph.plans.workloads import graph
from tidegraph.streaming import events as ev

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return put


def replay(spark: SparkSession, parts: list[DataFrame], schema: str) -> DataFrame:
    """A stream of files read one a batch, in order."""
    import time

    scratch = Scratch(spark, "replay")
    for i, p in enumerate(parts):
        p.coalesce(1).write.mode("append").parquet(scratch.path(f"in/part={i}"))
        time.sleep(0.05)  # files are taken in order of their times
    raw = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(scratch.path("in/*"))
    return raw


def _start(size: int) -> str:
    return f"(floor(epoch(ts) / {size}) * {size})::BIGINT"


register("st_tumbling", f"SELECT {_start(86400)} AS start, count(*) AS n FROM events GROUP BY 1")(lambda spark, d: ev.run_to_end(ev.windowed(ev.events_stream(spark, d), "1 day"), "complete"))
register("st_sliding", "SELECT (floor(epoch(ts) / 21600) - k)::BIGINT * 21600 AS start, count(*) AS n FROM events, (SELECT unnest(range(0, 4)) AS k) GROUP BY 1")(
    lambda spark, d: ev.run_to_end(ev.windowed(ev.events_stream(spark, d), "1 day", "6 hours"), "complete")
)
register(
    "st_session",
    """SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*) AS n FROM (
  SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
    SELECT user_id, ts, event_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""",
)(lambda spark, d: ev.run_to_end(ev.sessions(ev.events_stream(spark, d)), "complete"))
register("st_dedup", "SELECT DISTINCT event_id FROM events")(
    lambda spark, d: ev.run_to_end(ev.without_repeats(ev.events_stream(spark, d).unionByName(ev.events_stream(spark, d))).select("event_id"))
)
register("st_stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")(
    lambda spark, d: ev.run_to_end(ev.events_stream(spark, d).join(spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_name"), F.expr("user_id = c_custkey")).select("event_id", "c_name"))
)
register("st_stream_stream_join", "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")(
    lambda spark, d: ev.run_to_end(ev.clicks_to_purchases(ev.events_stream(spark, d).where("event_type = 'click'"), ev.events_stream(spark, d).where("event_type = 'purchase'")))
)


@register("st_watermark_late", "SELECT (floor(epoch(max(ts)) / 86400) * 86400)::BIGINT AS last_day, (SELECT count(*) FROM events WHERE epoch(ts) >= 86400 * 7 + (SELECT floor(epoch(min(ts)) / 86400) * 86400 FROM events)) AS n FROM events")
def _late(spark, d):
    """Events from the eighth day on come first, the first week after them: by then the watermark has closed its windows."""
    e = ev.as_utc(spark.read.parquet(f"{d}/events.parquet"))
    first = e.agg(F.floor(F.unix_timestamp(F.min("ts")) / 86400) * 86400).first()[0]
    late = F.unix_timestamp("ts") < F.lit(first + 7 * 86400)
    schema = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"
    stream = replay(spark, [e.where(~late), e.where("false"), e.where(late)], schema)
    closed = ev.run_to_end(ev.windowed(stream, "1 day"), "update")
    kept = closed.groupBy("start").agg(F.max("n").alias("n"))
    return kept.agg(F.max("start").alias("last_day"), F.sum("n").alias("n"))


@register("st_degree_update", "SELECT src AS id, count(*) AS degree FROM (SELECT DISTINCT user_id AS src, dst FROM (SELECT user_id, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL) GROUP BY 1")
def _degrees(spark, d):
    e = graph(spark, d, "user_next").edges
    return ev.running_degrees(replay(spark, [e.where(f"pmod(src + dst, 3) = {i}") for i in range(3)], "src bigint, dst bigint"))


@register("st_bfs_incremental", bfs_sql("part_supplier", STATE_SQL))
def _bfs(spark, d):
    e = graph(spark, d, "part_supplier").edges
    return ev.incremental_bfs(replay(spark, [e.where(f"pmod(src + dst, 3) = {i}") for i in range(3)], "src bigint, dst bigint"), 0)
