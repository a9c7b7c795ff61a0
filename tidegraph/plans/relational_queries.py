"""Operators a user needs around the methods: a query each, with SQL for an independent engine.

Where one SQL text serves both engines it is written once, with tables in braces.
"""

from __future__ import annotations

import re
from collections.abc import Callable

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions import vectors
from tidegraph.model import OFFSETS, Graph
from tidegraph.operators import joins
from tidegraph.operators.bfs import bfs_level
from tidegraph.plans.method_queries import ROOTS, STATE_SQL, bfs_sql
from tidegraph.plans.scratch import Scratch, settings
from tidegraph.plans.workloads import SQL as EDGES
from tidegraph.plans.workloads import graph, read
from tidegraph.sources import files
from tidegraph.sources.urand import urand_of

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return put


def both(name: str, sql: str, other: str | None = None) -> None:
    """sql runs on Spark with {table} for tables, and without the braces, or as `other`, elsewhere."""
    tables = sorted(set(re.findall(r"\{(\w+)\}", sql)))
    QUERIES[name] = lambda spark, d: spark.sql(sql, **{t: read(spark, d, t) for t in tables})
    SQL[name] = other or re.sub(r"\{(\w+)\}", r"\1", sql)


# -- sources and sinks -----------------------------------------------------------------------------

register("scan_parquet_pruned", "SELECT l_orderkey, l_partkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1997-02-01'")(
    lambda spark, d: read(spark, d, "lineitem").where("l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1997-02-01'").select("l_orderkey", "l_partkey", "l_quantity")
)
for _kind in ("csv", "json", "orc"):
    register(f"scan_edges_{_kind}_roundtrip", EDGES["part_supplier"])(lambda spark, d, k=_kind: files.round_trip(graph(spark, d, "part_supplier").edges, k))


@register("source_urand", "SELECT ('0x' || substr(md5('42:a:' || i), 1, 15))::BIGINT % 1024 AS src, ('0x' || substr(md5('42:b:' || i), 1, 15))::BIGINT % 1024 AS dst FROM (SELECT l_orderkey * 8 + l_linenumber AS i FROM lineitem) WHERE i IS NOT NULL")
def _urand(spark, d):
    """A draw for each order line, by the source's own function; its key is the draw's number."""
    return urand_of(read(spark, d, "lineitem").select((F.col("l_orderkey") * 8 + F.col("l_linenumber")).alias("i")), "i", 1 << 10)


@register("source_edge_list_text", EDGES["part_supplier"])
def _text(spark, d):
    path = Scratch(spark, "edge-list").path("edges")
    files.write_edge_list(graph(spark, d, "part_supplier").edges, path)
    return files.read_edge_list(spark, path)


@register("sink_bucketed_edges", f"SELECT src, dst, (src % 8)::INTEGER AS blk FROM ({EDGES['part_next']})")
def _bucketed(spark, d):
    scratch = Scratch(spark, "bucketed")
    return files.save_bucketed(graph(spark, d, "part_next").edges, "tide_sink_" + scratch.root.rpartition("-")[2], 8, path=scratch.path("edges"))


@register("sink_partitioned_levels", bfs_sql("part_supplier", f"SELECT * FROM ({STATE_SQL}) WHERE level <= 2"))
def _levels(spark, d):
    path = Scratch(spark, "levels").path("state")
    bfs_level(graph(spark, d, "part_supplier"), 0).state.write.partitionBy("level").parquet(path)
    return spark.read.parquet(path).where("level <= 2").select("id", "parent", "level")


# -- graph views -----------------------------------------------------------------------------------

for _w in ("part_supplier", "part_next", "trade_dag", "copurchase", "page_path", "host_path", "order_chain", "hierarchy", "user_next", "turns"):
    register(f"edges_{_w}", EDGES[_w])(lambda spark, d, w=_w: graph(spark, d, w).edges)
register("edges_undirected", f"WITH e AS ({EDGES['part_next']}) SELECT src, dst FROM e UNION SELECT dst, src FROM e")(lambda spark, d: graph(spark, d, "part_next").undirected().edges)
register("edges_reverse", f"SELECT dst AS src, src AS dst FROM ({EDGES['part_next']})")(lambda spark, d: graph(spark, d, "part_next").reverse().edges)
both(
    "edges_filter_predicates",
    "SELECT l_orderkey AS src, l_partkey AS dst, CASE WHEN l_quantity < 10 THEN 'few' WHEN l_quantity < 30 THEN 'some' ELSE 'many' END AS size FROM {lineitem} "
    "WHERE l_returnflag IN ('A', 'R') AND l_quantity BETWEEN 5 AND 40 AND l_linestatus LIKE 'F%' AND l_suppkey IS NOT DISTINCT FROM l_suppkey",
)
register("subgraph_by_segment", f"SELECT e.src, e.dst FROM ({EDGES['trade_dag']}) e SEMI JOIN (SELECT c_custkey + 2000000000000 AS k FROM customer WHERE c_mktsegment = 'BUILDING') c ON e.src = c.k")(
    lambda spark, d: graph(spark, d, "trade_dag").edges.join(read(spark, d, "customer").where("c_mktsegment = 'BUILDING'").select((F.col("c_custkey") + 2_000_000_000_000).alias("src")), "src", "left_semi")
)
_DEG = "WITH e AS ({edges}), v AS (SELECT src AS id FROM e UNION SELECT dst FROM e) SELECT id, coalesce(n, 0)::BIGINT AS degree FROM v LEFT JOIN (SELECT {end} AS k, count(*) AS n FROM {of} GROUP BY 1) ON k = id"
register("out_degree", _DEG.format(edges=EDGES["trade_dag"], end="src", of="e"))(lambda spark, d: graph(spark, d, "trade_dag").degrees("out"))
register("in_degree", _DEG.format(edges=EDGES["trade_dag"], end="dst", of="e"))(lambda spark, d: graph(spark, d, "trade_dag").degrees("in"))
register("degree_all", _DEG.format(edges=EDGES["part_next"], end="x", of="(SELECT src AS x FROM e UNION ALL SELECT dst FROM e)"))(lambda spark, d: graph(spark, d, "part_next").degrees("all"))
register("adjacency_lists", f"SELECT src AS id, string_agg(dst::VARCHAR, ',' ORDER BY dst) AS nbrs FROM ({EDGES['part_next']}) GROUP BY src")(
    lambda spark, d: graph(spark, d, "part_next").adjacency().select("id", F.concat_ws(",", F.transform("nbrs", lambda x: x.cast("string"))).alias("nbrs"))
)
register("edges_from_adjacency", EDGES["part_next"])(lambda spark, d: Graph.from_adjacency(graph(spark, d, "part_next").adjacency(chunk=16)).edges)
register("neighbours_of", f"SELECT src, dst FROM ({EDGES['copurchase']}) WHERE src IN (0, 1, 2)")(lambda spark, d: graph(spark, d, "copurchase").edges.where("src in (0, 1, 2)"))
register("two_hop", f"WITH e AS MATERIALIZED ({EDGES['copurchase']}) SELECT DISTINCT b.dst AS id FROM e a JOIN e b ON a.dst = b.src WHERE a.src = 0 AND b.dst <> 0")(
    lambda spark, d: (e := graph(spark, d, "copurchase").edges).where("src = 0").select(F.col("dst").alias("src")).join(e, "src").where("dst <> 0").select(F.col("dst").alias("id")).distinct()
)
register(
    "validate_edges_report",
    f"""WITH e AS MATERIALIZED ({EDGES["dirty"]}), v AS (SELECT src AS id FROM ({EDGES["part_supplier"]})), flat AS (SELECT src, dst, count(*) AS n FROM e GROUP BY 1, 2)
SELECT (SELECT count(*) FROM e) AS edges, (SELECT count(*) FROM e WHERE src IS NULL OR dst IS NULL) AS null_ends, (SELECT count(*) FROM e WHERE src = dst) AS loops,
  (SELECT sum(n - 1)::BIGINT FROM flat WHERE src IS NOT NULL AND dst IS NOT NULL) AS surplus,
  (SELECT count(DISTINCT id) FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) WHERE id IS NOT NULL AND id NOT IN (SELECT id FROM v)) AS unknown_ends""",
)(lambda spark, d: Graph(graph(spark, d, "dirty").edges, graph(spark, d, "part_supplier").vertices).validate())

# -- joins -----------------------------------------------------------------------------------------

_J = "SELECT o_orderkey, c_name, n_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey"
for _name, _hint in (("join_hash_shuffle", "SHUFFLE_HASH"), ("join_sort_merge", "MERGE"), ("join_broadcast", None)):

    @register(_name, _J)
    def _join(spark, d, hint=_hint):
        o, c, n = (read(spark, d, t) for t in ("orders", "customer", "nation"))
        c = c.select("c_custkey", "c_name", "c_nationkey")
        c, n = (c.hint(hint), n.hint(hint)) if hint else (c, F.broadcast(n))  # nations are a fixed few
        return o.select("o_orderkey", "o_custkey").join(c, o["o_custkey"] == c["c_custkey"]).join(n, c["c_nationkey"] == n["n_nationkey"]).select("o_orderkey", "c_name", "n_name")


both("join_nested_loop_theta", "SELECT n_name, r_name FROM {nation} JOIN {region} ON n_regionkey < r_regionkey")
both("join_cross", "SELECT n_name, r_name FROM {nation} CROSS JOIN {region}")
both("join_left_outer", "SELECT c_custkey, coalesce(o_orderkey, -1) AS o_orderkey FROM {customer} LEFT JOIN {orders} ON c_custkey = o_custkey AND o_orderstatus = 'P'")
both("join_full_outer", "SELECT coalesce(p_partkey, -1) AS p_partkey, coalesce(s_suppkey, -1) AS s_suppkey FROM {part} FULL JOIN {supplier} ON p_partkey = s_suppkey * 3")
both("join_semi", "SELECT c_custkey, c_name FROM {customer} LEFT SEMI JOIN {orders} ON c_custkey = o_custkey AND o_totalprice > 200000", "SELECT c_custkey, c_name FROM customer SEMI JOIN (SELECT * FROM orders WHERE o_totalprice > 200000) o ON c_custkey = o_custkey")
both("join_anti", "SELECT c_custkey, c_name FROM {customer} LEFT ANTI JOIN {orders} ON c_custkey = o_custkey", "SELECT c_custkey, c_name FROM customer ANTI JOIN orders ON c_custkey = o_custkey")


@register("join_range_bucketed", "SELECT event_id, band FROM events JOIN (SELECT unnest(range(0, 40)) AS band) ON value >= band * 12.5 AND value < band * 12.5 + 20")
def _range(spark, d):
    bands = spark.range(40).select(F.col("id").alias("band"), (F.col("id") * 12.5).alias("low"), (F.col("id") * 12.5 + 20).alias("high"))
    return joins.range_join(read(spark, d, "events").select("event_id", "value"), bands, "value", "low", "high", 16.0).select("event_id", "band")


@register(
    "join_asof",
    """SELECT event_id, coalesce(prior, -1) AS prior FROM (SELECT p.event_id, v.event_id AS prior, row_number() OVER (PARTITION BY p.event_id ORDER BY v.ts DESC NULLS LAST, v.event_id DESC) AS r
FROM (SELECT * FROM events WHERE event_type = 'purchase') p LEFT JOIN (SELECT * FROM events WHERE event_type <> 'purchase') v ON p.user_id = v.user_id AND v.ts <= p.ts) WHERE r = 1""",
)
def _asof(spark, d):
    e = read(spark, d, "events").select("event_id", "ts", "user_id", "event_type")
    left, right = e.where("event_type = 'purchase'").select("event_id", "ts", "user_id"), e.where("event_type <> 'purchase'")
    return joins.asof_join(left, right.select("event_id", "ts", "user_id"), "user_id", "ts", ["event_id"], "event_id").select("event_id", F.coalesce("asof_event_id", F.lit(-1)).alias("prior"))


both("join_interval", "SELECT a.event_id AS first_id, b.event_id AS next_id FROM {events} a JOIN {events} b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '1' HOUR")
register("join_skew_salted", f"SELECT src, dst, n FROM ({EDGES['host_path']}) e JOIN (SELECT src AS s, count(*) AS n FROM ({EDGES['host_path']}) GROUP BY 1) ON s = src")(
    lambda spark, d: joins.salted_join((e := graph(spark, d, "host_path").edges), e.groupBy("src").agg(F.count(F.lit(1)).alias("n")), "src").select("src", "dst", "n")
)

# -- aggregates ------------------------------------------------------------------------------------

both(
    "agg_hash_partial_final",
    "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS avg_disc, count(*) AS n FROM {lineitem} GROUP BY l_returnflag, l_linestatus",
)
both("agg_sort_based", "SELECT c_mktsegment, max(c_name) AS last_name, min(c_name) AS first_name FROM {customer} GROUP BY c_mktsegment")
both("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM {lineitem} GROUP BY l_returnflag")
both("agg_filtered", "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, count(*) FILTER (WHERE o_orderstatus = 'O') AS open FROM {orders} GROUP BY o_custkey")
both("agg_having", "SELECT l_partkey AS id, count(DISTINCT l_orderkey) AS degree FROM {lineitem} GROUP BY l_partkey HAVING count(DISTINCT l_orderkey) > 25")
_G = "FROM {orders} JOIN {customer} ON o_custkey = c_custkey JOIN {nation} ON c_nationkey = n_nationkey"
for _name, _by in (("agg_grouping_sets", "GROUPING SETS ((n_regionkey, c_mktsegment), (o_orderstatus), ())"), ("agg_cube", "CUBE (n_regionkey, c_mktsegment)"), ("agg_rollup", "ROLLUP (n_regionkey, c_mktsegment)")):
    _cols = ["n_regionkey", "c_mktsegment"] + ["o_orderstatus"] * (_name == "agg_grouping_sets")
    _shown = {"n_regionkey": "coalesce(n_regionkey, -1) AS region", "c_mktsegment": "coalesce(c_mktsegment, '') AS segment", "o_orderstatus": "coalesce(o_orderstatus, '') AS status"}
    _sel = f"SELECT {', '.join(_shown[c] for c in _cols)}, CAST({{g}}({', '.join(_cols)}) AS BIGINT) AS gid, count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18, 2))) AS DOUBLE) AS total {_G} GROUP BY {_by}"
    both(_name, _sel.replace("{g}", "grouping_id"), re.sub(r"\{(\w+)\}", r"\1", _sel.replace("{g}", "grouping")))


@register("agg_pivot", "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{t}') AS {t}" for t in ("click", "purchase", "view")) + " FROM events GROUP BY user_id")
def _pivot(spark, d):
    out = read(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1)))
    return out.na.fill(0)


@register("agg_unpivot", "SELECT l_orderkey, kind, round(sum(v), 2) AS total FROM (SELECT l_orderkey, 'quantity' AS kind, l_quantity AS v FROM lineitem UNION ALL SELECT l_orderkey, 'price', l_extendedprice FROM lineitem) GROUP BY 1, 2")
def _unpivot(spark, d):
    wide = read(spark, d, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("quantity"), F.sum("l_extendedprice").alias("price"))
    return wide.unpivot("l_orderkey", ["quantity", "price"], "kind", "total").withColumn("total", F.round("total", 2))


@register("agg_approx_distinct_error", "SELECT true AS within FROM (SELECT count(*) FROM lineitem)")
def _approx(spark, d):
    got = read(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("e"))
    return got.select((F.abs(F.col("a") - F.col("e")) <= F.col("e") * 0.08).alias("within"))


both(
    "agg_percentiles", "SELECT round(percentile(d, 0.5), 6) AS p50, round(percentile(d, 0.9), 6) AS p90, CAST(max(d) AS BIGINT) AS most FROM (SELECT count(*) AS d FROM {lineitem} GROUP BY l_partkey)",
    "SELECT round(quantile_cont(d, 0.5), 6) AS p50, round(quantile_cont(d, 0.9), 6) AS p90, max(d) AS most FROM (SELECT count(*) AS d FROM lineitem GROUP BY l_partkey)",
)
both("agg_stats", "SELECT round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_discount), 8) AS var, round(corr(l_quantity, l_extendedprice), 6) AS r FROM {lineitem}")
both("agg_min_by_claim", "SELECT l_suppkey AS id, min_by(l_partkey, CAST(l_linenumber AS BIGINT) * 100000000 + l_partkey) AS parent, min(l_linenumber) AS level FROM {lineitem} GROUP BY l_suppkey", "SELECT l_suppkey AS id, arg_min(l_partkey, l_linenumber::BIGINT * 100000000 + l_partkey) AS parent, min(l_linenumber) AS level FROM lineitem GROUP BY l_suppkey")

# -- windows, order, sets --------------------------------------------------------------------------

_D = "(SELECT l_suppkey AS id, count(*) AS d FROM {lineitem} GROUP BY l_suppkey)"
both(
    "win_rank_family",
    "SELECT id, CAST(row_number() OVER w AS BIGINT) AS rn, CAST(rank() OVER w AS BIGINT) AS rk, CAST(dense_rank() OVER (ORDER BY d DESC) AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS nt, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd "
    f"FROM {_D} WINDOW w AS (ORDER BY d DESC, id)",
)
both("win_lag_lead_edges", "SELECT o_orderkey, coalesce(lag(o_orderkey) OVER w, -1) AS prior, coalesce(lead(o_orderkey) OVER w, -1) AS following FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
both("win_first_last_nth", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS a, last_value(o_orderkey) OVER w AS z, coalesce(nth_value(o_orderkey, 2) OVER w, -1) AS b FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
both("win_rows_frame", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS moving FROM {orders}")
both("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS near FROM {events}")
both("sort_multi_nulls", "SELECT c_custkey, seg, CAST(row_number() OVER (ORDER BY seg DESC NULLS LAST, c_acctbal, c_custkey) AS BIGINT) AS place FROM (SELECT c_custkey, c_acctbal, nullif(c_mktsegment, 'BUILDING') AS seg FROM {customer})")
both("limit_offset", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")
both("topk_degree", f"SELECT id, d FROM {_D} ORDER BY d DESC, id LIMIT 10")
both("topk_per_group", "SELECT o_custkey, o_orderkey, CAST(r AS BIGINT) AS r FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM {orders}) WHERE r <= 3")
_A, _B = "SELECT l_partkey AS k FROM {lineitem} WHERE l_linenumber = 1", "SELECT l_partkey AS k FROM {lineitem} WHERE l_quantity < 20"
for _name, _op in (("set_union_all", "UNION ALL"), ("set_union", "UNION"), ("set_intersect", "INTERSECT"), ("set_intersect_all", "INTERSECT ALL"), ("set_except", "EXCEPT"), ("set_except_all", "EXCEPT ALL")):
    both(_name, f"{_A} {_op} {_B}")

# -- functions -------------------------------------------------------------------------------------

both(
    "str_url_parts", "SELECT page_id, parse_url(url, 'HOST') AS host, split(url, '/')[0] AS scheme, length(url) AS n, upper(substring(url, 1, 5)) AS head FROM {pages}",
    "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, split_part(url, '/', 1) AS scheme, length(url)::INTEGER AS n, upper(substring(url, 1, 5)) AS head FROM pages",
)
both(
    "str_href_extract", "SELECT page_id, explode(regexp_extract_all(html, 'href=\"([^\"]*)\"')) AS href FROM {pages}",
    "SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages",
)
both(
    "date_parts_trunc", "SELECT o_orderkey, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(quarter(o_orderdate) AS BIGINT) AS q, CAST(dayofyear(o_orderdate) AS BIGINT) AS doy, CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR(10)) AS m FROM {orders}",
)
both(
    "date_diff_interval", "SELECT o_orderkey, CAST(datediff(DATE '1999-01-01', CAST(o_orderdate AS DATE)) AS BIGINT) AS days, CAST(CAST(o_orderdate AS DATE) + INTERVAL '30' DAY AS STRING) AS due FROM {orders}",
    "SELECT o_orderkey, date_diff('day', o_orderdate::DATE, DATE '1999-01-01') AS days, (o_orderdate::DATE + INTERVAL 30 DAY)::DATE::VARCHAR AS due FROM orders",
)
both(
    "math_scalar",
    "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS lg, round(power(l_discount, 2), 8) AS sq, round(sqrt(l_quantity), 6) AS rt, mod(l_partkey, 7) AS m, abs(l_suppkey - l_partkey) AS gap, l_partkey & 15 AS low, xor_ AS x FROM (SELECT *, l_partkey ^ l_suppkey AS xor_ FROM {lineitem})",
    "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS lg, round(power(l_discount, 2), 8) AS sq, round(sqrt(l_quantity), 6) AS rt, l_partkey % 7 AS m, abs(l_suppkey - l_partkey) AS gap, l_partkey & 15 AS low, xor(l_partkey, l_suppkey) AS x FROM lineitem",
)


@register("arr_higher_order", f"SELECT src AS id, list_sum(list_transform(list(dst), lambda x: x % 10))::BIGINT AS s, len(list_filter(list(dst), lambda x: x % 2 = 0))::INTEGER AS even FROM ({EDGES['part_next']}) GROUP BY src")
def _higher(spark, d):
    adj = graph(spark, d, "part_next").adjacency()
    return adj.select("id", F.aggregate(F.transform("nbrs", lambda x: x % 10), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("s"), F.size(F.filter("nbrs", lambda x: x % 2 == 0)).alias("even"))


@register("arr_set_ops", f"WITH a AS (SELECT src, list(dst) AS n FROM ({EDGES['part_next']}) GROUP BY src) SELECT x.src AS a, y.src AS b, len(list_intersect(x.n, y.n))::INTEGER AS shared, len(list_distinct(list_concat(x.n, y.n)))::INTEGER AS either FROM a x JOIN a y ON y.src = x.src + 1")
def _sets(spark, d):
    adj = graph(spark, d, "part_next").adjacency()
    x, y = adj.select(F.col("id").alias("a"), F.col("nbrs").alias("na")), adj.select((F.col("id") - 1).alias("a"), F.col("id").alias("b"), F.col("nbrs").alias("nb"))
    return x.join(y, "a").select("a", "b", F.size(F.array_intersect("na", "nb")).alias("shared"), F.size(F.array_union("na", "nb")).alias("either"))


@register("vec_cosine", "SELECT a.vec_id, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS c FROM embeddings a JOIN embeddings b ON b.vec_id = 0")
def _cosine(spark, d):
    v = read(spark, d, "embeddings").select("vec_id", "embedding")
    one = v.where("vec_id = 0").select(F.col("embedding").alias("probe"))
    return v.join(F.broadcast(one)).select("vec_id", F.round(vectors.cosine("embedding", "probe"), 6).alias("c"))


both(
    "map_attrs", "SELECT c_custkey, map('segment', c_mktsegment, 'name', c_name)['segment'] AS seg, array_join(array_sort(map_keys(map_filter(map('segment', c_mktsegment, 'name', c_name), (k, v) -> k <> 'name'))), ',') AS keys FROM {customer}",
    "SELECT c_custkey, c_mktsegment AS seg, 'segment' AS keys FROM customer",
)
both("json_props", "SELECT event_id, from_json(props, 'k int').k AS k, get_json_object(props, '$.k') AS text FROM {events}", "SELECT event_id, (props::JSON ->> '$.k')::INTEGER AS k, props::JSON ->> '$.k' AS text FROM events")
both("json_emit", "SELECT n_nationkey, to_json(named_struct('name', n_name, 'region', n_regionkey)) AS j FROM {nation}", "SELECT n_nationkey, '{\"name\":\"' || n_name || '\",\"region\":' || n_regionkey || '}' AS j FROM nation")
both(
    "null_handling", "SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS seg, try_cast(substring(c_name, 10, 9) AS BIGINT) AS n, (try_cast(c_name AS BIGINT) IS NULL) AS bad, (nullif(c_nationkey, 3) IS NULL) AS gone FROM {customer}",
)
both("cast_decimal", "SELECT l_partkey AS src, l_suppkey AS dst, CAST(sum(CAST(l_extendedprice AS DECIMAL(18, 2))) AS DOUBLE) AS w FROM {lineitem} GROUP BY l_partkey, l_suppkey")
both("sub_scalar_corr", f"SELECT id, d FROM {_D} x WHERE d > (SELECT avg(y.d) FROM {_D} y)")
both("sub_exists", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
both("sub_in", "SELECT s_suppkey FROM {supplier} WHERE s_nationkey IN (SELECT n_nationkey FROM {nation} WHERE n_regionkey = 2)")
_KINDS = [(level, kind, OFFSETS[kind]) for level, kind in enumerate(("region", "nation", "customer", "order"))]
_TREE = f"""t AS (SELECT id, 0 AS level FROM {{start}} UNION ALL SELECT e.dst, t.level + 1 FROM t JOIN {{e}} e ON e.src = t.id)
SELECT id - CASE level {" ".join(f"WHEN {i} THEN {offset}" for i, _, offset in _KINDS)} END AS id, level, CASE level {" ".join(f"WHEN {i} THEN '{kind[0]}'" for i, kind, _ in _KINDS)} END AS kind FROM t"""
#: Spark hands on a recursion's rows in as many tasks as its first row was dealt to, if it keeps that row dealt.
_DEALT = {"spark.sql.cteRecursionAnchorRowsLimitToConvertToLocalRelation": "0", "spark.sql.adaptive.coalescePartitions.enabled": "false"}


@register("rcte_hierarchy", f"WITH RECURSIVE e AS MATERIALIZED ({EDGES['hierarchy']}), {_TREE.format(start=f'(SELECT {ROOTS['hierarchy']}::BIGINT AS id)', e='e')}")
def _tree(spark, d):
    """Region 0, its nations, their customers and their orders, under their own keys; with repeated rows, once for each way.

    Edges are bucketed once, so a step of the recursion moves the last level alone. LIMIT ALL lifts Spark's limit of 10^6 rows.
    """
    s = Scratch(spark, "rcte")
    edges = s.save_bucketed(graph(spark, d, "hierarchy").edges.where("src is not null"), "edges", "src")
    start = spark.range(ROOTS["hierarchy"], ROOTS["hierarchy"] + 1)
    with settings(spark, _DEALT):
        out = s.save(spark.sql(f"WITH RECURSIVE {_TREE} LIMIT ALL", start=start, e=edges), "levels")
    s.keep_only("levels")
    return out


register("sample_edges_hash", f"SELECT src, dst FROM ({EDGES['part_next']}) WHERE ('0x' || substr(md5(src || ':' || dst), 1, 15))::BIGINT % 10 = 0")(
    lambda spark, d: graph(spark, d, "part_next").edges.where(F.conv(F.substring(F.md5(F.concat_ws(":", F.col("src").cast("string"), F.col("dst").cast("string"))), 1, 15), 16, 10).cast("bigint") % 10 == 0)
)

# -- functions in Python ---------------------------------------------------------------------------


@register("udf_arrow_scalar", "SELECT vec_id, round(list_distance(embedding::DOUBLE[], list_transform(embedding, lambda x: 0::DOUBLE)), 5) AS n FROM embeddings")
def _scalar(spark, d):
    @F.pandas_udf("double")
    def length(v: pd.Series) -> pd.Series:
        return pd.Series(np.linalg.norm(np.stack(v.to_numpy()).astype(float), axis=1))

    return read(spark, d, "embeddings").select("vec_id", F.round(length("embedding"), 5).alias("n"))


@register("udaf_grouped", "SELECT l_suppkey, round(quantile_cont(l_quantity, 0.5), 6) AS mid FROM lineitem GROUP BY l_suppkey")
def _grouped(spark, d):
    @F.pandas_udf("double")
    def mid(v: pd.Series) -> float:
        return float(v.median())

    return read(spark, d, "lineitem").groupBy("l_suppkey").agg(F.round(mid("l_quantity"), 6).alias("mid"))


@register("udtf_neighbours", EDGES["part_next"])
def _udtf(spark, d):
    class Neighbours:
        def eval(self, row_id: int, nbrs: list):
            for x in nbrs:
                yield row_id, x

    spark.udtf.register("tide_neighbours", F.udtf(Neighbours, returnType="src bigint, dst bigint"))
    return spark.sql("SELECT t.src, t.dst FROM {adj} a, LATERAL tide_neighbours(a.id, a.nbrs) t", adj=graph(spark, d, "part_next").adjacency())


@register("cogroup_arrow", "SELECT c_custkey AS k, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS n FROM customer")
def _cogroup(spark, d):
    def one(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        return pa.table({"k": left["k"], "n": pa.array([right.num_rows] * left.num_rows, pa.int64())})

    c, o = read(spark, d, "customer").select(F.col("c_custkey").alias("k")), read(spark, d, "orders").select(F.col("o_custkey").alias("k"))
    return c.groupBy("k").cogroup(o.groupBy("k")).applyInArrow(one, "k bigint, n bigint")


