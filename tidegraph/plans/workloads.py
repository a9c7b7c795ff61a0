"""The graphs of the experiments, built from the given tables; for each also SQL for an independent engine."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from tidegraph.model import OFFSETS, Graph
from tidegraph.sources.urand import urand


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _both(a: DataFrame) -> DataFrame:
    """Distinct pairs in both directions."""
    pairs = a.select("src", "dst").distinct()
    return pairs.unionByName(pairs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def _both_sql(pairs: str) -> str:
    return f"SELECT src, dst FROM ({pairs}) UNION SELECT dst, src FROM ({pairs})"




def part_supplier(spark, d) -> DataFrame:
    return _both(read(spark, d, "lineitem").select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + OFFSETS["supplier"]).alias("dst")))


def order_part(spark, d) -> DataFrame:
    return _both(read(spark, d, "lineitem").select((F.col("l_orderkey") + OFFSETS["order"]).alias("src"), F.col("l_partkey").alias("dst")))


def order_part_window(spark, d, first: str = "1997-01-01", last: str = "1997-01-31") -> DataFrame:
    dated = read(spark, d, "orders").where(F.col("o_orderdate").cast("date").between(first, last)).select("o_orderkey")
    lines = read(spark, d, "lineitem").join(dated, F.col("l_orderkey") == F.col("o_orderkey"), "left_semi")
    return _both(lines.select((F.col("l_orderkey") + OFFSETS["order"]).alias("src"), F.col("l_partkey").alias("dst")))


def copurchase(spark, d) -> DataFrame:
    """Parts of one order; an order has few lines, so pairs stay few."""
    lines = read(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    a, b = lines.alias("a"), lines.alias("b")
    met = a.join(b, F.expr("a.l_orderkey = b.l_orderkey and a.l_partkey <> b.l_partkey"))
    return met.select(F.col("a.l_partkey").alias("src"), F.col("b.l_partkey").alias("dst")).distinct()


def bought_together(spark, d) -> DataFrame:
    """As copurchase, undirected: src < dst, once for each order that has both."""
    lines = read(spark, d, "lineitem").select("l_orderkey", "l_partkey").repartition("l_orderkey").distinct()
    a, b = lines.alias("a"), lines.alias("b")
    return a.join(b, F.expr("a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey")).select(F.col("a.l_partkey").alias("src"), F.col("b.l_partkey").alias("dst"))


def part_next(spark, d) -> DataFrame:
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    lines = read(spark, d, "lineitem").select("l_orderkey", F.col("l_partkey").alias("src"), F.lead("l_partkey").over(w).alias("dst"))
    return lines.where("dst is not null").select("src", "dst").distinct()


def trade_dag(spark, d) -> DataFrame:
    orders, lines = read(spark, d, "orders"), read(spark, d, "lineitem")
    parts = [
        orders.select((F.col("o_custkey") + OFFSETS["customer"]).alias("src"), (F.col("o_orderkey") + OFFSETS["order"]).alias("dst")),
        lines.select((F.col("l_orderkey") + OFFSETS["order"]).alias("src"), F.col("l_partkey").alias("dst")),
        lines.select(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + OFFSETS["supplier"]).alias("dst")),
    ]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).distinct()


def _hrefs(spark, d) -> DataFrame:
    """page_id, url, href."""
    pages = read(spark, d, "pages").select("page_id", "url", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'))).alias("href"))
    return pages


def _numbered(df: DataFrame, column: str, kind: str) -> DataFrame:
    """Dense rank of strings in binary order, by ranges, plus the kind's offset."""
    from tidegraph.model import dense_ids

    return dense_ids(df, column).select(column, (F.col("id") + OFFSETS[kind]).alias(f"{column}_id"))


def page_path(spark, d) -> DataFrame:
    refs = _hrefs(spark, d)
    return _both(refs.join(_numbered(refs, "href", "path"), "href").select((F.col("page_id") + OFFSETS["page"]).alias("src"), F.col("href_id").alias("dst")))


def host_path(spark, d) -> DataFrame:
    refs = _hrefs(spark, d).withColumn("host", F.regexp_extract("url", "^https?://([^/]+)", 1))
    return refs.join(_numbered(refs, "href", "path"), "href").join(_numbered(refs, "host", "host"), "host").select(F.col("host_id").alias("src"), F.col("href_id").alias("dst")).distinct()


def order_chain(spark, d) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return read(spark, d, "orders").select(F.col("o_orderkey").alias("src"), F.lead("o_orderkey").over(w).alias("dst")).where("dst is not null")


def hierarchy(spark, d) -> DataFrame:
    n, c, o = read(spark, d, "nation"), read(spark, d, "customer"), read(spark, d, "orders")
    parts = [
        n.select((F.col("n_regionkey").cast("bigint") + OFFSETS["region"]).alias("src"), (F.col("n_nationkey").cast("bigint") + OFFSETS["nation"]).alias("dst")),
        c.select((F.col("c_nationkey").cast("bigint") + OFFSETS["nation"]).alias("src"), (F.col("c_custkey") + OFFSETS["customer"]).alias("dst")),
        o.select((F.col("o_custkey") + OFFSETS["customer"]).alias("src"), (F.col("o_orderkey") + OFFSETS["order"]).alias("dst")),
    ]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def user_next(spark, d) -> DataFrame:
    """The order over all events: ranges of time are numbered apart and stitched at their edges."""
    from tidegraph.model import dense_ids

    events = read(spark, d, "events").select("user_id", F.struct("ts", "event_id").alias("at"))
    place = dense_ids(events, "at")
    rows = events.join(place, "at").select("id", "user_id")
    after = rows.select((F.col("id") - 1).alias("id"), F.col("user_id").alias("dst"))
    return rows.join(after, "id").select(F.col("user_id").alias("src"), "dst").distinct()


def turns(spark, d) -> DataFrame:
    """conv_id * 1000 + turn to the next turn."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    t = read(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("src"), F.lead(F.col("conv_id") * 1000 + F.col("turn")).over(w).alias("dst"))
    return t.where("dst is not null")


def knn(spark, d, k: int = 5, most: int = 1 << 16, tile: int = 1024) -> DataFrame:
    """k nearest by cosine, ties by id: the set of all vectors against all, block by block in numpy.

    Every block meets every other, so each vector is sent once a block: blocks are as large as a task holds (`most`
    vectors), and smaller only while there are too few pairs of blocks for the cores. Within a pair, tiles of asking and
    of held vectors bound the matrix of likenesses.
    """
    import numpy as np
    import pyarrow as pa

    v = read(spark, d, "embeddings").select("vec_id", "embedding")
    n = v.count()
    blocks = max(1, -(-n // most), min(-(-n // (2 * tile)), math.isqrt(2 * spark.sparkContext.defaultParallelism)))
    placed = v.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asks = placed.select(F.col("b").alias("q"), every.alias("b"), F.col("vec_id"), F.col("embedding"))
    held = placed.withColumn("q", every).select("q", "b", "vec_id", "embedding")

    def matrix(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
        x = np.stack(t["embedding"].to_numpy(zero_copy_only=False)).astype(float) if t.num_rows else np.zeros((0, 1))
        return t["vec_id"].to_numpy(), x

    def one(left: pa.Table, right: pa.Table) -> pa.Table:
        (a, x), (b, y) = matrix(left), matrix(right)
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        xn, yn = np.linalg.norm(x, axis=1), np.linalg.norm(y, axis=1)
        for i in range(0, len(a) if len(b) else 0, tile):
            mine, ids, near = a[i : i + tile, None], np.zeros((len(a[i : i + tile]), 0), np.int64), np.zeros((len(a[i : i + tile]), 0))
            for j in range(0, len(b), 4 * tile):
                to = slice(j, j + 4 * tile)
                c = np.round((x[i : i + tile] @ y[to].T) / np.outer(xn[i : i + tile], yn[to]), 9)
                c[mine == b[to]] = -np.inf
                ids, near = np.hstack((ids, np.broadcast_to(b[to], c.shape))), np.hstack((near, c))
                best = np.lexsort((ids, -near), axis=1)[:, :k]
                ids, near = np.take_along_axis(ids, best, 1), np.take_along_axis(near, best, 1)
            keep = near > -np.inf
            found.append((np.broadcast_to(mine, ids.shape)[keep], ids[keep], near[keep]))
        return pa.table(dict(zip(("src", "dst", "c"), (np.concatenate(x) for x in zip(*found, strict=True)), strict=True)))

    pairs = asks.groupBy("q", "b").cogroup(held.groupBy("q", "b")).applyInArrow(one, "src bigint, dst bigint, c double")
    w = Window.partitionBy("src").orderBy(F.desc("c"), "dst")
    return pairs.withColumn("r", F.row_number().over(w)).where(F.col("r") <= k).select("src", "dst")


def urand_k(spark, d) -> int:
    """The least k for which ten times 2^k reaches the number of order lines: 10, 13 and 16 on the given tables."""
    return max(1, (-(-read(spark, d, "lineitem").count() // 10) - 1).bit_length())


def urand_dense(spark, d) -> DataFrame:
    return urand(spark, urand_k(spark, d), 16)


def urand_sparse(spark, d) -> DataFrame:
    return urand(spark, urand_k(spark, d), 2)


def dirty(spark, d) -> DataFrame:
    """part_supplier with repeats, loops, null and unknown ends."""
    e = part_supplier(spark, d)
    n = F.lit(None).cast("bigint")
    parts = [
        e, e.where("src % 7 = 0 and src < 1000000000000"), e.where("src % 11 = 0").select("src", F.col("src").alias("dst")),
        e.where("src % 13 = 0").select("src", n.alias("dst")), e.where("src % 17 = 0").select(n.alias("src"), "dst"), e.where("src % 19 = 0").select("src", (F.col("dst") + 50_000_000_000_000).alias("dst")),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


BUILDERS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "part_supplier": part_supplier, "order_part": order_part, "order_part_window": order_part_window, "copurchase": copurchase, "part_next": part_next, "trade_dag": trade_dag,
    "page_path": page_path, "host_path": host_path, "order_chain": order_chain, "hierarchy": hierarchy, "user_next": user_next, "turns": turns, "knn": knn,
    "urand_dense": urand_dense, "urand_sparse": urand_sparse, "dirty": dirty,
}


def graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return Graph(BUILDERS[name](spark, sf_dir))


_S, _C, _O = OFFSETS["supplier"], OFFSETS["customer"], OFFSETS["order"]
_HREFS = "SELECT page_id, url, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS href FROM pages"
_PS = f"SELECT l_partkey AS src, l_suppkey + {_S} AS dst FROM lineitem"


def _urand_sql(degree: int) -> str:
    draw = lambda c: f"(('0x' || substr(md5('42:{c}:' || i), 1, 15))::BIGINT % n)"
    size = "(SELECT (1::BIGINT << greatest(1, ceil(log2(greatest(ceil(count(*) / 10.0), 1))))::INTEGER) AS n FROM lineitem)"
    pairs = f"SELECT {draw('a')} AS a, {draw('b')} AS b FROM (SELECT n, unnest(range(0, n * {degree} // 2)) AS i FROM {size})"
    return f"SELECT DISTINCT a AS src, b AS dst FROM (SELECT a, b FROM ({pairs}) UNION ALL SELECT b, a FROM ({pairs})) WHERE a <> b"


#: The same edges in SQL, for oracles.
SQL: dict[str, str] = {
    "part_supplier": _both_sql(_PS),
    "order_part": _both_sql(f"SELECT l_orderkey + {_O} AS src, l_partkey AS dst FROM lineitem"),
    "order_part_window": _both_sql(f"SELECT l_orderkey + {_O} AS src, l_partkey AS dst FROM lineitem JOIN orders ON o_orderkey = l_orderkey WHERE o_orderdate::DATE BETWEEN DATE '1997-01-01' AND DATE '1997-01-31'"),
    "copurchase": "SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey <> b.l_partkey",
    "part_next": "SELECT DISTINCT src, dst FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem) WHERE dst IS NOT NULL",
    "trade_dag": f"SELECT o_custkey + {_C} AS src, o_orderkey + {_O} AS dst FROM orders UNION SELECT l_orderkey + {_O}, l_partkey FROM lineitem UNION SELECT l_partkey, l_suppkey + {_S} FROM lineitem",
    "page_path": _both_sql(f"SELECT page_id + {OFFSETS['page']} AS src, dense_rank() OVER (ORDER BY href) - 1 + {OFFSETS['path']} AS dst FROM ({_HREFS})"),
    "host_path": f"SELECT DISTINCT dense_rank() OVER (ORDER BY regexp_extract(url, '^https?://([^/]+)', 1)) - 1 + {OFFSETS['host']} AS src, dense_rank() OVER (ORDER BY href) - 1 + {OFFSETS['path']} AS dst FROM ({_HREFS})",
    "order_chain": "SELECT src, dst FROM (SELECT o_orderkey AS src, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS dst FROM orders) WHERE dst IS NOT NULL",
    "hierarchy": f"SELECT n_regionkey::BIGINT + {OFFSETS['region']} AS src, n_nationkey::BIGINT + {OFFSETS['nation']} AS dst FROM nation UNION ALL SELECT c_nationkey::BIGINT + {OFFSETS['nation']}, c_custkey + {_C} FROM customer UNION ALL SELECT o_custkey + {_C}, o_orderkey + {_O} FROM orders",
    "user_next": "SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events) WHERE dst IS NOT NULL",
    "turns": "SELECT src, dst FROM (SELECT conv_id * 1000 + turn AS src, lead(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS dst FROM conversations) WHERE dst IS NOT NULL",
    "knn": "SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) DESC, b.vec_id) AS r FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 5",
    "urand_dense": _urand_sql(16),
    "urand_sparse": _urand_sql(2),
    "dirty": f"WITH e AS ({_both_sql(_PS)}) SELECT src, dst FROM e UNION ALL SELECT src, dst FROM e WHERE src % 7 = 0 AND src < 1000000000000 UNION ALL SELECT src, src FROM e WHERE src % 11 = 0 UNION ALL SELECT src, NULL FROM e WHERE src % 13 = 0 UNION ALL SELECT NULL, dst FROM e WHERE src % 17 = 0 UNION ALL SELECT src, dst + 50000000000000 FROM e WHERE src % 19 = 0",
}
