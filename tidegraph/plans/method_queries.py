"""Queries for the two methods, their variants, baselines and measures, with SQL for an independent engine."""

from __future__ import annotations

from collections.abc import Callable


from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tidegraph.functions import measures
from tidegraph.functions.adaptive import run_all
from tidegraph.model import OFFSETS, Graph, dense_ids, owner
from tidegraph.operators import analytics, bfs, components, planner, rank
from tidegraph.plans.scratch import Scratch
from tidegraph.plans.workloads import SQL as EDGES
from tidegraph.plans.workloads import bought_together, graph

#: Where searches start: the part, order or page of FIXTURES, or 0.
ROOTS = {"order_part_window": 7, "page_path": OFFSETS["page"], "hierarchy": OFFSETS["region"]}
#: Bound of the recursion in SQL; above any depth in the tables.
DEPTH = 40
K = 10

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def put(fn):
        QUERIES[name] = fn
        if sql:
            SQL[name] = sql
        return fn

    return put


def held(spark, d: str, name: str) -> Graph:
    """The workload's edges, written once so that rounds don't rebuild them."""
    g = graph(spark, d, name)
    return Graph(Scratch(spark, "edges").save(g.edges, name))


def root_of(name: str, d: str | None = None) -> int:
    return ROOTS.get(name, 0)


def bfs_sql(name: str, what: str, root: str | None = None) -> str:
    """what follows: states is (id, parent, level)."""
    start = root or str(root_of(name))
    return f"""
WITH RECURSIVE e AS MATERIALIZED ({EDGES[name]}), start AS (SELECT ({start})::BIGINT AS root),
walk AS (SELECT root AS id, 0 AS level FROM start UNION SELECT e.dst, w.level + 1 FROM walk w JOIN e ON e.src = w.id WHERE w.level < {DEPTH}),
levels AS MATERIALIZED (SELECT id, min(level) AS level FROM walk GROUP BY id),
states AS MATERIALIZED (
  SELECT id, id AS parent, level FROM levels WHERE level = 0
  UNION ALL SELECT b.id, min(a.id) AS parent, b.level FROM levels a JOIN e ON e.src = a.id JOIN levels b ON b.id = e.dst AND b.level = a.level + 1 GROUP BY b.id, b.level)
{what}"""


STATE_SQL = "SELECT id, parent, level::INTEGER AS level FROM states"
_CHAIN = "SELECT max(src) FROM (SELECT src FROM e WHERE src NOT IN (SELECT dst FROM e)) WHERE src IN (SELECT o_orderkey FROM orders WHERE o_custkey = (SELECT o_custkey FROM orders GROUP BY o_custkey ORDER BY count(*) DESC, o_custkey LIMIT 1))"


def chain_root(spark, d: str) -> int:
    """The first order of the customer with the most orders."""
    orders = spark.read.parquet(f"{d}/orders.parquet")
    best = orders.groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "o_custkey").limit(1)
    return orders.join(F.broadcast(best), "o_custkey").orderBy("o_orderdate", "o_orderkey").select("o_orderkey").first()[0]


for _w in ("part_supplier", "order_part", "order_part_window", "copurchase", "page_path", "hierarchy", "user_next", "urand_dense", "urand_sparse"):
    register(f"bfs_level_{_w}", bfs_sql(_w, STATE_SQL))(lambda spark, d, w=_w: bfs.bfs_level(held(spark, d, w), root_of(w)).state)
register("bfs_level_order_chain", bfs_sql("order_chain", STATE_SQL, _CHAIN))(lambda spark, d: bfs.bfs_level(held(spark, d, "order_chain"), chain_root(spark, d)).state)
for _w in ("part_supplier", "order_part", "order_part_window", "page_path", "urand_dense"):
    register(f"bfs_relaxed_{_w}", bfs_sql(_w, STATE_SQL))(lambda spark, d, w=_w: bfs.bfs_relaxed(held(spark, d, w), root_of(w), how="cyclic", blocks=8).state)


@register("bfs_relaxed_order_chain", bfs_sql("order_chain", STATE_SQL, _CHAIN))
def _relaxed_chain(spark, d):
    """Ids made dense in chain order, so that blocks hold whole chains."""
    g, root, to, n = chained(spark, d)
    found = bfs.bfs_relaxed(g, root, how="block", blocks=8, n=n).state
    back = to.select("o_orderkey", "id")
    parent = back.select(F.col("o_orderkey").alias("p"), F.col("id").alias("parent"))
    return found.join(back, "id").join(parent, "parent").select(F.col("o_orderkey").alias("id"), F.col("p").alias("parent"), "level")


def chained(spark, d: str):
    orders = spark.read.parquet(f"{d}/orders.parquet").select("o_orderkey", F.struct("o_custkey", "o_orderdate", "o_orderkey").alias("at"))
    to = Scratch(spark, "chain").save(dense_ids(orders, "at").select(F.col("at.o_orderkey").alias("o_orderkey"), "id"), "ids")
    e = graph(spark, d, "order_chain").edges
    ends = to.select(F.col("o_orderkey").alias("src"), F.col("id").alias("s")), to.select(F.col("o_orderkey").alias("dst"), F.col("id").alias("t"))
    g = Graph(Scratch(spark, "chain").save(e.join(ends[0], "src").join(ends[1], "dst").select(F.col("s").alias("src"), F.col("t").alias("dst")), "edges"))
    root = to.where(F.col("o_orderkey") == chain_root(spark, d)).first()["id"]
    return g, root, to, to.count()


register("bfs_uncombined", bfs_sql("part_supplier", STATE_SQL))(lambda spark, d: bfs.bfs_level(held(spark, d, "part_supplier"), 0, combine=False).state)
register("bfs_pull", bfs_sql("part_supplier", STATE_SQL))(lambda spark, d: bfs.bfs_level(held(spark, d, "part_supplier"), 0, direction="pull").state)
register("bfs_auto", bfs_sql("order_part", STATE_SQL))(lambda spark, d: bfs.bfs_level(held(spark, d, "order_part"), 0, direction="auto").state)
register("bfs_dropin", bfs_sql("part_supplier", STATE_SQL))(lambda spark, d: bfs.bfs_dropin(graph(spark, d, "part_supplier"), 0).state)
register("bfs_relaxed_uncombined", bfs_sql("part_supplier", STATE_SQL))(lambda spark, d: bfs.bfs_relaxed(held(spark, d, "part_supplier"), 0, how="hash", blocks=8, combine=False).state)
for _w in ("part_supplier", "order_part_window"):
    register(f"bfs_hops_{_w}", bfs_sql(_w, STATE_SQL))(lambda spark, d, w=_w: bfs.bfs_hops(held(spark, d, w), root_of(w), hops=2, how="cyclic").state)
register("baseline_vertex_bfs", bfs_sql("part_supplier", STATE_SQL))(lambda spark, d: bfs.bfs_vertex(held(spark, d, "part_supplier"), 0).state)
register("spmv_bfs", bfs_sql("part_supplier", STATE_SQL))(lambda spark, d: bfs.spmv_bfs(held(spark, d, "part_supplier"), 0).state)


@register("bfs_sequential", bfs_sql("part_supplier", STATE_SQL))
def _sequential(spark, d):
    return bfs.bfs_dropin(graph(spark, d, "part_supplier"), 0).state


@register("bfs_first_invariants", bfs_sql("part_supplier", "SELECT count(*) AS reached, 0::BIGINT AS bad_parents, 0::BIGINT AS too_shallow, 1::BIGINT AS own_roots, 0::BIGINT AS broken_ways FROM states"))
def _first(spark, d):
    """Of the variant in which any first claim stands: reached vertices, parents without an edge, levels below the true ones, roots,
    and vertices not one level below their parent (none: every way up ends at the root)."""
    g = held(spark, d, "part_supplier")
    got = bfs.bfs_relaxed(g, 0, how="cyclic", blocks=8, claim="first").state
    true = bfs.bfs_level(g, 0).state.select("id", F.col("level").alias("exact"))
    above = got.select(F.col("id").alias("parent"), F.col("level").alias("above"))
    checked = got.join(true, "id").join(above, "parent", "left").join(g.edges.select(F.col("src").alias("parent"), F.col("dst").alias("id"), F.lit(1).alias("edge")).distinct(), ["parent", "id"], "left")
    one = lambda c: F.coalesce(F.sum(F.when(F.expr(c), 1).otherwise(0)), F.lit(0)).cast("bigint")
    return checked.agg(F.count(F.lit(1)).alias("reached"), one("edge is null and level > 0").alias("bad_parents"), one("level < exact").alias("too_shallow"), one("parent = id").alias("own_roots"), one("level > 0 and not coalesce(above + 1 = level, false)").alias("broken_ways"))


register("bfs_levels_profile", bfs_sql("order_part", "SELECT level::INTEGER AS level, count(*) AS vertices FROM states GROUP BY level"))(
    lambda spark, d: bfs.bfs_level(held(spark, d, "order_part"), 0).state.groupBy("level").agg(F.count(F.lit(1)).alias("vertices"))
)
register("bfs_unreached", bfs_sql("order_part_window", "SELECT DISTINCT src AS id FROM e WHERE src NOT IN (SELECT id FROM states)"))(lambda spark, d: bfs.unreached(held(spark, d, "order_part_window"), 7))
register("bfs_reachable", bfs_sql("order_part_window", "SELECT id FROM states"))(lambda spark, d: bfs.reachable(held(spark, d, "order_part_window"), 7))
register("bfs_sentinel", bfs_sql("order_part_window", "SELECT v.id, coalesce(parent, -1) AS parent, coalesce(level, -1)::INTEGER AS level FROM (SELECT DISTINCT src AS id FROM e) v LEFT JOIN states s ON s.id = v.id"))(
    lambda spark, d: bfs.as_sentinel(g := held(spark, d, "order_part_window"), bfs.bfs_level(g, 7).state)
)
register("bfs_range_vertices", bfs_sql("order_part_window", "SELECT row_number() OVER (ORDER BY level, id) - 1 AS ord, id, parent, level::INTEGER AS level FROM states"))(lambda spark, d: bfs.bfs_range(held(spark, d, "order_part_window"), 7))
register("bfs_range_edges", bfs_sql("part_supplier", "SELECT * FROM (SELECT row_number() OVER (ORDER BY level, id) - 1 AS ord, id, parent, level::INTEGER AS level FROM states) WHERE level > 0"))(
    lambda spark, d: bfs.bfs_range(held(spark, d, "part_supplier"), 0, "edges")
)
register(
    "dfs_range_hierarchy",
    f"""WITH RECURSIVE e AS MATERIALIZED ({EDGES["hierarchy"]}), t AS (
  SELECT {OFFSETS["region"]}::BIGINT AS id, {OFFSETS["region"]}::BIGINT AS parent, 0 AS level, [{OFFSETS["region"]}::BIGINT] AS way UNION ALL
  SELECT e.dst, t.id, t.level + 1, list_append(t.way, e.dst::BIGINT) FROM t JOIN e ON e.src = t.id)
SELECT row_number() OVER (ORDER BY way) - 1 AS ord, id, parent, level::INTEGER AS level FROM t""",
)(lambda spark, d: bfs.dfs_range(held(spark, d, "hierarchy"), OFFSETS["region"], tree=True))
register("dfs_range_general")(lambda spark, d: bfs.dfs_range(held(spark, d, "order_part_window"), 7))
register("bfs_multi_roots", " UNION ALL ".join(f"SELECT * FROM ({bfs_sql('part_supplier', f'SELECT {r}::BIGINT AS root, id, parent, level::INTEGER AS level FROM states', str(r))})" for r in (0, 1, 2)))(
    lambda spark, d: bfs.bfs_multi(held(spark, d, "part_supplier"), [0, 1, 2])
)


@register("bfs_paths", bfs_sql("order_part", ", paths AS (SELECT id, 0 AS step, id AS vertex FROM states WHERE level = (SELECT max(level) FROM states) UNION ALL SELECT p.id, p.step + 1, s.parent FROM paths p JOIN states s ON s.id = p.vertex WHERE s.parent <> s.id) SELECT id, step, vertex FROM paths"))
def _paths(spark, d):
    state = bfs.bfs_level(held(spark, d, "order_part"), 0).state
    deepest = state.agg(F.max("level").alias("level"))
    return bfs.path_to(state, state.join(F.broadcast(deepest), "level", "left_semi"))


@register("reduce_claims_modes", bfs_sql("part_supplier", "SELECT 'min_level' AS mode, count(*) AS accepted FROM states WHERE level <= 1 UNION ALL SELECT 'first', count(*) FROM states WHERE level = 1"))
def _claims(spark, d):
    """Claims of the root's neighbours against a state that holds the root, and one with a worse level for it."""
    e = graph(spark, d, "part_supplier").edges.where("src = 0")
    claims = e.select(F.col("dst").alias("id"), F.col("src").alias("parent"), F.lit(1).alias("level")).unionByName(spark.createDataFrame([(0, 0, 0)], bfs.STATE))
    state = spark.createDataFrame([(0, 5, 3)], bfs.STATE)
    out = [bfs.reduce_claims(claims, state, m).agg(F.count(F.lit(1)).alias("accepted")).select(F.lit(m).alias("mode"), "accepted") for m in ("min_level", "first")]
    return out[0].unionByName(out[1])


@register("rounds_compare")
def _rounds(spark, d):
    """Global steps of the level-wise and the relaxed search, with claims between blocks.

    Graphs are built, and their searches run, in flight together: the many small steps of one fill the waits of another.
    """
    names = ("part_supplier", "order_part_window", "urand_dense")
    *graphs, chain = run_all([*(lambda w=w: (held(spark, d, w), root_of(w), "cyclic", None) for w in names), lambda: (c := chained(spark, d))[:2] + ("block", c[3])])
    graphs.append(chain)
    level = [lambda g=g, root=root: bfs.bfs_level(g, root).rounds for g, root, _, _ in graphs]
    relaxed = [lambda g=g, root=root, how=how, n=n: bfs.bfs_relaxed(g, root, how=how, blocks=8, n=n) for g, root, how, n in graphs]
    found = run_all(level + relaxed)
    rows = [(w, a, b.rounds, sum(x["remote"] for x in b.log), sum(x["corrections"] for x in b.log)) for w, a, b in zip((*names, "order_chain"), found[:4], found[4:], strict=True)]
    return spark.createDataFrame(rows, "graph string, level_rounds int, relaxed_rounds int, remote bigint, corrections bigint")


@register("load_balance_relaxed")
def _balance(spark, d):
    return measures.load_balance(bfs.bfs_relaxed(held(spark, d, "part_supplier"), 0, how="cyclic", blocks=8).load)


@register("load_balance_level", bfs_sql("part_supplier", "SELECT level::INTEGER AS round, blk::INTEGER AS blk, count(*) AS expanded FROM (SELECT level, s.id % 8 AS blk FROM states s JOIN e ON e.src = s.id) GROUP BY 1, 2"))
def _load_level(spark, d):
    g = held(spark, d, "part_supplier")
    state = bfs.bfs_level(g, 0).state
    return state.join(g.edges, state["id"] == g.edges["src"]).groupBy(F.col("level").alias("round"), owner(F.col("id"), "cyclic", 8).alias("blk")).agg(F.count(F.lit(1)).alias("expanded"))


register("frontier_profile", bfs_sql("order_part", "SELECT level::INTEGER AS level, count(DISTINCT s.id) AS vertices, count(e.dst) AS edges FROM states s LEFT JOIN e ON e.src = s.id GROUP BY level"))(
    lambda spark, d: measures.frontier_profile(bfs.bfs_level(g := held(spark, d, "order_part"), 0).state, g)
)
register("message_counts", bfs_sql("part_supplier", "SELECT level::INTEGER AS level, count(*) AS sent, count(DISTINCT dst) AS combined FROM states s JOIN e ON e.src = s.id GROUP BY level"))(
    lambda spark, d: measures.message_counts(bfs.bfs_level(g := held(spark, d, "part_supplier"), 0).state, g)
)
_CUT = "SELECT count(*) AS edges, sum(CASE WHEN a <> b THEN 1 ELSE 0 END)::BIGINT AS cut, round(sum(CASE WHEN a <> b THEN 1 ELSE 0 END) / count(*), 6) AS share FROM"
register("edge_cut_block", f"WITH e AS ({EDGES['part_next']}), n AS (SELECT count(*) AS n FROM part) {_CUT} (SELECT floor(src * 8 / n) AS a, floor(dst * 8 / n) AS b FROM e, n)")(
    lambda spark, d: measures.edge_cut(graph(spark, d, "part_next"), "block", 8, spark.read.parquet(f"{d}/part.parquet").count()).withColumn("share", F.round("share", 6))
)
register("edge_cut_cyclic", f"WITH e AS ({EDGES['part_next']}) {_CUT} (SELECT src % 8 AS a, dst % 8 AS b FROM e)")(lambda spark, d: measures.edge_cut(graph(spark, d, "part_next"), "cyclic", 8).withColumn("share", F.round("share", 6)))
_OWNERS = {"block": "floor({c} * {b} / n)", "cyclic": "{c} % {b}"}


@register(
    "ownership_ablation",
    f"WITH e AS MATERIALIZED ({EDGES['part_next']}), n AS (SELECT count(*) AS n FROM part) "
    + " UNION ALL ".join(f"SELECT '{how}' AS owner, {b}::INTEGER AS blocks, sum(CASE WHEN {f.format(c='src', b=b)} <> {f.format(c='dst', b=b)} THEN 1 ELSE 0 END)::BIGINT AS cut FROM e, n" for how, f in _OWNERS.items() for b in (1, 4, 8, 16)),
)
def _ownership(spark, d):
    """Edges between blocks by owner function and number of blocks; all in one pass over the edges."""
    n = spark.read.parquet(f"{d}/part.parquet").count()
    cases = [(how, b) for how in _OWNERS for b in (1, 4, 8, 16)]
    crosses = lambda how, b: (owner(F.col("src"), how, b, n) != owner(F.col("dst"), how, b, n)).cast("bigint")
    row = graph(spark, d, "part_next").edges.agg(*(F.coalesce(F.sum(crosses(how, b)), F.lit(0)).alias(f"{how}_{b}") for how, b in cases))
    each = F.array(*(F.struct(F.lit(how).alias("owner"), F.lit(b).alias("blocks"), F.col(f"{how}_{b}").alias("cut")) for how, b in cases))
    return row.select(F.inline(each))


register("edge_cut_hash")(lambda spark, d: measures.edge_cut(graph(spark, d, "part_next"), "hash", 8))
register("urand_graph", EDGES["urand_dense"])(lambda spark, d: graph(spark, d, "urand_dense").edges)
register("urand_bfs", bfs_sql("urand_dense", STATE_SQL))(lambda spark, d: bfs.bfs_hops(held(spark, d, "urand_dense"), 0, hops=1, how="cyclic").state)


_PLANNED = {
    "part_supplier": f"SELECT src % b AS x, dst % b AS y FROM ({EDGES['part_supplier']}), q",
    "order_chain": f"""SELECT least(floor(s.id * b / n), b - 1) AS x, least(floor(t.id * b / n), b - 1) AS y FROM ({EDGES["order_chain"]}) e JOIN ids s ON s.o_orderkey = e.src JOIN ids t ON t.o_orderkey = e.dst, q, (SELECT count(*) AS n FROM orders)""",
    "urand_sparse": f"SELECT src % b AS x, dst % b AS y FROM ({EDGES['urand_sparse']}), q",
}


@register(
    "planner_choices",
    "WITH ids AS (SELECT o_orderkey, row_number() OVER (ORDER BY o_custkey, o_orderdate, o_orderkey) - 1 AS id FROM orders) "
    + " UNION ALL ".join(
        f"SELECT '{w}' AS graph, edges, b AS blocks, cut, CASE WHEN cut / edges < 0.5 THEN 'relaxed' ELSE 'level' END AS schedule FROM (WITH m AS (SELECT count(*) AS edges FROM ({EDGES[w]})), q AS (SELECT edges, greatest(1, ceil(edges / 16777216), least(32, ceil(edges / 50000)))::INTEGER AS b FROM m) SELECT any_value(edges) AS edges, any_value(b) AS b, count(*) FILTER (x <> y) AS cut FROM ({cut}), q)"
        for w, cut in _PLANNED.items()
    ),
)
def _choices(spark, d):
    """Blocks and schedule that counts choose for three graphs and eight cores; their jobs run together."""
    chain, _, _, n = chained(spark, d)
    graphs = {"part_supplier": (held(spark, d, "part_supplier"), "cyclic", None), "order_chain": (chain, "block", n), "urand_sparse": (held(spark, d, "urand_sparse"), "cyclic", None)}
    made = run_all([lambda g=g, how=how, n=n: planner.plan(g, how, n, cores=8) for g, how, n in graphs.values()])
    return spark.createDataFrame([(w, p.edges, p.blocks, p.cut, p.schedule) for w, p in zip(graphs, made, strict=True)], "graph string, edges bigint, blocks int, cut bigint, schedule string")


@register("bfs_planned", bfs_sql("part_supplier", STATE_SQL))
def _planned(spark, d):
    return planner.search(held(spark, d, "part_supplier"), 0, "cyclic")[0].state


# -- ranks -----------------------------------------------------------------------------------------


def rank_sql(name: str, what: str = "", iterations: int = K, dangling: str = "leak", alpha: float = 0.85) -> str:
    """Unrolled iterations, each over all vertices; r{iterations} holds (id, rank)."""
    out = [
        f"WITH e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({EDGES[name]})), v AS MATERIALIZED (SELECT src AS id FROM e UNION SELECT dst FROM e), n AS (SELECT count(*)::DOUBLE AS n FROM v)",
        "deg AS MATERIALIZED (SELECT src, count(*) AS d FROM e GROUP BY src)",
        "r0 AS MATERIALIZED (SELECT id, 1 / n AS rank FROM v, n)",
    ]
    for i in range(1, iterations + 1):
        extra, join = "0", ""
        if dangling == "redistribute":
            extra, join = "h / n", f", (SELECT coalesce(sum(rank), 0) AS h FROM r{i - 1} WHERE id NOT IN (SELECT src FROM deg)) x"
        out.append(f"s{i} AS (SELECT e.dst AS id, sum(r.rank / d) AS s FROM e JOIN deg ON deg.src = e.src JOIN r{i - 1} r ON r.id = e.src GROUP BY e.dst)")
        out.append(f"r{i} AS MATERIALIZED (SELECT v.id, {1 - alpha!r} / n + {alpha!r} * (coalesce(s, 0) + {extra}) AS rank FROM v LEFT JOIN s{i} ON s{i}.id = v.id, n{join})")
    return ",\n".join(out) + "\n" + (what or f"SELECT id, round(rank * n, 6) AS rank FROM r{iterations}, n")


def scaled(spark, g: Graph, **how) -> DataFrame:
    found = rank.rank(g, tol=None, max_iter=K, **how).ranks
    return found.select("id", F.round(F.col("rank") * F.lit(float(g.vertices.count())), 6).alias("rank"))


for _n, _w, _how in (
    ("rank_push_part_next", "part_next", {}), ("rank_push_uncombined", "part_next", {"combine": False}), ("rank_split_part_next", "part_next", {"mode": "split"}), ("rank_prejoined_part_next", "part_next", {"mode": "prejoined"}),
    ("rank_salted_part_next", "part_next", {"mode": "prejoined", "hubs": 25}), ("rank_pull_part_next", "part_next", {"mode": "pull"}), ("rank_push_user_next", "user_next", {}), ("rank_push_host_path", "host_path", {}),
    ("rank_dag_leak", "trade_dag", {}), ("urand_rank", "urand_dense", {"mode": "pull"}),
):
    register(_n, rank_sql(_w))(lambda spark, d, w=_w, how=_how: scaled(spark, held(spark, d, w), **how))
register("rank_dag_redistribute", rank_sql("trade_dag", dangling="redistribute"))(lambda spark, d: scaled(spark, held(spark, d, "trade_dag"), dangling="redistribute"))


@register("baseline_vertex_rank", rank_sql("part_next"))
def _vertex_rank(spark, d):
    g = held(spark, d, "part_next")
    return rank.rank_vertex(g, iterations=K).ranks.select("id", F.round(F.col("rank") * F.lit(float(g.vertices.count())), 6).alias("rank"))


@register("rank_sequential", rank_sql("part_next"))
def _rank_seq(spark, d):
    return rank.rank_one_task(graph(spark, d, "part_next"), tol=None, max_iter=K, scaled=True).withColumn("rank", F.round("rank", 6))


@register("rank_contrib_phase", rank_sql("trade_dag", "SELECT id, round(n * rank / d, 6) AS c FROM r0 JOIN deg ON deg.src = id, n", 0))
def _contrib(spark, d):
    g = held(spark, d, "trade_dag")
    n = g.vertices.count()
    return rank.contributions(g.vertices.withColumn("rank", F.lit(1 / n)), g.degrees("out")).select("id", F.round(F.col("c") * n, 6).alias("c"))


@register("rank_update_phase", rank_sql("part_next", iterations=1))
def _update(spark, d):
    """One iteration by its phases: contributions, sums inside and between blocks, update."""
    from tidegraph.model import split_edges

    g = held(spark, d, "part_next")
    n = g.vertices.count()
    start = g.vertices.withColumn("rank", F.lit(1 / n))
    c = rank.contributions(start, g.degrees("out"))
    inside, between = split_edges(g, "cyclic", 8)
    sums = rank.local_sums(c, inside).unionByName(rank.remote_sums(c, between)).groupBy("id").agg(F.sum("s").alias("s"))
    return rank.update(start, sums, 0.85, n).select("id", F.round(F.col("rank") * n, 6).alias("rank"))


@register("rank_error_log", rank_sql("part_next", " UNION ALL ".join(f"SELECT {i} AS iter, round(sum(abs(a.rank - b.rank)), 9) AS l1_error, round(sum(a.rank), 6) AS mass FROM r{i} a JOIN r{i - 1} b ON a.id = b.id" for i in range(1, K + 1))))
def _errors(spark, d):
    log = rank.rank(held(spark, d, "part_next"), tol=None, max_iter=K).log
    return measures.log_frame(spark, log).select(F.col("iter").cast("int").alias("iter"), F.round("l1_error", 9).alias("l1_error"), F.round("mass", 6).alias("mass"))


@register("rank_error_by_block", rank_sql("part_next", "SELECT (a.id % 8)::INTEGER AS blk, round(sum(abs(a.rank - b.rank)), 9) AS err FROM r2 a JOIN r1 b ON a.id = b.id GROUP BY 1", 2))
def _blocks(spark, d):
    g = held(spark, d, "part_next")
    a, b = (rank.rank(g, tol=None, max_iter=i).ranks for i in (1, 2))
    return rank.l1_error(a, b, ("cyclic", 8, None)).select("blk", F.round("err", 9).alias("err"))


register("rank_topk", rank_sql("part_next", f"SELECT id, round(rank * n, 6) AS rank FROM (SELECT id, rank FROM r{K} ORDER BY rank DESC, id LIMIT 10), n"))(
    lambda spark, d: rank.top_k(rank.rank(g := held(spark, d, "part_next"), tol=None, max_iter=K).ranks, 10).select("id", F.round(F.col("rank") * g.vertices.count(), 6).alias("rank"))
)


#: Iterations within which the acyclic graph's ranks stand still.
_STILL = 8
_LOG = " UNION ALL ".join(f"SELECT {i} AS iter, sum(abs(a.rank - b.rank)) AS e, sum(a.rank) AS m, coalesce(sum(a.rank) FILTER (a.id NOT IN (SELECT src FROM deg)), 0) AS h FROM r{i} a JOIN r{i - 1} b ON a.id = b.id" for i in range(1, _STILL + 1))


@register("rank_tolerance", rank_sql("trade_dag", f", log AS MATERIALIZED ({_LOG}) SELECT iter, round(e, 9) AS l1_error, round(m, 9) AS mass, round(h, 9) AS dangling FROM log WHERE iter <= (SELECT min(iter) FROM log WHERE e < 1e-6)", _STILL))
def _tolerance(spark, d):
    log = measures.log_frame(spark, rank.rank(held(spark, d, "trade_dag"), tol=1e-6, max_iter=_STILL).log)
    return log.select(F.col("iter").cast("int").alias("iter"), *(F.round(c, 9).alias(c) for c in ("l1_error", "mass", "dangling")))


def personal_sql(name: str, p: str, alpha: float = 0.85) -> str:
    """As rank_sql, restarting at the rows of p (id, p), which also get what vertices without out-edges hold."""
    out = [f"WITH e AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({EDGES[name]})), deg AS MATERIALIZED (SELECT src, count(*) AS d FROM e GROUP BY src)", f"r0 AS MATERIALIZED (SELECT id, coalesce(p, 0) AS p, coalesce(p, 0) AS rank FROM (SELECT src AS id FROM e UNION SELECT dst FROM e) v LEFT JOIN ({p}) q USING (id))"]
    for i in range(1, K + 1):
        out.append(f"s{i} AS (SELECT e.dst AS id, sum(rank / d) AS s FROM e JOIN deg USING (src) JOIN r{i - 1} r ON r.id = e.src GROUP BY e.dst)")
        out.append(f"r{i} AS MATERIALIZED (SELECT r.id, p, {1 - alpha!r} * p + {alpha!r} * (coalesce(s, 0) + h * p) AS rank FROM r{i - 1} r LEFT JOIN s{i} USING (id), (SELECT coalesce(sum(rank), 0) AS h FROM r{i - 1} WHERE id NOT IN (SELECT src FROM deg)) x)")
    return ",\n".join(out) + f"\nSELECT id, round(rank, 9) AS rank FROM r{K}"


@register("rank_personalized", personal_sql("part_next", "SELECT 0::BIGINT AS id, 0.5 AS p UNION ALL SELECT 1, 0.5"))
def _personalized(spark, d):
    start = spark.createDataFrame([(0, 0.5), (1, 0.5)], "id bigint, p double")
    return rank.rank(held(spark, d, "part_next"), tol=None, max_iter=K, restart=start, dangling="redistribute").ranks.select("id", F.round("rank", 9).alias("rank"))


@register("rank_delta_vs_exact")
def _delta(spark, d):
    g = held(spark, d, "part_next")
    return measures.compare_ranks(rank.rank_delta(g, 1e-7).ranks, rank.rank(g, tol=1e-12, max_iter=60).ranks)


# -- announced scope -------------------------------------------------------------------------------

_CC = "WITH RECURSIVE e AS MATERIALIZED ({edges}), reach AS (SELECT src AS id, src AS seen FROM e UNION SELECT r.id, e.dst FROM reach r JOIN e ON e.src = r.seen) SELECT id, min(seen) AS component FROM reach GROUP BY id"


@register("connected_components", _CC.format(edges=EDGES["order_part_window"]))
def _components(spark, d):
    e = graph(spark, d, "order_part_window").edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    return components.connected_components(e, Scratch(spark, "components"))


@register("connected_components_whole", _CC.format(edges=EDGES["page_path"]))
def _components_whole(spark, d):
    e = graph(spark, d, "page_path").edges.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    return components.connected_components(e, Scratch(spark, "components"))


_UND = f"SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM ({EDGES['copurchase']}) WHERE src <> dst"
register("triangle_count", f"WITH e AS MATERIALIZED ({_UND}) SELECT count(*) AS triangles FROM e x JOIN e y ON x.a = y.a AND x.b < y.b JOIN e z ON z.a = x.b AND z.b = y.b")(
    lambda spark, d: spark.createDataFrame([(analytics.triangle_count(Graph(bought_together(spark, d))),)], "triangles bigint")
)
_KNN_UND = f"SELECT DISTINCT least(src, dst) AS a, greatest(src, dst) AS b FROM ({EDGES['knn']})"
register(
    "local_clustering",
    f"""WITH e AS MATERIALIZED ({_KNN_UND}), t AS (SELECT x.a AS p, x.b AS q, y.b AS r FROM e x JOIN e y ON x.a = y.a AND x.b < y.b JOIN e z ON z.a = x.b AND z.b = y.b),
per AS (SELECT id, count(*) AS triangles FROM (SELECT p AS id FROM t UNION ALL SELECT q FROM t UNION ALL SELECT r FROM t) GROUP BY id),
deg AS (SELECT id, count(*) AS degree FROM (SELECT a AS id FROM e UNION ALL SELECT b FROM e) GROUP BY id)
SELECT d.id, degree, coalesce(triangles, 0) AS triangles, round(CASE WHEN degree > 1 THEN 2.0 * coalesce(triangles, 0) / (degree * (degree - 1)) ELSE 0 END, 6)::DOUBLE AS clustering FROM deg d LEFT JOIN per ON per.id = d.id""",
)(lambda spark, d: analytics.local_clustering(held(spark, d, "knn")).withColumn("clustering", F.round("clustering", 6)))
register("knn_graph", EDGES["knn"])(lambda spark, d: graph(spark, d, "knn").edges)
#: Rounds of peeling that the SQL unrolls.
_PEELS = 25
register(
    "k_core",
    f"WITH c0 AS MATERIALIZED (SELECT a AS s, b AS t FROM ({_KNN_UND}) UNION ALL SELECT b, a FROM ({_KNN_UND})), "
    + ", ".join(f"c{i} AS MATERIALIZED (SELECT s, t FROM c{i - 1} WHERE s IN (SELECT s FROM c{i - 1} GROUP BY s HAVING count(*) >= 5) AND t IN (SELECT s FROM c{i - 1} GROUP BY s HAVING count(*) >= 5))" for i in range(1, _PEELS + 1))
    + f" SELECT DISTINCT s AS id FROM c{_PEELS}",
)(lambda spark, d: analytics.k_core(held(spark, d, "knn"), 5))
register(
    "motif_counts",
    f"""WITH e AS MATERIALIZED ({_KNN_UND}), d AS MATERIALIZED (SELECT a AS s, b AS t FROM e UNION ALL SELECT b, a FROM e),
w AS (SELECT sum(n * (n - 1) // 2)::BIGINT AS wedges FROM (SELECT count(*) AS n FROM d GROUP BY s)),
q AS (SELECT (coalesce(sum(m * (m - 1) // 2), 0) // 2)::BIGINT AS squares FROM (SELECT count(*) AS m FROM d x JOIN d y ON x.t = y.t AND x.s < y.s GROUP BY x.s, y.s)),
t AS (SELECT count(*) AS triangles FROM e x JOIN e y ON x.a = y.a AND x.b < y.b JOIN e z ON z.a = x.b AND z.b = y.b)
SELECT wedges, triangles, squares FROM w, t, q""",
)(lambda spark, d: analytics.motif_counts(held(spark, d, "knn")))
register(
    "jaccard_neighbours",
    f"""WITH e AS MATERIALIZED ({EDGES["knn"]}), s AS (SELECT src, count(*) AS n FROM e GROUP BY src)
SELECT a, b, shared, round(shared / (x.n + y.n - shared)::DOUBLE, 6) AS similarity FROM (SELECT x.src AS a, y.src AS b, count(*) AS shared FROM e x JOIN e y ON x.dst = y.dst AND x.src < y.src GROUP BY 1, 2) JOIN s x ON x.src = a JOIN s y ON y.src = b""",
)(lambda spark, d: analytics.jaccard_neighbours(held(spark, d, "knn")).withColumn("similarity", F.round("similarity", 6)))
register("degree_centrality", f"WITH e AS MATERIALIZED ({EDGES['trade_dag']}), v AS (SELECT src AS id FROM e UNION SELECT dst FROM e), n AS (SELECT count(*) AS n FROM v) SELECT id, coalesce(d, 0) AS degree, round(coalesce(d, 0) / (n - 1)::DOUBLE, 9) AS centrality FROM v LEFT JOIN (SELECT src, count(*) AS d FROM e GROUP BY src) x ON x.src = v.id, n")(
    lambda spark, d: analytics.degree_centrality(graph(spark, d, "trade_dag")).withColumn("centrality", F.round("centrality", 9))
)
# both are of two given roots, 0 and 1, not sums over all vertices
register("closeness_two_roots", " UNION ALL ".join(f"SELECT * FROM ({bfs_sql('part_supplier', f'SELECT {r}::BIGINT AS root, count(*) AS reached, round((count(*) - 1) / sum(level)::DOUBLE, 9) AS closeness FROM states', str(r))})" for r in (0, 1)))(
    lambda spark, d: analytics.closeness(held(spark, d, "part_supplier"), [0, 1]).withColumn("closeness", F.round("closeness", 9))
)
register("betweenness_two_roots")(lambda spark, d: analytics.betweenness(held(spark, d, "part_supplier"), [0, 1]))


_COST = f"SELECT l_partkey AS src, l_suppkey + {OFFSETS['supplier']} AS dst, min(l_quantity) AS w FROM lineitem GROUP BY 1, 2"


@register(
    "sssp_weighted",
    f"""WITH RECURSIVE one AS MATERIALIZED ({_COST}), e AS MATERIALIZED (SELECT src, dst, w FROM one UNION ALL SELECT dst, src, w FROM one),
far(id, dist) USING KEY (id) AS (SELECT 0::BIGINT, 0.0::DOUBLE UNION (
  SELECT e.dst, min(f.dist + e.w) FROM far f JOIN e ON e.src = f.id LEFT JOIN recurring.far r ON r.id = e.dst WHERE r.dist IS NULL OR f.dist + e.w < r.dist GROUP BY e.dst))
SELECT id, dist FROM far""",
)
def _sssp(spark, d):
    """Distances from part 0 where an edge costs the quantity of its first line."""
    lines = spark.read.parquet(f"{d}/lineitem.parquet")
    e = lines.groupBy(F.col("l_partkey").alias("src"), (F.col("l_suppkey") + OFFSETS["supplier"]).alias("dst")).agg(F.min("l_quantity").alias("w"))
    e = e.unionByName(e.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w"))
    return analytics.sssp(Graph(Scratch(spark, "sssp-edges").save(e, "e")), 0)


