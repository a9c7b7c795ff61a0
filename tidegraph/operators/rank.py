"""Random-surfer rank: r'(u) = (1 - alpha) / n + alpha * sum of r(v) / outdegree(v) over edges v -> u.

All modes compute the same Jacobi iteration; old and new ranks never mix, as an iteration reads one
written table and writes the next. Each iteration is one job: error, mass and the rank held by
vertices without out-edges are observed while the table is written.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from tidegraph.functions.adaptive import choose_blocks, small
from tidegraph.model import Graph, owner
from tidegraph.operators.oneprocess import Spool, in_one_task
from tidegraph.plans.scratch import Scratch, joined_in_place

MODES = ("push", "pull", "split", "prejoined")
DANGLING = ("leak", "redistribute", "self")


@dataclass
class Ranks:
    """ranks: id, rank. log: a dict an iteration (iter, l1_error, mass, dangling, seconds)."""

    ranks: DataFrame
    log: list[dict] = field(default_factory=list)


def rank_seq(src: np.ndarray, dst: np.ndarray, ids: np.ndarray, alpha: float = 0.85, tol: float | None = 1e-6, max_iter: int = 100, dangling: str = "leak", most: int = 50_000_000) -> tuple[np.ndarray, list[float]]:
    """The iteration over arrays in one process: ranks in order of the ascending ids, and the errors; refuses more than `most` edges."""
    if len(src) > most:
        raise ValueError(f"{len(src)} edges are too many for one process; use a distributed rank")
    n = len(ids)
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    return _iterate(np.bincount(s, minlength=n), lambda share: np.bincount(d, weights=share[s], minlength=n), alpha, tol, max_iter, dangling)


def _iterate(degree: np.ndarray, gain: Callable[[np.ndarray], np.ndarray], alpha: float, tol: float | None, max_iter: int, dangling: str) -> tuple[np.ndarray, list[float]]:
    """gain: what vertices get if each of their in-edges brings its source's share."""
    n = len(degree)
    lone = degree == 0
    rank, errors = np.full(n, 1 / max(n, 1)), []
    for _ in range(max_iter):
        gained = gain(np.where(lone, 0.0, rank / np.maximum(degree, 1)))
        if dangling == "redistribute":
            gained += rank[lone].sum() / n
        elif dangling == "self":
            gained[lone] += rank[lone]
        new = (1 - alpha) / max(n, 1) + alpha * gained
        errors.append(float(np.abs(new - rank).sum()))
        rank = new
        if tol is not None and errors[-1] < tol:
            break
    return rank, errors


def rank_one_task(g: Graph, alpha: float = 0.85, tol: float | None = 1e-6, max_iter: int = 100, dangling: str = "leak", scaled: bool = False) -> DataFrame:
    """id, rank as by rank_seq, in one task over an edge table of any size: the vertices are in its memory, the edges in a
    file that each iteration reads. scaled: ranks times the number of vertices."""

    def one(held: Spool) -> tuple[np.ndarray, np.ndarray]:
        got, _ = _iterate(held.degrees(), held.gained, alpha, tol, max_iter, dangling)
        return held.ids, got * len(got) if scaled else got

    return in_one_task(g.edges, one, "id bigint, rank double")


# -- the three phases ------------------------------------------------------------------------------


def contributions(ranks: DataFrame, degrees: DataFrame) -> DataFrame:
    """id, c: rank over out-degree, for vertices with out-edges. degrees: id, degree."""
    return ranks.join(degrees.where("degree > 0"), "id").select("id", (F.col("rank") / F.col("degree")).alias("c"))


def local_sums(contrib: DataFrame, inside: DataFrame) -> DataFrame:
    """id, s: what edges inside blocks bring, summed before anything leaves a block."""
    return contrib.join(inside, contrib["id"] == inside["src"]).groupBy(F.col("dst").alias("id")).agg(F.sum("c").alias("s"))


def remote_sums(contrib: DataFrame, between: DataFrame) -> DataFrame:
    """id, s: what edges between blocks bring; partial sums by destination go to the owner."""
    return local_sums(contrib, between)


def update(ranks: DataFrame, sums: DataFrame, alpha: float, n: int, extra: float = 0.0) -> DataFrame:
    """id, rank, old: every vertex, also those that nothing points at. extra: what each gets besides."""
    new = F.lit((1 - alpha) / n) + F.lit(alpha) * (F.coalesce("s", F.lit(0.0)) + F.lit(extra))
    return ranks.join(sums, "id", "left").select("id", new.alias("rank"), F.col("rank").alias("old"))


def l1_error(old: DataFrame, new: DataFrame, blocks: tuple[str, int, int | None] | None = None) -> DataFrame:
    """err: the sum of absolute differences; with blocks (how, number, n), blk and err for each block."""
    both = old.select("id", F.col("rank").alias("old")).join(new, "id").select("id", F.abs(F.col("rank") - F.col("old")).alias("e"))
    if blocks:
        how, count, n = blocks
        return both.groupBy(owner(F.col("id"), how, count, n).alias("blk")).agg(F.sum("e").alias("err"))
    return both.agg(F.sum("e").alias("err"))


def rank(
    g: Graph, alpha: float = 0.85, tol: float | None = 1e-6, max_iter: int = 100, mode: str = "push", combine: bool = True, hubs: int | None = None,
    dangling: str = "leak", how: str = "hash", blocks: int | None = None, restart: DataFrame | None = None, weight: str | None = None,
) -> Ranks:
    """Ranks of all vertices.

    mode: push sends along out-edges; pull gathers by in-edges, broadcasting contributions while few; prejoined stores
    1 / degree on the edges, so an iteration divides nothing. Edges lie bucketed by source and ranks by vertex, in buckets as
    many as a shuffle's partitions, so an iteration moves partial sums by destination and nothing else. split buckets both by
    block: edges inside a block are summed in place, and of edges between blocks one partial sum for each block and target
    moves. combine=False moves one row an edge. hubs: vertices of more out-edges than this have them spread over all tasks,
    and their ranks broadcast while few, so no bucket holds a hub's whole list. how="block" needs dense ids.
    restart (id, p) replaces the uniform restart; weight names an edge column.
    """
    if not 0 <= alpha < 1:
        raise ValueError("alpha must lie in [0, 1)")
    if mode not in MODES or dangling not in DANGLING:
        raise ValueError(f"mode is one of {MODES}, dangling one of {DANGLING}")
    if hubs is not None and mode not in ("push", "prejoined"):
        raise ValueError("hubs are spread in the modes push and prejoined")
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "rank")
    split = mode == "split"
    key = "blk" if split else "id"
    w = F.col(weight) if weight else F.lit(1.0)
    edges = g.edges.select("src", "dst", w.cast("double").alias("share"))
    degree = edges.groupBy("src").agg(F.sum("share").alias("d"), F.count(F.lit(1)).alias("out")).where("d > 0")
    n = g.vertices.count()
    start = F.lit(1 / max(n, 1)) if restart is None else F.coalesce("p", F.lit(0.0))
    ranks = g.vertices.join(degree.withColumnRenamed("src", "id"), "id", "left")
    ranks = ranks if restart is None else ranks.join(restart, "id", "left")
    buckets = scratch.buckets(g.edges)
    if split:
        m = degree.agg(F.coalesce(F.sum("out"), F.lit(0))).first()[0]
        blocks = blocks or choose_blocks(m, spark.sparkContext.defaultParallelism)
        buckets = min(blocks, 1 << 13)
        own = lambda c: owner(F.col(c), how, blocks, n)
        ranks = ranks.withColumn("blk", own("id"))
        cut = edges.withColumn("blk", own("src")).withColumn("dblk", own("dst"))
        inside = scratch.save_bucketed(cut.where("blk = dblk").drop("dblk"), "inside", "blk", n=buckets, sort=("src",))
        between = scratch.save_bucketed(cut.where("blk <> dblk"), "between", "blk", n=buckets, sort=("src",))
    else:
        if mode == "prejoined":
            edges = edges.join(degree.select("src", "d"), "src").select("src", "dst", (F.col("share") / F.col("d")).alias("share"))
        spread = None
        if hubs is not None:
            # fewer than edges / hubs rows
            wide = scratch.save(degree.where(F.col("out") > hubs).select("src"), "hubs")
            rows = wide.count()
            if rows:
                wide = small(wide, rows)
                spread = scratch.save(edges.join(wide, "src", "left_semi"), "hub-edges")
                edges = edges.join(wide, "src", "left_anti")
        edges = scratch.save_bucketed(edges, "edges", "dst" if mode == "pull" else "src", n=buckets)
    kept = ["id", "lone", "d", *(["blk"] if split else []), *(["p"] if restart is not None else [])]
    ranks = ranks.withColumns({"lone": F.col("d").isNull(), "d": F.coalesce("d", F.lit(1.0)), "rank": start, **({"p": F.coalesce("p", F.lit(0.0))} if restart is not None else {})})
    ranks = scratch.save_bucketed(ranks.select(*kept, "rank"), "0", key, n=buckets)
    held = ranks.where("lone").agg(F.coalesce(F.sum("rank"), F.lit(0.0))).first()[0]
    placed = split or buckets == int(spark.conf.get("spark.sql.shuffle.partitions"))
    log: list[dict] = []

    def gained() -> DataFrame:
        """ranks with s: what each vertex gets, null if nothing."""
        # the contribution phase: rank over out-degree at the vertex, unless the edges hold it
        share = F.col("rank") if mode == "prejoined" else F.col("rank") / F.col("d")
        source = ranks.where("not lone").select(F.col("id").alias("src"), share.alias("c"), *(["blk"] if split else []))
        brought = F.sum(F.col("c") * F.col("share")).alias("s")
        if split:
            near = inside.join(source, ["blk", "src"]).groupBy("blk", F.col("dst").alias("id")).agg(brought)
            far = between.join(source, ["blk", "src"]).groupBy("blk", "dblk", "dst").agg(brought) if combine else between.join(source, ["blk", "src"]).withColumn("s", F.col("c") * F.col("share"))
            far = far.select(F.col("dblk").alias("blk"), F.col("dst").alias("id"), "s").repartition(buckets, "blk").groupBy("blk", "id").agg(F.sum("s").alias("away"))
            both = ranks.join(near, ["blk", "id"], "left").join(far, ["blk", "id"], "left")  # a union would forget where rows are
            return both.withColumn("s", F.coalesce("s", F.lit(0.0)) + F.coalesce("away", F.lit(0.0)))
        sent = edges.join(small(source, n, 100_000) if mode == "pull" else source, "src").select("dst", "c", "share")
        if spread is not None:
            sent = sent.unionByName(spread.join(small(source.join(wide, "src", "left_semi"), rows), "src").select("dst", "c", "share"))
        if not combine:
            sent = sent.repartition("dst")
        return ranks.join(sent.groupBy(F.col("dst").alias("id")).agg(brought), "id", "left")

    for i in range(1, max_iter + 1):
        began = time.time()
        s = F.coalesce("s", F.lit(0.0))
        base = F.lit((1 - alpha) / max(n, 1)) if restart is None else F.lit(1 - alpha) * F.col("p")
        if dangling == "redistribute":
            s = s + (F.lit(held / max(n, 1)) if restart is None else F.lit(held) * F.col("p"))
        elif dangling == "self":
            s = s + F.when(F.col("lone"), F.col("rank")).otherwise(0.0)
        new = gained().withColumn("new", base + F.lit(alpha) * s)
        seen = Observation(f"rank-{i}")
        new = new.observe(
            seen, F.coalesce(F.sum(F.abs(F.col("new") - F.col("rank"))), F.lit(0.0)).alias("err"), F.coalesce(F.sum("new"), F.lit(0.0)).alias("mass"), F.coalesce(F.sum(F.when(F.col("lone"), F.col("new"))), F.lit(0.0)).alias("held")
        )
        with joined_in_place(spark):
            ranks = scratch.save_bucketed(new.select(*kept, F.col("new").alias("rank")), str(i), key, n=buckets, placed=placed)
        scratch.drop_table(str(i - 1))
        got = seen.get
        held = got["held"]
        log.append({"iter": i, "l1_error": got["err"], "mass": got["mass"], "dangling": held, "seconds": time.time() - began})
        if tol is not None and got["err"] < tol:
            break
    # what a lazy result reads must not hang on a table's name
    last = spark.read.schema(ranks.schema).parquet(scratch.path(str(len(log))))
    scratch.keep_only(str(len(log)))
    return Ranks(last.select("id", "rank"), log)


def rank_vertex(g: Graph, alpha: float = 0.85, iterations: int = 10) -> Ranks:
    """Vertex-centric: every vertex tells its out-neighbours its share, then adds up what it was told."""
    from tidegraph.operators.bfs import superstep

    spark = g.edges.sparkSession
    scratch = Scratch(spark, "rank-vertex")
    degree = g.degrees("out")
    n = g.vertices.count()
    start = degree.select("id", "degree", F.lit(1 / n).alias("rank"), F.lit(True).alias("active"))
    edges = scratch.save(g.edges.select("src", "dst"), "edges")

    def tell(active: DataFrame) -> DataFrame:
        return active.where("degree > 0").join(edges, active["id"] == edges["src"]).select(F.col("dst").alias("id"), (F.col("rank") / F.col("degree")).alias("c"))

    def take(state: DataFrame, told: DataFrame) -> DataFrame:
        new = F.lit((1 - alpha) / n) + F.lit(alpha) * F.coalesce("s", F.lit(0.0))
        return state.join(told, "id", "left").select("id", "degree", new.alias("rank"), "active")

    state, log = superstep(start, tell, lambda m: m.agg(F.sum("c").alias("s")), take, lambda active, r: r >= iterations, scratch)
    return Ranks(state.select("id", "rank"), log)


def rank_delta(g: Graph, eps: float = 1e-9, alpha: float = 0.85, max_iter: int = 200) -> Ranks:
    """Residual-driven: only changes above eps travel on. Within eps / (1 - alpha) a vertex of the fixed point."""
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "rank-delta")
    degree = g.degrees("out").where("degree > 0")
    edges = scratch.save(g.edges.join(degree.withColumnRenamed("id", "src"), "src").select("src", "dst", (F.lit(alpha) / F.col("degree")).alias("k")), "edges")
    n = g.vertices.count()
    state = scratch.save(g.vertices.select("id", F.lit(0.0).alias("rank"), F.lit((1 - alpha) / n).alias("residual")), "0")
    log: list[dict] = []
    for i in range(1, max_iter + 1):
        began = time.time()
        moving = state.where(F.abs("residual") > eps).select(F.col("id").alias("src"), "residual")
        got = edges.join(moving, "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("residual") * F.col("k")).alias("in"))
        settled = F.abs(F.col("residual")) > eps
        state = scratch.save(
            state.join(got, "id", "left").select("id", F.when(settled, F.col("rank") + F.col("residual")).otherwise(F.col("rank")).alias("rank"), (F.when(settled, 0.0).otherwise(F.col("residual")) + F.coalesce("in", F.lit(0.0))).alias("residual")),
            str(i),
        )
        scratch.drop(str(i - 1))
        left = state.where(F.abs("residual") > eps).count()
        log.append({"iter": i, "active": left, "seconds": time.time() - began})
        if not left:
            break
    else:
        raise RuntimeError(f"residuals stay above {eps} after {max_iter} iterations")
    return Ranks(state.select("id", (F.col("rank") + F.col("residual")).alias("rank")), log)


def top_k(ranks: DataFrame, k: int) -> DataFrame:
    """The k highest ranks; ties to smaller ids."""
    return ranks.orderBy(F.desc("rank"), "id").limit(k)
