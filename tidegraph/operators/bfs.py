"""Breadth-first search: sequential, level by level, and relaxed.

Every variant but claim="first" returns exact levels and, of the possible parents one level up, the
smallest. Results hold reached vertices; the root is its own parent.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from tidegraph.functions.adaptive import choose_blocks, small
from tidegraph.model import Graph, dense_ids, owner
from tidegraph.operators.oneprocess import in_one_task
from tidegraph.plans.scratch import Scratch

STATE = "id bigint, parent bigint, level int"
#: Bytes of a claim's columns.
CLAIM_BYTES = 20


@dataclass
class Traversal:
    """state: id, parent, level. log: a dict a round. load: round, blk, expanded, from searches by blocks.

    Of a relaxed round the log has: active (blocks), expanded (edges followed), remote (claims over crossing edges),
    combined (claims sent), accepted, rejected, corrections (levels lowered after a vertex had one), bytes, seconds.
    """

    state: DataFrame
    log: list[dict] = field(default_factory=list)
    load: DataFrame | None = None

    @property
    def rounds(self) -> int:
        return len(self.log)


def _seed(spark, root: int) -> DataFrame:
    return spark.createDataFrame([(root, root, 0)], STATE)


# -- one process -----------------------------------------------------------------------------------


def bfs_seq(src: np.ndarray, dst: np.ndarray, root: int, most: int = 50_000_000) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """ids, parents and levels of reached vertices by arrays in one process; refuses more than `most` edges."""
    if len(src) > most:
        raise ValueError(f"{len(src)} edges are too many for one process; use a distributed search")
    order = np.lexsort((dst, src))
    src, dst = src[order], dst[order]
    ids = np.unique(np.concatenate((src, dst, [root])))
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    first = np.searchsorted(s, np.arange(len(ids) + 1))
    parent, level = np.full(len(ids), -1), np.full(len(ids), -1)
    front = np.searchsorted(ids, [root])
    parent[front], level[front] = front, 0
    depth = 0
    while len(front):
        depth += 1
        count = first[front + 1] - first[front]
        at = np.repeat(first[front] - (np.cumsum(count) - count), count) + np.arange(count.sum())
        near, via = d[at], np.repeat(front, count)
        new = parent[near] < 0
        near, via = near[new], via[new]
        # ids ascend with positions, so the first of the sorted proposals has the smallest parent
        pick = np.lexsort((via, near))
        near, via = near[pick], via[pick]
        keep = np.concatenate(([True], near[1:] != near[:-1])) if len(near) else np.zeros(0, bool)
        front = near[keep]
        parent[front], level[front] = via[keep], depth
    got = level >= 0
    return ids[got], ids[parent[got]], level[got]


def bfs_sweep(src: np.ndarray, dst: np.ndarray, root: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """As bfs_seq, by a sweep over all edges for each level: no sorting, but the edges are read once a level."""
    ids = np.unique(np.concatenate((src, dst, [root])))
    s, d = np.searchsorted(ids, src), np.searchsorted(ids, dst)
    level, parent = np.full(len(ids), -1), np.full(len(ids), len(ids))
    at = np.searchsorted(ids, root)
    level[at], parent[at], depth, more = 0, at, 0, True
    while more:
        on = (level[s] == depth) & (level[d] < 0)
        np.minimum.at(parent, d[on], s[on])
        depth, more = depth + 1, bool(on.any())
        level[d[on]] = depth
    got = level >= 0
    return ids[got], ids[parent[got]], level[got]


def bfs_dropin(g: Graph, root: int) -> Traversal:
    """The sequential search over a distributed edge table: all of it in one task, which holds the vertices and keeps the
    edges in a file. An ablation only."""
    return Traversal(in_one_task(g.edges, lambda held: held.search(root), STATE, also=(root,)))


# -- level by level --------------------------------------------------------------------------------


def bfs_level(g: Graph, root: int, max_level: int | None = None, combine: bool = True, direction: str = "push", targets: DataFrame | None = None) -> Traversal:
    """One global step a level.

    Edges are bucketed by source and reached vertices by id, in as many buckets, with a folder a level that is only
    added to. A step therefore moves claims and nothing else: the frontier lies beside its edges (and is broadcast while
    its counted rows keep within the bound), what was reached beside the claims for it. combine=False sends one row an edge to
    the owner before any reduction. direction: push along out-edges, pull (unreached vertices look for
    a reached in-neighbour), or auto, which pulls while the frontier holds over a tenth of the vertices.
    Stops early when all targets (id) are reached.
    """
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfs")
    edges = g.edges.select("src", "dst")
    buckets = scratch.buckets(edges)
    edges = scratch.save_bucketed(edges, "edges", "src", n=buckets)
    state = scratch.save_bucketed(_seed(spark, root), "state", "id", n=buckets, folders=("level",))
    log, n, depth = [], 1, 0
    whole = g.vertices.count() if direction != "push" else 0
    while n and (max_level is None or depth < max_level):
        began = time.time()
        step = small(state.where(F.col("level") == depth).select(F.col("id").alias("src")), n)
        depth += 1
        seen = state.select(F.col("id").alias("dst"))
        pull = direction == "pull" or direction == "auto" and n * 10 > whole
        if pull:
            open_ = edges.join(seen, "dst", "left_anti")
            claims = open_.join(step, "src", "left_semi")
        else:
            claims = edges.join(step, "src")
        if not combine:
            claims = claims.repartition("dst")
        claims = claims.groupBy("dst").agg(F.min("src").alias("parent"))
        found = claims.join(seen, "dst", "left_anti").select(F.col("dst").alias("id"), "parent", F.lit(depth).alias("level"))
        state = scratch.save_bucketed(found, "state", "id", n=buckets, folders=("level",), placed=True, append=True)
        active, n = n, state.where(F.col("level") == depth).count()
        log.append({"round": depth, "active": active, "found": n, "seconds": time.time() - began})
        if targets is not None and targets.join(state, "id", "left_anti").isEmpty():
            break
    scratch.drop_table("edges")
    return Traversal(scratch.release("state", STATE), log)


def bfs_multi(g: Graph, roots: list[int], max_level: int | None = None) -> DataFrame:
    """root, id, parent, level for several distinct roots in one search.

    Reached pairs are bucketed by (root, id), so a level moves its frontier (or broadcasts it, if small) and its claims.
    """
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfs-multi")
    schema = f"root bigint, {STATE}"
    edges = g.edges.select("src", "dst")
    buckets = scratch.buckets(edges)
    edges = scratch.save_bucketed(edges, "edges", "src", n=buckets)
    seeds = [(r, r, r, 0) for r in dict.fromkeys(roots)]
    state = scratch.save_bucketed(spark.createDataFrame(seeds, schema), "state", ("root", "id"), n=buckets, folders=("level",))
    n, depth = len(seeds), 0
    while n and (max_level is None or depth < max_level):
        front = small(state.where(F.col("level") == depth).select("root", F.col("id").alias("src")), n)
        depth += 1
        claims = edges.join(front, "src").groupBy("root", F.col("dst").alias("id")).agg(F.min("src").alias("parent"))
        found = claims.join(state.select("root", "id"), ["root", "id"], "left_anti").select("root", "id", "parent", F.lit(depth).alias("level"))
        state = scratch.save_bucketed(found, "state", ("root", "id"), n=buckets, folders=("level",), placed=True, append=True)
        n = state.where(F.col("level") == depth).count()
    scratch.drop_table("edges")
    return scratch.release("state", schema)


# -- claims ----------------------------------------------------------------------------------------


def reduce_claims(claims: DataFrame, state: DataFrame, mode: str = "min_level") -> DataFrame:
    """Of many claims (id, parent, level) for a vertex, the one that replaces its state, if any does.

    min_level: the smallest level, then the smallest parent, if better than the state. first: the same
    choice among this round's claims, but only for vertices without state. A keyed reduction stands
    for an atomic update: it may be run again, or in two places, with the same outcome.
    """
    best = claims.groupBy("id").agg(F.min(F.struct("level", "parent")).alias("c")).select("id", "c.parent", "c.level")
    if mode == "first":
        return best.join(state.select("id"), "id", "left_anti")
    if mode != "min_level":
        raise ValueError(f"no claim mode {mode!r}")
    old = state.select("id", F.col("level").alias("old_level"), F.col("parent").alias("old_parent"))
    better = F.expr("old_level is null or level < old_level or (level = old_level and parent < old_parent)")
    return best.join(old, "id", "left").where(better).select("id", "parent", "level")


# -- relaxed ---------------------------------------------------------------------------------------

#: Rows that a block gives out. state: changed tells whether this round changed it (n). claim: n is the block it goes
#: to. count: id 0 edges followed, 1 corrections, 2 claims before combining (n).
_OUT = "kind string, blk int, id bigint, parent bigint, level int, n bigint"
_FAR = np.iinfo(np.int32).max


def _first_of(*keys: np.ndarray) -> np.ndarray:
    """Positions of rows sorted by the last key, then those before it; of rows that share the last key, the first."""
    order = np.lexsort(keys)
    last = keys[-1][order]
    return order[np.concatenate(([True], last[1:] != last[:-1]))] if len(order) else order


def drain(known: dict[str, np.ndarray], src: np.ndarray, dst: np.ndarray, dblk: np.ndarray, blk: int, first_only: bool = False, combine: bool = True) -> dict[str, np.ndarray]:
    """A block follows its own edges until nothing changes.

    known: id, parent, level, fresh (an accepted claim, not yet state). Only a lower level counts (with first_only, any
    level of a vertex without one). Levels are worked off in ascending order, so claims of unequal level cost no needless
    correction. Returns all state, what changed, and claims that leave: of those for one vertex the best one, with combine.
    """
    local = dblk == blk
    ids = np.unique(np.concatenate((known["id"], src, dst[local])))
    n = len(ids)
    level, parent = np.full(n, _FAR), np.full(n, -1)
    old = ~known["fresh"]
    at = np.searchsorted(ids, known["id"][old])
    level[at], parent[at] = known["level"][old], known["parent"][old]
    order = np.argsort(src, kind="stable")
    src, dst, dblk, local = src[order], dst[order], dblk[order], local[order]
    inner = np.where(local, np.searchsorted(ids, dst), -1)
    first = np.searchsorted(src, ids, side="left")
    last = np.searchsorted(src, ids, side="right")
    changed, queued = np.zeros(n, bool), np.zeros(n, bool)
    sent = []
    expanded = corrections = remote = 0

    def offer(where: np.ndarray, by: np.ndarray, to: np.ndarray) -> None:
        nonlocal corrections
        better = (level[where] == _FAR) if first_only else (to < level[where])
        where, by, to = where[better], by[better], to[better]
        pick = _first_of(by, to, where)
        where = where[pick]
        corrections += int((level[where] != _FAR).sum())
        queued[where] = changed[where] = True
        level[where], parent[where] = to[pick], by[pick]

    new = known["fresh"]
    offer(np.searchsorted(ids, known["id"][new]), known["parent"][new], known["level"][new])
    while queued.any():
        now = level[queued].min()
        front = np.flatnonzero(queued & (level == now))
        queued[front] = False
        count = last[front] - first[front]
        expanded += int(count.sum())
        edge = np.repeat(first[front] - (np.cumsum(count) - count), count) + np.arange(count.sum())
        via = ids[np.repeat(front, count)]
        inside = local[edge]
        offer(inner[edge[inside]], via[inside], np.full(int(inside.sum()), now + 1))
        away = edge[~inside]
        remote += len(away)
        sent.append((dst[away], via[~inside], np.full(len(away), now + 1), dblk[away]))
    none = np.zeros(0, np.int64)
    out = [np.concatenate([none, *x]) for x in zip(*sent, strict=True)] if sent else [none] * 4
    if combine:
        pick = _first_of(out[1], out[2], out[0])
        out = [x[pick] for x in out]
    got = np.flatnonzero(level != _FAR)
    return {
        "id": ids[got], "parent": parent[got], "level": level[got], "changed": changed[got],
        "out_id": out[0], "out_parent": out[1], "out_level": out[2], "out_blk": out[3], "counts": np.array([expanded, corrections, remote]),
    }


def _closing(known: dict[str, np.ndarray], src: np.ndarray, dst: np.ndarray) -> dict[str, np.ndarray]:
    """For each target of a block's reached vertices, the smallest (level + 1, source): the smallest of these over all
    blocks is the target's level and its smallest parent."""
    at = np.minimum(np.searchsorted(known["id"], src), max(len(known["id"]) - 1, 0))
    use = known["id"][at] == src if len(known["id"]) else np.zeros(len(src), bool)
    src, dst, level = src[use], dst[use], known["level"][at[use]] + 1
    pick = _first_of(src, level, dst)
    return {"id": dst[pick], "parent": src[pick], "level": level[pick]}


def _columns(kind: list[str], sizes: list[int], blk: int, *columns: np.ndarray) -> pa.Table:
    types = pa.int64(), pa.int64(), pa.int32(), pa.int64()
    arrays = [pa.array(c.astype(t.to_pandas_dtype()), t) for c, t in zip(columns, types, strict=True)]
    return pa.table([pa.array(np.repeat(kind, sizes).tolist(), pa.string()), pa.array(np.full(sum(sizes), blk, np.int32)), *arrays], names=["kind", "blk", "id", "parent", "level", "n"])


def bfs_relaxed(
    g: Graph, root: int, how: str = "hash", blocks: int | None = None, n: int | None = None, claim: str = "min_level", combine: bool = True, max_rounds: int = 10_000, block_edges: int = 1 << 24, hub_edges: int | None = None
) -> Traversal:
    """Blocks follow their own edges to exhaustion; only claims that cross blocks wait for a global step.

    Edges and states lie in tables bucketed by owning block. A round reads the blocks that accepted a claim, with their
    edges and last state, and writes their new state; then claims go to their owners' buckets, the round's one
    exchange, where those that are not better than the state are dropped. Parents come from one pass at the end.
    blocks follows from the number of edges, and is doubled while one block holds over twice block_edges. Vertices of more
    than hub_edges (a quarter of block_edges) out-edges are not followed inside blocks: a join sends their claims after the
    round, so no hub fills a block. how="block" needs dense ids and n. Raises after max_rounds without an end.
    """
    if claim not in ("min_level", "first"):
        raise ValueError(f"no claim mode {claim!r}")
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfs-relaxed")
    first_only, hub_edges = claim == "first", hub_edges or block_edges // 4
    edges = g.edges.select("src", "dst")
    degrees = edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    m, widest = degrees.agg(F.coalesce(F.sum("d"), F.lit(0)), F.coalesce(F.max("d"), F.lit(0))).first()
    hubs = None
    if widest > hub_edges:
        # fewer than m / hub_edges rows
        hubs = scratch.save(degrees.where(F.col("d") > hub_edges).select("src"), "hubs")
        rows = hubs.count()
        hubs_side = small(hubs, rows)
        hub_out = scratch.save(edges.join(hubs_side, "src", "left_semi"), "hub-edges")
        edges = edges.join(hubs_side, "src", "left_anti")
    blocks = blocks or choose_blocks(m, spark.sparkContext.defaultParallelism, block_edges)
    while m > 2 * block_edges and edges.groupBy(owner(F.col("src"), how, blocks, n)).count().agg(F.max("count")).first()[0] > 2 * block_edges:
        blocks *= 2
    buckets = min(blocks, 1 << 13)
    mine = owner(F.col("id"), how, blocks, n).alias("blk")
    cut = edges.withColumn("blk", owner(F.col("src"), how, blocks, n)).withColumn("dblk", owner(F.col("dst"), how, blocks, n))
    edges = scratch.save_bucketed(cut, "edges", "blk", n=buckets, sort=("src",))

    def one(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        blk = key[0].as_py()
        known = {k: left[k].to_numpy() for k in ("id", "parent", "level")} | {"fresh": left["fresh"].to_numpy(zero_copy_only=False).astype(bool)}
        if not known["fresh"].any():  # no claim came
            return _columns(["state"], [0], blk, *[np.zeros(0)] * 4)
        got = drain(known, right["src"].to_numpy(), right["dst"].to_numpy(), right["dblk"].to_numpy(), blk, first_only, combine)
        sizes = [len(got["id"]), len(got["out_id"]), 3]
        none = np.zeros(3, np.int64)
        join = lambda a, b, c: np.concatenate([got[a] if a else none, got[b], c])
        return _columns(["state", "claim", "count"], sizes, blk, join("id", "out_id", np.arange(3)), join("parent", "out_parent", none), join("level", "out_level", none), join("changed", "out_blk", got["counts"]))

    def close(key: tuple, left: pa.Table, right: pa.Table) -> pa.Table:
        order = np.argsort(left["id"].to_numpy())
        got = _closing({"id": left["id"].to_numpy()[order], "level": left["level"].to_numpy()[order].astype(np.int64)}, right["src"].to_numpy(), right["dst"].to_numpy())
        return pa.table({"id": pa.array(got["id"], pa.int64()), "parent": pa.array(got["parent"], pa.int64()), "level": pa.array(got["level"].astype(np.int32), pa.int32())})

    rounds: list[DataFrame] = []
    version: dict[int, int] = {}  # the round that wrote a block's last state

    def state(of: list[int] | None = None) -> list[DataFrame]:
        """blk, id, parent, level, n of the blocks: a part for each round that wrote any of them."""
        by: dict[int, list[int]] = {}
        for b in sorted(version) if of is None else of:
            if b in version:
                by.setdefault(version[b], []).append(b)
        return [rounds[v].where("kind = 'state'").where(F.col("blk").isin(bs)).select("blk", "id", "parent", "level", "n") for v, bs in by.items()]

    def union(parts: list[DataFrame]) -> DataFrame:
        return reduce(DataFrame.unionByName, parts)

    accepted = _seed(spark, root).select(mine, "id", "parent", "level").repartition(buckets, "blk")
    active = [x[0] for x in accepted.select("blk").collect()]  # the root's block
    log: list[dict] = []
    while active:
        if len(log) == max_rounds:
            raise RuntimeError(f"claims still come after {max_rounds} rounds")
        began, r = time.time(), len(log) + 1
        old = [x.select("blk", "id", "parent", "level", F.lit(False).alias("fresh")) for x in state(active)]
        left = union([accepted.select("blk", "id", "parent", "level", F.lit(True).alias("fresh")), *old])
        right = edges.where(F.col("blk").isin(active))
        seen, total = Observation(f"round-{r}"), lambda x: F.coalesce(F.sum(F.expr(x)), F.lit(0))
        # observed while the table is written: counts, and the blocks that claims go to (no more numbers than blocks)
        out = left.groupBy("blk").cogroup(right.groupBy("blk")).applyInArrow(one, _OUT).observe(
            seen, *(total(f"if(kind = 'count' and id = {i}, n, 0)").alias(c) for i, c in enumerate(("expanded", "corrections", "remote"))),
            total("if(kind = 'claim', 1, 0)").alias("sent"), F.expr("array_join(collect_set(if(kind = 'claim', cast(n as string), null)), ',')").alias("to"),
        )
        out = scratch.save_bucketed(out, f"round-{r}", "blk", n=buckets, folders=("kind",), placed=True)
        rounds.append(out)
        version.update(dict.fromkeys(active, r - 1))
        counts = seen.get
        to, rows_sent = {int(x) for x in counts["to"].split(",") if x}, counts["sent"]
        claims = out.where("kind = 'claim'").select(F.col("n").cast("int").alias("blk"), "id", "parent", "level")
        if hubs is not None:
            moved = small(out.where("kind = 'state' and n = 1").select(F.col("id").alias("src"), "level").join(hubs_side, "src"), rows)
            sent = hub_out.join(moved, "src").select(F.col("dst").alias("id"), F.col("src").alias("parent"), F.col("level") + 1)
            sent = scratch.save(sent.toDF("id", "parent", "level").groupBy("id").agg(F.min(F.struct("level", "parent")).alias("c")).select(mine, "id", "c.parent", "c.level"), f"hubs-{r}")
            extra = {x[0]: x[1] for x in sent.groupBy("blk").count().collect()}
            to, rows_sent = to | set(extra), rows_sent + sum(extra.values())
            claims = claims.unionByName(sent)
        now, active, taken = len(active), [], 0
        if to:
            # claims move to their owners' buckets, where the states already are
            fresh = claims.repartition(buckets, "blk").select("blk", "id", F.struct("level", "parent").alias("c"), F.lit(None).cast("int").alias("old"))
            held = [x.select("blk", "id", F.lit(None).cast("struct<level:int,parent:bigint>").alias("c"), F.col("level").alias("old")) for x in state(sorted(to))]
            best = union([fresh, *held]).groupBy("blk", "id").agg(F.min("c").alias("c"), F.min("old").alias("old"))
            best = best.where("c is not null and old is null" if first_only else "c is not null and (old is null or c.level < old)").select("blk", "id", "c.parent", "c.level")
            seen = Observation(f"claims-{r}")
            best = best.observe(seen, F.count(F.lit(1)).alias("taken"), F.expr("array_join(collect_set(cast(blk as string)), ',')").alias("blocks"))
            accepted = scratch.save_bucketed(best, f"claims-{r}", "blk", n=buckets, placed=True)
            active, taken = sorted(int(x) for x in seen.get["blocks"].split(",") if x), seen.get["taken"]
        log.append({"round": r, "active": now, "expanded": counts["expanded"], "remote": counts["remote"], "combined": rows_sent, "accepted": taken, "rejected": rows_sent - taken, "corrections": counts["corrections"], "bytes": rows_sent * CLAIM_BYTES, "seconds": time.time() - began})
    if first_only:
        found = union(state()).select("id", "parent", "level")
    else:
        known = union([x.select("blk", "id", "level") for x in state()])
        ways = known.groupBy("blk").cogroup(edges.groupBy("blk")).applyInArrow(close, STATE)
        if hubs is not None:
            at_hubs = small(known.join(hubs_side, F.col("id") == F.col("src"), "left_semi").select(F.col("id").alias("src"), "level"), rows)
            ways = ways.unionByName(hub_out.join(at_hubs, "src").select(F.col("dst").alias("id"), F.col("src").alias("parent"), (F.col("level") + 1).alias("level")))
        best = ways.where(F.col("id") != F.lit(root)).groupBy("id").agg(F.min(F.struct("level", "parent")).alias("c")).select("id", "c.parent", "c.level")
        found = best.unionByName(_seed(spark, root))
    found = scratch.save(found, "state")
    load = scratch.save(union([x.where("kind = 'count' and id = 0").select(F.lit(i + 1).alias("round"), "blk", F.col("n").alias("expanded")) for i, x in enumerate(rounds)]), "load")
    scratch.keep_only("state", "load")
    return Traversal(found, log, load)


def smallest_parents(g: Graph, state: DataFrame) -> DataFrame:
    """Of all edges from one level to the next, the smallest source; state: id, level."""
    up = state.select(F.col("id").alias("src"), F.col("level").alias("up"))
    down = state.select(F.col("id").alias("dst"), F.col("level"))
    found = g.edges.select("src", "dst").join(up, "src").join(down, "dst").where("up + 1 = level").groupBy(F.col("dst").alias("id"), "level").agg(F.min("src").alias("parent"))
    return found.select("id", "parent", "level").unionByName(state.where("level = 0").select("id", F.col("id").alias("parent"), "level"))


def bfs_hops(g: Graph, root: int, hops: int = 2, how: str = "hash", blocks: int = 8, n: int | None = None) -> Traversal:
    """Relaxed search in joins alone: up to `hops` steps along edges inside blocks for each step between blocks."""
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfs-hops")
    cut = scratch.save(g.edges.select("src", "dst").withColumn("inside", owner(F.col("src"), how, blocks, n) == owner(F.col("dst"), how, blocks, n)), "edges")
    inside, between = cut.where("inside").select("src", "dst"), cut.where("not inside").select("src", "dst")

    def follow(front: DataFrame, edges: DataFrame) -> DataFrame:
        return front.join(edges, front["id"] == edges["src"]).groupBy(F.col("dst").alias("id")).agg(F.min(F.col("level") + 1).alias("level"))

    claims = scratch.save(spark.createDataFrame([(root, 0)], "id bigint, level int"), "claims-0")
    state = scratch.save(claims.limit(0), "state-0")
    log: list[dict] = []
    while True:
        began = time.time()
        r = len(log) + 1
        now, reached = claims, claims
        for _ in range(hops):
            now = follow(now, inside)
            reached = reached.unionByName(now)
        best = reached.groupBy("id").agg(F.min("level").alias("level"))
        better = best.join(state.withColumnRenamed("level", "old"), "id", "left").where("old is null or level < old").select("id", "level")
        better = scratch.save(better, f"better-{r}")
        count = better.count()
        log.append({"round": r, "combined": count, "seconds": time.time() - began})
        if not count:
            break
        state = scratch.save(state.unionByName(better).groupBy("id").agg(F.min("level").alias("level")), f"state-{r}")
        # what was reached by the last step inside has not been followed inside yet
        tip = better.join(now.select("id", F.col("level").alias("tip")), "id").where("tip = level").select("id", "level")
        sent = follow(better, between).unionByName(follow(tip, inside)).groupBy("id").agg(F.min("level").alias("level"))
        claims = scratch.save(sent.join(state.withColumnRenamed("level", "old"), "id", "left").where("old is null or level < old").select("id", "level"), f"claims-{r}")
        if claims.isEmpty():
            break
    return Traversal(smallest_parents(g, state), log)


# -- supersteps ------------------------------------------------------------------------------------


def superstep(state: DataFrame, messages, combine, apply, until, scratch: Scratch, most: int = 100_000) -> tuple[DataFrame, list[dict]]:
    """The vertex-centric loop: messages(state) are combined by id and applied to the state until nothing is active.

    state holds id and active; combine takes grouped messages; apply(state, combined) gives the next state.
    """
    state = scratch.save(state, "state-0")
    log: list[dict] = []
    for r in range(1, most + 1):
        began = time.time()
        state = scratch.save(apply(state, combine(messages(state.where("active")).groupBy("id"))), f"state-{r}")
        scratch.drop(f"state-{r - 1}")
        active = state.where("active").count()
        log.append({"round": r, "active": active, "seconds": time.time() - began})
        if until(active, r):
            return state, log
    raise RuntimeError(f"vertices are still active after {most} rounds")


def bfs_vertex(g: Graph, root: int) -> Traversal:
    """Vertex-centric: active vertices tell their out-neighbours; a vertex takes the smallest teller once."""
    spark = g.edges.sparkSession
    start = g.vertices.unionByName(spark.createDataFrame([(root,)], "id bigint")).distinct()
    start = start.select("id", F.expr(f"if(id = {root}, id, null)").alias("parent"), F.expr(f"if(id = {root}, 0, null)").alias("level"), (F.col("id") == root).alias("active"))

    def tell(active: DataFrame) -> DataFrame:
        return active.join(g.edges, active["id"] == g.edges["src"]).select(F.col("dst").alias("id"), F.col("src").alias("by"), (F.col("level") + 1).alias("to"))

    def take(state: DataFrame, told: DataFrame) -> DataFrame:
        new = F.expr("level is null and to is not null")
        return state.join(told, "id", "left").select("id", F.when(new, F.col("by")).otherwise(F.col("parent")).alias("parent"), F.when(new, F.col("to")).otherwise(F.col("level")).alias("level"), new.alias("active"))

    state, log = superstep(start, tell, lambda m: m.agg(F.min("by").alias("by"), F.min("to").alias("to")), take, lambda active, r: not active, Scratch(spark, "bfs-vertex"))
    return Traversal(state.where("level is not null").select("id", "parent", "level"), log)


#: add and multiply of the semirings, over columns.
SEMIRINGS = {
    "or_and": (lambda x: F.max(x), lambda v, w: v),
    "plus_times": (lambda x: F.sum(x), lambda v, w: v * w),
    "min_plus": (lambda x: F.min(x), lambda v, w: v + w),
}


def semiring_spmv(edges: DataFrame, vector: DataFrame, ring: str = "plus_times") -> DataFrame:
    """id, value: the vector (id, value) times the matrix of edges (src, dst, w), over a semiring."""
    add, multiply = SEMIRINGS[ring]
    joined = edges.join(vector.withColumnRenamed("id", "src"), "src")
    return joined.groupBy(F.col("dst").alias("id")).agg(add(multiply(F.col("value"), F.col("w"))).alias("value"))


def spmv_bfs(g: Graph, root: int) -> Traversal:
    """Levels by products of the frontier vector with the matrix, masked by what was seen, which lies beside the matrix."""
    spark = g.edges.sparkSession
    scratch = Scratch(spark, "bfs-spmv")
    edges = g.edges.select("src", "dst", F.lit(1).alias("w"))
    buckets = scratch.buckets(edges)
    edges = scratch.save_bucketed(edges, "edges", "src", n=buckets)
    state = scratch.save_bucketed(spark.createDataFrame([(root, 0)], "id bigint, level int"), "state", "id", n=buckets, folders=("level",))
    n, depth = 1, 0
    while n:
        front = small(state.where(F.col("level") == depth).select("id", F.lit(1).alias("value")), n)
        depth += 1
        found = semiring_spmv(edges, front, "or_and").join(state.select("id"), "id", "left_anti").select("id", F.lit(depth).alias("level"))
        state = scratch.save_bucketed(found, "state", "id", n=buckets, folders=("level",), placed=True, append=True)
        n = state.where(F.col("level") == depth).count()
    scratch.drop_table("edges")
    return Traversal(smallest_parents(g, scratch.release("state", "id bigint, level int")), [{"round": i} for i in range(1, depth + 1)])


# -- views and by-products -------------------------------------------------------------------------


def bfs_range(g: Graph, root: int, what: str = "vertices") -> DataFrame:
    """ord, id, parent, level in level order, ids ascending within a level; edges leaves the root out.

    Ranges of (level, id) are numbered apart, so no task holds a whole level.
    """
    state = bfs_level(g, root).state
    out = dense_ids(state.select(F.struct("level", "id", "parent").alias("at")), "at").select(F.col("id").alias("ord"), "at.id", "at.parent", "at.level")
    return out.where("level > 0") if what == "edges" else out


def reachable(g: Graph, root: int) -> DataFrame:
    return bfs_level(g, root).state.select("id")


def unreached(g: Graph, root: int) -> DataFrame:
    return g.vertices.join(reachable(g, root), "id", "left_anti")


def as_sentinel(g: Graph, state: DataFrame) -> DataFrame:
    """Every vertex, with -1 for the parent and level of unreached ones."""
    return g.vertices.join(state, "id", "left").select("id", F.coalesce("parent", F.lit(-1)).alias("parent"), F.coalesce("level", F.lit(-1)).alias("level"))


def path_to(state: DataFrame, ids: DataFrame) -> DataFrame:
    """id, step, vertex: from each id (step 0) along parents to the root; one join a step."""
    spark = state.sparkSession
    scratch = Scratch(spark, "paths")
    parents = state.select(F.col("id").alias("vertex"), "parent")
    now = scratch.save(ids.select("id").join(state.select("id"), "id").select("id", F.lit(0).alias("step"), F.col("id").alias("vertex")), "0")
    paths, step = [scratch.path("0")], 0
    while True:
        step += 1
        now = scratch.save(now.join(parents, "vertex").where("parent <> vertex").select("id", F.lit(step).alias("step"), F.col("parent").alias("vertex")), str(step))
        if now.isEmpty():
            break
        paths.append(scratch.path(str(step)))
    return spark.read.parquet(*paths)


def dfs_range(g: Graph, root: int, tree: bool = False, most: int = 20_000_000) -> DataFrame:
    """ord, id, parent, level in depth-first preorder, neighbours ascending.

    tree: each vertex's path of ids sorts the preorder, so no task holds the tree. Otherwise the order is
    inherently sequential, and the reachable part goes to one task if its edges keep within `most`.
    """
    from pyspark.sql.window import Window

    spark = g.edges.sparkSession
    if tree:
        state = bfs_level(g, root).state
        steps = path_to(state, state.select("id"))
        keyed = steps.groupBy("id").agg(F.transform(F.sort_array(F.collect_list(F.struct((-F.col("step")).alias("s"), "vertex"))), lambda x: x["vertex"]).alias("way"))
        joined = keyed.join(state, "id")
        n = int(spark.conf.get("spark.sql.shuffle.partitions"))
        scratch = Scratch(spark, "dfs")
        ranged = scratch.save(joined.repartitionByRange(n, "way").withColumn("part", F.spark_partition_id()), "ranges")
        sizes = ranged.groupBy("part").agg(F.count(F.lit(1)).alias("n"))
        before = sizes.select("part", F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
        r = F.row_number().over(Window.partitionBy("part").orderBy("way"))
        return ranged.withColumn("r", r).join(F.broadcast(before), "part").select((F.col("before") + F.col("r") - 1).cast("bigint").alias("ord"), "id", "parent", "level")
    part = g.edges.select("src", "dst").join(reachable(g, root).withColumnRenamed("id", "src"), "src", "left_semi")
    if part.count() > most:
        raise ValueError("the reachable part is too large for one task; depth-first order is sequential")

    def one(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near: dict[int, list[int]] = {}
        for batch in batches:
            for s, d in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                near.setdefault(s, []).append(d)
        rows, seen = [], {root}
        rows.append((root, root, 0))
        walk = [(root, 0, iter(sorted(near.get(root, []))))]
        while walk:
            at, depth, rest = walk[-1]
            for d in rest:
                if d not in seen:
                    seen.add(d)
                    rows.append((d, at, depth + 1))
                    walk.append((d, depth + 1, iter(sorted(near.get(d, [])))))
                    break
            else:
                walk.pop()
        columns = list(zip(*rows, strict=True))
        yield pa.RecordBatch.from_arrays([pa.array(range(len(rows)), pa.int64()), pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int32())], names=["ord", "id", "parent", "level"])

    return part.coalesce(1).mapInArrow(one, f"ord bigint, {STATE}")
